"""Quality rules: an isolation forest on rule statistics.

Random axis splits isolate odd documents after few splits; the mean path length over trees gives a score in
(0, 1). Trees are grown on a bounded hash sample of the statistics, the score of every document is computed,
and the threshold is calibrated on all labelled rows from a histogram of their scores.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.llm.common import hash_sample, materialise, text_parts, text_slices, words_of
from veilgrid.llm.text_stats import COUNTS, FEATURES, rule_counts, rule_features

TREES = 100
SUBSAMPLE = 256
#: Rows of the sample from which every tree draws its own subsample.
SAMPLE_ROWS = 10_000
#: Share of good labelled documents (among those that pass the base rules) that the threshold may reject.
MAX_GOOD_REJECTED = 0.005
BINS = 2000
#: Features that the forest splits on. With all ten, cuts are wasted on what varies among good documents: a cut that costs 0.5 % of
#: good labelled rows then rejects a fifth of the bad ones instead of nearly all (README).
SPLIT_ON = [FEATURES.index(f) for f in ("symbols_per_word", "upper_share", "marks_per_word", "mean_word_chars")]
DEFAULT_THRESHOLD = 0.65


@dataclass(frozen=True)
class Forest:
    """Trees as flat arrays: feature (-1 at a leaf), cut, left child (the right one is next), adjusted depth."""

    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    depth: np.ndarray
    norm: float

    def score(self, x: np.ndarray) -> np.ndarray:
        """Anomaly score of each row: 2^(-mean path / expected path)."""
        total = np.zeros(len(x))
        rows = np.arange(len(x))
        for t in range(len(self.feature)):
            node = np.zeros(len(x), dtype=np.int64)
            while True:
                f = self.feature[t][node]
                inner = f >= 0
                if not inner.any():
                    break
                step = self.left[t][node] + (x[rows, np.maximum(f, 0)] >= self.cut[t][node])
                node = np.where(inner, step, node)
            total += self.depth[t][node]
        return np.exp2(-total / len(self.feature) / self.norm) if self.norm else np.full(len(x), 0.5)


def _expected_path(n: int) -> float:
    """Mean depth of an unsuccessful search in a random binary tree of n rows."""
    return 0.0 if n <= 1 else 1.0 if n == 2 else 2 * (np.log(n - 1) + np.euler_gamma) - 2 * (n - 1) / n


def grow_forest(sample: np.ndarray, trees: int = TREES, subsample: int = SUBSAMPLE, seed: int = 7) -> Forest:
    rng = np.random.default_rng(seed)
    size = min(subsample, len(sample))
    limit = int(np.ceil(np.log2(max(size, 2))))
    grown = []
    for _ in range(trees):
        nodes: list[list[float]] = [[-1, 0.0, 0, 0.0]]
        work = [(0, sample[rng.choice(len(sample), size, replace=False)] if size else sample, 0)]
        while work:
            at, x, depth = work.pop()
            spread = np.flatnonzero(x.max(axis=0) > x.min(axis=0)) if len(x) > 1 else []
            if depth >= limit or not len(spread):
                nodes[at][3] = depth + _expected_path(len(x))
                continue
            f = int(rng.choice(spread))
            low, high = x[:, f].min(), x[:, f].max()
            cut = rng.uniform(low, high)
            cut = cut if cut > low else high
            nodes[at] = [f, cut, len(nodes), 0.0]
            right = x[:, f] >= cut
            work += [(len(nodes), x[~right], depth + 1), (len(nodes) + 1, x[right], depth + 1)]
            nodes += [[-1, 0.0, 0, 0.0], [-1, 0.0, 0, 0.0]]
        grown.append(nodes)
    width = max(map(len, grown))
    table = np.array([g + [[-1, 0.0, 0, 0.0]] * (width - len(g)) for g in grown])
    return Forest(table[..., 0].astype(np.int64), table[..., 1], table[..., 2].astype(np.int64), table[..., 3], _expected_path(size))


def _scaled(features: np.ndarray) -> np.ndarray:
    """Random cuts are uniform over a range: logarithms keep one extreme value from taking all cuts."""
    return np.log1p(np.maximum(features[:, SPLIT_ON], 0) * 10)


STATS_SCHEMA = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS) + ", features array<double>"


def rule_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of counts and scale-free features per document, over whole texts."""
    names = ["doc_id", *COUNTS, "features"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in text_slices(batches):
            counts, features = [], []
            for text in texts:
                words = words_of(text)
                counts.append(rule_counts(text, words))
                features.append(rule_features(text, words, counts[-1]))
            columns = [arrow for arrow in (pa.array(c, type=pa.int64()) for c in zip(*counts, strict=True))]
            yield pa.RecordBatch.from_arrays([part.column(0), *columns, pa.array(features, type=pa.list_(pa.float64()))], names=names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, STATS_SCHEMA)


def base_failed():
    """The plain rules: too short, or mostly repeated 3-word windows."""
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


@dataclass(frozen=True)
class RuleModel:
    forest: Forest
    threshold: float


def _score_stats(stats: DataFrame, forest: Forest) -> DataFrame:
    @F.pandas_udf("double")
    def score(features):
        return features.__class__(forest.score(_scaled(np.stack(features.to_numpy())))) if len(features) else features.astype(float)

    return stats.withColumn("anomaly", score("features"))


def fit_rules(stats: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, max_good_rejected: float = MAX_GOOD_REJECTED) -> tuple[RuleModel, DataFrame]:
    """Forest from a bounded hash sample of the statistics; threshold from all labelled rows (doc_id, quality).

    Among cuts that reject at most ``max_good_rejected`` of the good labelled rows, the one that rejects most bad rows
    is taken (the highest of those that tie). Without labelled rows of both kinds the default threshold holds.
    """
    passed = stats.where(~base_failed())
    sample = hash_sample(passed, sample_rows, "doc_id", "n_words", "word_chars")
    rows = [r.features for r in sample.select("features").collect()]
    forest = grow_forest(_scaled(np.array(rows, dtype=float).reshape(-1, len(FEATURES))))
    scored = materialise(_score_stats(stats, forest))
    judged = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull()).groupBy("doc_id").agg(F.max("quality").alias("quality"))
    marked = scored.where(~base_failed()).select("doc_id", "anomaly").join(judged, "doc_id")
    bins = marked.groupBy(F.floor(F.col("anomaly") * BINS).cast("int").alias("bin"), (F.col("quality") == 1).alias("good")).count().collect()
    good, bad = np.zeros(BINS + 1), np.zeros(BINS + 1)
    for r in bins:
        (good if r.good else bad)[r.bin] += r["count"]
    if not good.sum() or not bad.sum():
        return RuleModel(forest, DEFAULT_THRESHOLD), scored
    good_over, bad_over = np.cumsum(good[::-1])[::-1], np.cumsum(bad[::-1])[::-1]
    allowed = np.flatnonzero(good_over <= max_good_rejected * good.sum())
    best = allowed[bad_over[allowed] == bad_over[allowed].max()].max()
    return RuleModel(forest, best / BINS), scored


def apply_rules(scored: DataFrame, model: RuleModel) -> DataFrame:
    failed = base_failed()
    return scored.select("doc_id", *COUNTS, failed.alias("base_failed"), (~failed & (F.col("anomaly") < model.threshold)).alias("kept"), "anomaly")


def quality_rules(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, counts, base_failed, kept, anomaly), one row per input row.

    Null and blank texts have zero words and fail the base rules; a null doc_id is judged but has no label;
    repeated rows are judged alike; an empty table gives no rows; other columns are not read.
    """
    model, scored = fit_rules(materialise(rule_statistics(docs, id_col, text_col)), labels)
    return apply_rules(scored, model)


def keep_good_rows(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that the rules keep, all columns unchanged.

    Texts never leave their partition. Their statistics are computed a second time: keeping them beside the texts would write the
    whole corpus once more.
    """
    model, _ = fit_rules(materialise(rule_statistics(docs, id_col, text_col)), labels)

    @F.arrow_udf("boolean")
    def good(texts: pa.Array) -> pa.Array:
        out = []
        for part in text_parts(texts):
            words = [words_of(t) for t in part]
            counts = [rule_counts(t, w) for t, w in zip(part, words, strict=True)]
            features = [rule_features(t, w, c) for t, w, c in zip(part, words, counts, strict=True)]
            fine = model.forest.score(_scaled(np.array(features))) < model.threshold
            out += [bool(f) and c[0] >= 50 and 100 * c[4] <= 50 * c[0] for f, c in zip(fine, counts, strict=True)]
        return pa.array(out, type=pa.bool_())

    return docs.where(good(F.col(text_col)))
