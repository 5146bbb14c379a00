"""Quality classifier by positive-unlabelled learning.

A linear model on text features minimises the non-negative unbiased risk: trusted positives, unlabelled web text
and a class prior stand in for negatives. The unlabelled part of the risk that positives explain is taken off it,
and where that difference would turn negative the step goes the other way, which keeps the model from fitting the sample.

The prior is estimated from the same two samples, with no look at any label of a negative: a model that tells
positives from unlabelled text ranks the texts of the other half, and among its top texts, where next to no negatives are, the
unlabelled share over the positive share is the prior.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.llm.common import hash_sample, id_remainder, materialise, text_parts, text_slices, words_of
from veilgrid.llm.text_stats import FEATURES, rule_counts, rule_features

#: Hashed byte-pair buckets beside the rule features.
BUCKETS = 256
WIDTH = BUCKETS + 2 * len(FEATURES) + 1
#: Sizes of the two training samples, in distinct ids.
POSITIVES = 6_000
UNLABELLED = 6_000
EPOCHS = 60
BATCH = 500
_CLASS = np.arange(256)
_CLASS[ord("A") : ord("Z") + 1] = ord("A")
_CLASS[ord("0") : ord("9") + 1] = ord("0")
_CLASS[128:] = 128


def text_vector(text: str | None) -> np.ndarray:
    """Features of one whole text: rule features, their logarithms, the length's logarithm, and square roots of hashed byte-pair shares."""
    out = np.zeros(WIDTH, dtype=np.float32)
    words = words_of(text)
    if not words:
        return out
    rules = np.array(rule_features(text, words, rule_counts(text, words)))
    k = len(FEATURES)
    out[:k], out[k : 2 * k], out[2 * k] = rules, np.log(rules + 0.01), np.log1p(len(words))
    data = np.frombuffer(text.encode("utf-8"), dtype=np.uint8)
    pairs = np.zeros(BUCKETS, dtype=np.int64)
    for at in range(0, max(1, len(data) - 1), 1 << 20):
        b = _CLASS[data[at : at + (1 << 20) + 1]]
        pairs += np.bincount(((b[:-1] * 131 + b[1:]) * 40503 >> 4) % BUCKETS, minlength=BUCKETS)
    out[2 * k + 1 :] = np.sqrt(pairs / max(1, len(data) - 1))
    return out


@dataclass(frozen=True)
class LinearModel:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.clip(((x - self.mean) / self.scale).clip(-8, 8) @ self.weights + self.bias, -35, 35)
        return 1 / (1 + np.exp(-z))


def fit_pu(positive: np.ndarray, unlabelled: np.ndarray, prior: float, epochs: int = EPOCHS, batch: int = BATCH, decay: float = 1e-3, rate: float = 0.01, seed: int = 11) -> LinearModel:
    """Minimise prior * R+(positive) + max(0, R-(unlabelled) - prior * R-(positive)) with logistic loss."""
    width = positive.shape[1]
    if not len(positive) or not len(unlabelled):
        return LinearModel(np.zeros(width), np.ones(width), np.zeros(width), 1.0, prior)
    mean, scale = unlabelled.mean(axis=0), unlabelled.std(axis=0) + 1e-3
    p, u = (((x - mean) / scale).clip(-8, 8) for x in (positive, unlabelled))
    rng = np.random.default_rng(seed)
    w = np.zeros(width + 1)
    m, v, step = np.zeros_like(w), np.zeros_like(w), 0
    p, u = (np.hstack([x, np.ones((len(x), 1))]) for x in (p, u))
    rounds = max(1, len(u) // batch)
    for _ in range(epochs):
        pi, ui = rng.permutation(len(p)), rng.permutation(len(u))
        for k in range(rounds):
            xp, xu = p[pi[k::rounds]] if len(p) >= rounds else p, u[ui[k::rounds]]
            sp, su = _sigmoid(xp @ w), _sigmoid(xu @ w)
            negative = np.mean(-np.log1p(-su.clip(0, 1 - 1e-12))) - prior * np.mean(-np.log1p(-sp.clip(0, 1 - 1e-12)))
            unlabelled_part = xu.T @ su / len(xu) - prior * (xp.T @ sp / len(xp))
            gradient = unlabelled_part + prior * (xp.T @ (sp - 1) / len(xp)) if negative >= 0 else -unlabelled_part
            gradient = gradient + decay * np.append(w[:-1], 0)
            step += 1
            m, v = 0.9 * m + 0.1 * gradient, 0.999 * v + 0.001 * gradient**2
            w = w - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return LinearModel(mean, scale, w[:-1], float(w[-1]), prior)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -35, 35)))


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, seed: int = 13) -> float:
    """Share of positives among unlabelled rows: the least ratio of both sets' shares above a threshold, allowing for chance, by two-fold cross-fitting.

    Give few features: a model that tells the positive sample from its own kind makes the share too small.
    """
    if min(len(positive), len(unlabelled)) < 4:
        return 0.5
    rng = np.random.default_rng(seed)
    sides = [[x[rng.permutation(len(x))[k::2]] for k in (0, 1)] for x in (positive, unlabelled)]
    found = []
    for fit, other in ((0, 1), (1, 0)):
        weights = _ridge_logistic(np.vstack([sides[0][fit], sides[1][fit]]), np.repeat([1.0, 0.0], [len(sides[0][fit]), len(sides[1][fit])]))
        p, u = (np.sort(_with_one(x[other]) @ weights) for x in sides)
        slack = sum((np.log(40) / (2 * len(x))) ** 0.5 for x in (p, u))
        share_p, share_u = (1 - np.searchsorted(x, p, side="left") / len(x) for x in (p, u))
        best = np.argmin((share_u + slack) / share_p)
        found.append(share_u[best] / share_p[best])
    return float(np.clip(np.mean(found), 0.01, 0.99))


def _with_one(x: np.ndarray) -> np.ndarray:
    return np.hstack([x, np.ones((len(x), 1))])


def _ridge_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 12) -> np.ndarray:
    """Weights (the last one is the bias) of a logistic regression by Newton steps."""
    x, w = _with_one(x), np.zeros(x.shape[1] + 1)
    penalty = ridge * len(x) * np.eye(len(w)) / len(w)
    for _ in range(steps):
        p = _sigmoid(x @ w)
        w = w + np.linalg.solve((x.T * (p * (1 - p) + 1e-6)) @ x + penalty, x.T @ (y - p) - penalty @ w)
    return w


def _sample_vectors(docs: DataFrame, sure: DataFrame, free: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Vectors of the documents with the given ids (two bounded sets of distinct ids), one row an id, by one scan of the texts.

    Of the rows of an id that repeats the one with the least vector counts; tasks fold them before anything is sent.
    """
    wanted = sure.select("doc_id", F.lit(1).alias("p"), F.lit(0).alias("u")).unionByName(free.select("doc_id", F.lit(0).alias("p"), F.lit(1).alias("u")))
    wanted = F.broadcast(wanted.groupBy("doc_id").agg(F.max("p").alias("p"), F.max("u").alias("u")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in text_slices(batches):
            vectors = pa.array([text_vector(t).tobytes() for t in texts], type=pa.binary())
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), part.column(3), vectors], names=["doc_id", "p", "u", "x"])

    found = docs.select("doc_id", "text").join(wanted, "doc_id").select("doc_id", "text", "p", "u").mapInArrow(run, "doc_id long, p int, u int, x binary")
    rows = found.groupBy("doc_id", "p", "u").agg(F.min("x").alias("x")).orderBy("doc_id").collect()  # at most both samples' sizes
    return tuple(np.array([np.frombuffer(r.x, dtype=np.float32) for r in rows if r[side]], dtype=np.float64).reshape(-1, WIDTH) for side in ("p", "u"))


def fit_quality(docs: DataFrame, labels: DataFrame, positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> LinearModel:
    """docs(doc_id, text), labels(doc_id, quality). Only labels of ids whose crc32 remainder modulo 3 isn't 1 are used.

    Positives are good labelled documents (at most ``positives`` ids); the unlabelled sample (at most ``unlabelled`` ids) is drawn from all
    documents outside the held-out fold with no look at labels.
    """
    fold = F.coalesce(id_remainder(F.col("doc_id")) != 1, F.lit(False))
    good = labels.where(fold & (F.col("quality") == 1)).select("doc_id").distinct()
    at_hand = materialise(docs.select("doc_id").where(fold).distinct())
    sure = materialise(hash_sample(materialise(good.join(at_hand, "doc_id", "left_semi")), positives, "doc_id"))
    free = materialise(hash_sample(at_hand, unlabelled, "doc_id"))
    p, u = _sample_vectors(docs, sure, free)
    if not len(p) or not len(u):
        return fit_pu(p, u, 0.5)
    mean, scale = u.mean(axis=0), u.std(axis=0) + 1e-3
    few = 2 * len(FEATURES) + 1
    return fit_pu(p, u, min(estimate_prior(*(((x - mean) / scale).clip(-8, 8)[:, :few] for x in (p, u))), 0.98))


def _scorer(model: LinearModel):
    @F.arrow_udf("double")
    def score(texts: pa.Array) -> pa.Array:
        parts = [model.score(np.array([text_vector(t) for t in part])) for part in text_parts(texts)]
        return pa.array(np.concatenate(parts) if parts else np.empty(0), type=pa.float64())

    return score


def quality_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted), one row per input row.

    Null and blank texts have the zero vector and get the score that the model gives it. A null doc_id is scored, is never
    used for training and isn't held out; repeated rows score alike; an empty table gives no rows. Without a
    positive or an unlabelled row every score is the constant of an untrained model. Other columns aren't read.
    """
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    model = fit_quality(docs, labels)
    score = _scorer(model)
    held_out = F.coalesce(id_remainder(F.col("doc_id")) == 1, F.lit(False))
    return docs.select("doc_id", held_out.alias("held_out"), score("text").alias("score")).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def keep_quality_rows(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = 0.5) -> DataFrame:
    """The rows of docs that score at least ``least``, all columns unchanged."""
    model = fit_quality(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")), labels)
    return docs.where(_scorer(model)(F.col(text_col)) >= least)
