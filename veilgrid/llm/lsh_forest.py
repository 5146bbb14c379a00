"""Approximate nearest neighbours with a hash-prefix forest.

Every tree is a sorted array of long hash strings. A symbol of a string names the nearest signed axis among a few axes of
a random rotation. A query descends each tree to its longest-prefix matches by binary search and then ascends the
trees together, one symbol at a time and a few trees at a time, until a neighbour as far off as its k-th best so far would
have been met with the wanted chance. That chance follows from the symbols' chance of being equal at an angle,
so the ascent is as deep as the query needs, whatever the table's size.

The table is indexed in blocks of bounded size inside the partitions that hold it, so vectors are never shuffled; trees of
a block are built once for a pass of queries, and a pass takes as many queries as fit QUERY_BYTES. Candidates
of all blocks are merged by exact distance. Work is queries x rows x the share of a block that is met.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilgrid.llm.common import arrow_long, materialise

TREES = 256
SYMBOLS = 6
#: Axes of one symbol: 16 symbols of 4 bits.
AXES = 8
SYMBOL_BITS = 4
#: Wanted chance that a neighbour at the k-th best angle has been met.
TARGET = 0.96
#: Trees that ascend between two looks at that chance.
STRIDE = 16
#: Vectors indexed together; bounds a task's memory.
BLOCK_ROWS = 32_768
#: Bytes of query vectors sent to the blocks in one pass.
QUERY_BYTES = 32 << 20
#: Queries whose places in the trees are looked up together.
QUERY_BATCH = 512
_ANGLES = np.linspace(0, np.pi, 65)


def usable(vector_col):
    """Vectors that are null, zero, or hold null or non-finite components take no part."""
    v = F.col(vector_col)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return v.isNotNull() & (F.size(v) > 0) & fine & F.exists(v, lambda x: x != 0)


def axis_symbols(y: np.ndarray) -> np.ndarray:
    """Nearest signed axis of each row: twice the axis, plus one on its negative side."""
    axis = np.abs(y).argmax(axis=1)
    return (2 * axis + (y[np.arange(len(y)), axis] < 0)).astype(np.uint32)


def hash_strings(x: np.ndarray, trees: int, symbols: int, seed: int = 5) -> np.ndarray:
    """(trees, rows) strings, most significant symbol first. A rotation serves as many symbols as it has groups of axes."""
    rng, dim = np.random.default_rng(seed), x.shape[1]
    axes, out = min(AXES, dim), np.zeros((trees, len(x)), dtype=np.uint32)
    at = groups = dim // axes
    for t in range(trees):
        for _ in range(symbols):
            if at == groups:
                turned, at = x @ np.linalg.qr(rng.standard_normal((dim, dim)))[0].astype(np.float32), 0
            out[t] = out[t] << np.uint32(SYMBOL_BITS) | axis_symbols(turned[:, at * axes : (at + 1) * axes])
            at += 1
    return out


def equal_chance(axes: int, draws: int = 20_000, seed: int = 6) -> np.ndarray:
    """Chance that a symbol is equal for two vectors at each angle of a grid, by simulation; it falls with the angle."""
    rng = np.random.default_rng(seed)
    a, b = rng.standard_normal((2, draws, axes))
    own = axis_symbols(a)
    return np.minimum.accumulate([np.mean(own == axis_symbols(np.cos(t) * a + np.sin(t) * b)) for t in _ANGLES])


class Forest:
    """Sorted arrays over one block of distinct vectors."""

    def __init__(self, vectors: np.ndarray, trees: int = TREES, symbols: int = SYMBOLS, chance: np.ndarray | None = None):
        self.vectors, self.unit, self.trees, self.symbols = vectors, _unit(vectors), trees, symbols
        self.chance = equal_chance(min(AXES, vectors.shape[1])) if chance is None else chance
        strings = hash_strings(self.unit, trees, symbols)
        self.order = np.argsort(strings, axis=1, kind="stable").astype(np.int32)
        self.sorted = np.take_along_axis(strings, self.order, axis=1)

    def places(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First and last place of each query's prefixes: two arrays (query, depth - 1, tree)."""
        strings = hash_strings(queries, self.trees, self.symbols)
        low, high = np.empty((2, len(queries), self.symbols, self.trees), dtype=np.int32)
        for depth in range(1, self.symbols + 1):
            shift = np.uint64(SYMBOL_BITS * (self.symbols - depth))
            prefix = strings.astype(np.uint64) >> shift
            first, last = prefix << shift, ((prefix + np.uint64(1)) << shift) - np.uint64(1)
            for t in range(self.trees):
                low[:, depth - 1, t] = np.searchsorted(self.sorted[t], first[t].astype(np.uint32), side="left")
                high[:, depth - 1, t] = np.searchsorted(self.sorted[t], last[t].astype(np.uint32), side="right")
        return low, high

    def search(self, query: np.ndarray, unit: np.ndarray, low: np.ndarray, high: np.ndarray, k: int, target: float) -> tuple[np.ndarray, np.ndarray, int]:
        """(rows, distances, depth reached) of all candidates of one query; places (depth - 1, tree) are given."""
        met, enough = np.zeros(len(self.unit), dtype=bool), min(k, len(self.unit))
        rows, gaps, best, worst = [], [], np.empty(0), np.empty(0)  # best: the k least distances so far, worst: their cosines
        sizes = (high - low).sum(axis=1)
        start = int(np.flatnonzero(sizes >= k)[-1]) + 1 if (sizes >= k).any() else 1  # the longest prefixes that can do
        steps = [(start, 0, self.trees)] + [(d, t, min(t + STRIDE, self.trees)) for d in range(start - 1, 0, -1) for t in range(0, self.trees, STRIDE)]
        for depth, a, b in steps:
            taken = np.zeros(len(met), dtype=bool)
            taken[self._rows(low[depth - 1, a:b], high[depth - 1, a:b], a)] = True
            new = np.flatnonzero(taken & ~met)
            met[new] = True
            rows.append(new)
            gaps.append(np.sqrt(((self.vectors[new] - query) ** 2).sum(axis=1)))
            best, worst = np.append(best, gaps[-1]), np.append(worst, self.unit[new] @ unit)
            if len(best) > k:
                kept = np.argpartition(best, k - 1)[:k]
                best, worst = best[kept], worst[kept]
            if len(best) >= enough:
                equal = np.interp(np.arccos(np.clip(worst.min(initial=1), -1, 1)), _ANGLES, self.chance)
                shallow = 1 - equal**depth
                missed = shallow ** b * (1 - equal ** min(depth + 1, start)) ** (self.trees - b)
                if 1 - missed >= target:
                    return np.concatenate(rows), np.concatenate(gaps), depth
        rest = np.flatnonzero(~met) if len(best) < enough or target >= 1 else np.empty(0, dtype=np.int64)
        gaps.append(np.sqrt(((self.vectors[rest] - query) ** 2).sum(axis=1)))
        return np.concatenate([*rows, rest]), np.concatenate(gaps), 0 if len(rest) else 1

    def _rows(self, low: np.ndarray, high: np.ndarray, first_tree: int) -> np.ndarray:
        size = (high - low).astype(np.int64)
        total = int(size.sum())
        inside = np.arange(total) - np.repeat(np.cumsum(size) - size, size)
        tree = first_tree + np.arange(len(size))
        return self.order.ravel()[np.repeat(tree * self.order.shape[1] + low, size) + inside]


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return (x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.float32)


def fold_equal(ids: np.ndarray, vectors: np.ndarray, keep: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct vectors, their group's first place in the ids, ids): equal vectors tie, so only a group's ``keep`` least ids can be results."""
    raw = np.ascontiguousarray(vectors + 0.0).view(np.dtype((np.void, vectors.shape[1] * 8))).ravel()
    _, first, group = np.unique(raw, return_index=True, return_inverse=True)
    order = np.lexsort((ids, group))
    sorted_group = group[order]
    nth = np.arange(len(ids)) - np.searchsorted(sorted_group, sorted_group)
    order = order[nth < keep]
    return vectors[first], np.searchsorted(group[order], np.arange(len(first) + 1)), ids[order]


def search_block(ids, vectors, query_ids, queries, k, trees, symbols, target, chance):
    """The k + 1 nearest rows met for each query (its own among them), by exact double distance, ties to the smaller id."""
    distinct, start, kept_ids = fold_equal(ids, vectors, k + 1)
    forest, out = Forest(distinct, trees, symbols, chance), []
    for at in range(0, len(query_ids), QUERY_BATCH):
        part = queries[at : at + QUERY_BATCH]
        unit = _unit(part)
        low, high = forest.places(unit)
        for q in range(len(part)):
            rows, gaps, _ = forest.search(part[q], unit[q], low[q], high[q], k + 1, target)
            if len(rows) > k + 1:
                near = np.flatnonzero(gaps <= np.partition(gaps, k)[k])
                rows, gaps = rows[near], gaps[near]
            copies = start[rows + 1] - start[rows]
            inside = np.arange(copies.sum()) - np.repeat(np.cumsum(copies) - copies, copies)
            v, d = kept_ids[np.repeat(start[rows], copies) + inside], np.repeat(gaps, copies)
            best = np.lexsort((v, d))[: k + 1]
            out.append((np.full(len(best), query_ids[at + q]), v[best], d[best]))
    return [np.concatenate(x) for x in zip(*out, strict=True)]


def _search_partition(query_ids, queries, k, trees, symbols, target, block_rows):
    chance = equal_chance(min(AXES, queries.shape[1]))

    def blocks(batches):
        ids, vectors, held = [], [], 0
        for b in batches:
            for at in range(0, b.num_rows, block_rows):
                part = b.slice(at, block_rows)
                if held + part.num_rows > block_rows and held:
                    yield np.concatenate(ids), np.concatenate(vectors)
                    ids, vectors, held = [], [], 0
                ids.append(part.column(0).to_numpy(zero_copy_only=False))
                vectors.append(part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1))
                held += part.num_rows
        if held:
            yield np.concatenate(ids), np.concatenate(vectors)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, vectors in blocks(batches):
            q, v, d = search_block(ids, vectors, query_ids, queries, k, trees, symbols, target, chance)
            yield pa.RecordBatch.from_arrays([arrow_long(q), arrow_long(v), pa.array(d, type=pa.float64())], names=["query_id", "vec_id", "score"])

    return run


def nearest_neighbours(table: DataFrame, query_filter, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", trees: int = TREES, symbols: int = SYMBOLS, target: float = TARGET, block_rows: int = BLOCK_ROWS, query_bytes: int = QUERY_BYTES) -> DataFrame:
    """(query_id, rank, vec_id, score): for each id that meets ``query_filter`` its k nearest other rows found.

    Scores are Euclidean distances of the original vectors in double precision; ties go to the smaller id. Every row of
    the table is indexed, by its direction: vectors of one length (or nearly) are what the hashes are meant for.
    Unusable vectors (null, empty, zero, null or non-finite components), null ids and vectors of another length
    than the most common one (the shorter of those that tie) take no part; equal vectors under different ids are all candidates. An id that stands in
    several rows is one query, with the least of its vectors, and all but one row of that vector and id are candidates; an
    empty table gives no rows.
    """
    good = table.where(usable(vector_col) & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"))
    common = good.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    dim = common.n if common else 1
    good = good.where(F.size("v") == dim)
    queries = good.where(query_filter(F.col("vec_id"))).groupBy("vec_id").agg(F.min("v").alias("v"))
    groups = max(1, -(-queries.count() * dim * 8 // query_bytes))
    parts = []
    for g in range(groups):
        rows = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(groups)) == g).toArrow()  # about query_bytes of them
        if not rows.num_rows:
            continue
        ids, vectors = rows["vec_id"].to_numpy(), rows["v"].combine_chunks().flatten().to_numpy().reshape(-1, dim)
        found = good.mapInArrow(_search_partition(ids, vectors, k, trees, symbols, target, block_rows), "query_id long, vec_id long, score double")
        parts.append(_best(found, k) if groups == 1 else materialise(_best(found, k)))
    if not parts:
        return good.select(F.col("vec_id").alias("query_id"), F.lit(1).alias("rank"), "vec_id", F.lit(0.0).alias("score")).where(F.lit(False))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _best(found: DataFrame, k: int) -> DataFrame:
    """The k best of k + 1 a block, without the query's own row: the first at distance zero with its id."""
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    near = found.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k + 1)
    owns = (F.col("vec_id") == F.col("query_id")) & (F.col("score") == 0)
    so_far = near.withColumn("owns", F.sum(owns.cast("int")).over(order.rowsBetween(Window.unboundedPreceding, 0))).where(~(owns & (F.col("owns") == 1)))
    ranked = so_far.withColumn("rank", F.col("place") - F.least("owns", F.lit(1))).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
