"""SimHash near-duplicates with bit-sliced comparison.

Fingerprints are 64-bit majorities of XXH64 (seed 42) over 3-word shingles of the lower-cased text. Equal
fingerprints are folded first, so groups of exact copies cost one row. Two fingerprints within the radius agree
on at least ``blocks - radius`` of ``blocks`` bit blocks, hence share one key of the tables below; the
tables' keys get longer as the corpus grows. Inside a bucket the bit planes lie one after another (one machine word
holds one bit of 64 fingerprints); each plane updates 64 distances at once with carry-save counters that saturate at
radius + 1, and a word whose 64 distances have all passed the radius is abandoned. A bucket emits a spanning forest of its links, never
all pairs. Buckets above ``bucket_limit`` are cut into tiles (pairs of chunks) that together still compare every pair.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilgrid.llm.common import arrow_long, join_with_hubs, materialise, shuffle_partitions, text_slices
from veilgrid.llm.components import connected_components

RADIUS = 3
SHINGLE = 3
SEED = 42
#: Fingerprints compared in one task without tiling: at most 16384^2 / 2 pairs in 64-pair words.
BUCKET_LIMIT = 16_384
#: Shingles hashed at a time, which bounds the memory a very long text takes.
HASH_CHUNK = 1 << 15
#: (row, word) cells compared at a time.
CELLS = 1 << 16
ONES = np.uint64(0xFFFFFFFFFFFFFFFF)
U1 = np.uint64(1)


def simhash(text: str | None) -> int:
    """Unsigned fingerprint of one whole text; 0 for a text without words (null included)."""
    words = text.encode("utf-8").lower().split() if text else []  # bytes.lower() maps A-Z only
    if not words:
        return 0
    if len(words) < SHINGLE:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    n = len(words) - SHINGLE + 1
    ones = np.zeros(64, dtype=np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, n, HASH_CHUNK):
        piece = words[at : min(at + HASH_CHUNK, n) + SHINGLE - 1]
        h = np.array([digest(s, SEED) for s in map(b" ".join, zip(piece, piece[1:], piece[2:], strict=False))], dtype="<u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: tuple[Column, ...] = ()) -> DataFrame:
    """(doc_id, fp BIGINT, and the kept long columns): the fingerprint's bits as a signed long."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), *keep)
    kept = rows.columns[2:]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in text_slices(batches):
            fp = np.array([simhash(t) for t in texts], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([part.column(0), arrow_long(fp), *part.columns[2:]], names=["doc_id", "fp", *kept])

    return rows.mapInArrow(run, ", ".join(f"{c} long" for c in ["doc_id", "fp", *kept]))


def key_tables(distinct: int, radius: int = RADIUS) -> list[int]:
    """Bit masks whose masked values are bucket keys. More blocks make longer keys and more tables.

    A bucket of random fingerprints then stays near or under a thousand rows: 16-bit keys up to 2^26
    fingerprints, 26-bit keys up to 2^36, 32-bit keys beyond.
    """
    blocks = radius + 1 if distinct <= 1 << 26 else radius + 2 if distinct <= 1 << 36 else radius + 3
    edge = [64 * k // blocks for k in range(blocks + 1)]
    masks = [((1 << edge[k + 1]) - 1) ^ ((1 << edge[k]) - 1) for k in range(blocks)]
    return [sum(chosen) for chosen in combinations(masks, blocks - radius)]


def link_bucket_rows(group: np.ndarray, fp: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """For rows sorted by group: the index of each row's representative after linking rows of a group within the radius."""
    n = len(fp)
    parent = np.arange(n, dtype=np.int64)
    if n < 2:
        return parent
    words = (n + 63) // 64
    padded = np.zeros(words * 64, dtype="<u8")
    padded[:n] = fp
    bits = np.unpackbits(padded.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    planes = np.packbits(bits.T.copy(), axis=1, bitorder="little").view("<u8")
    change = np.flatnonzero(group[1:] != group[:-1]) + 1
    end = np.repeat(np.append(change, n), np.diff(np.concatenate([[0], change, [n]])))
    row = np.arange(n, dtype=np.int64)
    first, last = (row + 1) >> 6, (end - 1) >> 6
    cells = np.where(end > row + 1, last - first + 1, 0)
    stop = np.cumsum(cells)
    at = 0
    while at < n:
        base = stop[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(stop, base + CELLS, side="right")))
        count = cells[at:to]
        i = np.repeat(row[at:to], count)
        if len(i):
            w = np.repeat(first[at:to], count) + np.arange(len(i)) - np.repeat(np.cumsum(count) - count, count)
            for lo in range(0, len(i), CELLS):
                _link_cells(i[lo : lo + CELLS], w[lo : lo + CELLS], fp, end, planes, parent, radius)
        at = to
    return _roots(parent, row)


def _link_cells(i, w, fp, end, planes, parent, radius: int) -> None:
    """Compare row i with the 64 rows of word w for all cells at once."""
    start = w << 6
    low = np.clip(i + 1 - start, 0, 64)
    high = np.clip(end[i] - start, 0, 64)
    over = ~(_below(high) & ~_below(low))  # lanes outside the bucket or not after the row count as passed
    counters = [np.zeros(len(i), dtype=np.uint64) for _ in range(radius.bit_length())]
    f = fp[i]
    for p in range(64):
        mask = np.uint64(0) - ((f >> np.uint64(p)) & U1)
        carry = planes[p][w] ^ mask
        if (radius + 1) & radius:
            over |= _add_generic(counters, carry, radius)
        else:  # radius + 1 is a power of two: the carry out of the last counter says that it is passed
            for c in counters:
                carry_out = c & carry
                c ^= carry
                carry = carry_out
            over |= carry
        if p % 8 == 7:
            alive = np.flatnonzero(over != ONES)
            if len(alive) < len(over):
                i, w, f, over = i[alive], w[alive], f[alive], over[alive]
                counters = [c[alive] for c in counters]
            if not len(i):
                return
    lanes = np.unpackbits((~over).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    cell, lane = np.nonzero(lanes)
    _unite(parent, i[cell], (w[cell] << 6) + lane)


def _add_generic(counters, carry, radius: int):
    for c in counters:
        carry_out = c & carry
        c ^= carry
        carry = carry_out
    passed = carry.copy()
    equal = np.full_like(carry, ONES)
    for k, c in reversed(list(enumerate(counters))):  # counter > radius
        bit = ONES if radius >> k & 1 else np.uint64(0)
        passed |= equal & c & ~bit
        equal &= ~(c ^ bit)
    return passed


def _below(k: np.ndarray) -> np.ndarray:
    """Words whose lowest k bits are set, 0 <= k <= 64."""
    k = k.astype(np.uint64)
    return np.where(k >= 64, ONES, (U1 << (k & np.uint64(63))) - U1)


def _roots(parent: np.ndarray, of: np.ndarray) -> np.ndarray:
    up = parent[of]
    while True:
        above = parent[up]
        if np.array_equal(above, up):
            return up
        up = above


def _unite(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    while len(a):
        ra, rb = _roots(parent, a), _roots(parent, b)
        parent[a], parent[b] = ra, rb
        apart = ra != rb
        a, b = ra[apart], rb[apart]
        if len(a):
            np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))


def _links_of_partition(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)) for b in batches if b.num_rows]
        if not parts:
            return
        group, fp = np.concatenate([x for x, _ in parts]), np.concatenate([x for _, x in parts])
        order = np.lexsort((fp, group))
        group, fp = group[order], fp[order].view(np.uint64)
        root = link_bucket_rows(group, fp, radius)
        moved = np.flatnonzero(root != np.arange(len(root)))
        a, b = fp[moved].view(np.int64), fp[root[moved]].view(np.int64)
        for at in range(0, len(a), 1 << 16):
            yield pa.RecordBatch.from_arrays([arrow_long(a[at : at + (1 << 16)]), arrow_long(b[at : at + (1 << 16)])], names=["a", "b"])

    return run


def fingerprint_links(distinct_fps: DataFrame, radius: int = RADIUS, bucket_limit: int = BUCKET_LIMIT, partition_rows: int = 1 << 19, count: int | None = None) -> DataFrame:
    """distinct_fps(fp) -> (a, b): edges that join exactly the fingerprints connected by distances within the radius."""
    spark = distinct_fps.sparkSession
    n = distinct_fps.count() if count is None else count
    masks = key_tables(n, radius)
    keys = F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k")) for t, m in enumerate(masks)]))
    rows = distinct_fps.select("fp", keys.alias("x")).select("fp", F.xxhash64("x.t", "x.k").alias("bucket"))
    hot = materialise(rows.groupBy("bucket").count().where(F.col("count") > bucket_limit).select("bucket", F.ceil(F.col("count") / F.lit(bucket_limit)).cast("int").alias("chunks")), n * len(masks) // bucket_limit)
    if hot.isEmpty():
        tiled = rows.select(F.col("bucket").alias("tile"), "fp")
    else:
        tiled = rows.join(hot, "bucket", "left").select(F.explode(_tiles()).alias("tile"), "fp")
    tasks = max(shuffle_partitions(spark), -(-n * len(masks) // partition_rows))
    return tiled.repartition(tasks, "tile").mapInArrow(_links_of_partition(radius), "a long, b long").distinct()


def _tiles() -> Column:
    """Tile keys of a row: its bucket, or for a hot bucket one for each pair of its chunk with another chunk."""
    chunks = F.coalesce(F.col("chunks"), F.lit(1))
    own = F.pmod(F.xxhash64(F.lit("chunk"), F.col("fp")), chunks)
    pairs = F.transform(F.sequence(F.lit(0), chunks - 1), lambda j: F.xxhash64(F.col("bucket"), F.least(own, j.cast("long")), F.greatest(own, j.cast("long"))))
    return F.when(F.col("chunks").isNull(), F.array("bucket")).otherwise(pairs)


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, bucket_limit: int = BUCKET_LIMIT) -> DataFrame:
    """(doc_id, fp, fingerprint, component_id), one row per input row.

    component_id is the smallest doc_id reachable over links of at most ``radius`` differing bits. Null and blank
    texts have fingerprint zero and link like any other; repeated rows keep their repeats; a null doc_id gets a
    component but never names one (a component of null ids only has a null component_id); an empty table gives
    no rows; other columns of the input are not read.
    """
    prints = materialise(fingerprints(docs, id_col, text_col))
    named, n = rooted(prints.groupBy("fp").agg(F.min("doc_id").alias("least_id"), F.count("*").alias("copies")), prints.count(), radius, bucket_limit)
    least = materialise(named.groupBy("root").agg(F.min("least_id").alias("component_id"), F.count("*").alias("n")), n)
    of_fp = materialise(join_with_hubs(named, least, "root", "n").select("fp", "copies", "component_id"), n)
    return join_with_hubs(prints, of_fp, "fp", "copies").select("doc_id", "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def rooted(folded: DataFrame, most: int, radius: int = RADIUS, bucket_limit: int = BUCKET_LIMIT) -> tuple[DataFrame, int]:
    """A table with one row a fingerprint (fp, ...), at most ``most`` of them, with ``root``, the component's least fingerprint; and its rows."""
    folded = materialise(folded, most)
    n = folded.count()
    links = fingerprint_links(folded.select("fp"), radius, bucket_limit, count=n)
    roots = connected_components(links, most=n * len(key_tables(n, radius))).withColumnRenamed("node", "fp")  # a bucket's forest has fewer edges than rows
    return materialise(folded.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp")), n), n


def keep_one_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, bucket_limit: int = BUCKET_LIMIT) -> DataFrame:
    """One row of each component, all columns unchanged: the row with the smallest id, of those that tie one by a hash of the text.

    Components are of rows, whatever their ids: an id that stands for several different texts loses none of them. Null ids
    come last, so a group without any id keeps one row; repeated rows are one; an empty table gives no rows.
    """
    columns = docs.columns
    key = [F.xxhash64(F.lit(k), F.col(id_col).cast("long"), F.lit("/"), F.col(text_col)).alias(f"_key{k}") for k in (1, 2)]  # 128 bits of id and text
    prints = materialise(fingerprints(docs, id_col, text_col, tuple(key)))
    row = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "_key1", "_key2")
    named, _ = rooted(prints.groupBy("fp").agg(F.min(row).alias("row")), prints.count(), radius, bucket_limit)
    heads = named.groupBy("root").agg(F.min("row").alias("row")).select("row._key1", "row._key2")
    single = docs.select("*", *key).dropDuplicates(["_key1", "_key2"])  # copies fold in each task, so no key fills one
    return single.join(heads, ["_key1", "_key2"], "left_semi").select(*[F.col(f"`{c}`") for c in columns])
