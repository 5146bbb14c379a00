"""Helpers shared by the corpus operators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.lineage import ensure_checkpoint_dir, materialise

__all__ = ["arrow_long", "ensure_checkpoint_dir", "hash_sample", "id_remainder", "join_with_hubs", "materialise", "row_slices", "shuffle_partitions", "text_parts", "text_slices", "words_of"]

#: Most rows, and bytes of text beyond the first row, that are handed from an Arrow batch to Python code at a time.
SLICE_ROWS = 512
SLICE_BYTES = 16 << 20


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_bounds(texts: pa.Array) -> Iterator[tuple[int, int]]:
    """Bounds of slices that are small in rows and bytes, so that a batch of long texts is never decoded at once."""
    at, ends = 0, np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
    while at < len(texts):
        limit = (ends[at - 1] if at else 0) + SLICE_BYTES
        stop = min(at + SLICE_ROWS, max(at + 1, int(np.searchsorted(ends, limit, side="right"))))
        yield at, stop
        at = stop


def text_parts(texts: pa.Array) -> Iterator[list[str | None]]:
    for at, stop in text_bounds(texts):
        yield texts.slice(at, stop - at).to_pylist()


def text_slices(batches: Iterator[pa.RecordBatch], column: str = "text") -> Iterator[tuple[pa.RecordBatch, list[str | None]]]:
    """Slices of the batches with their texts."""
    for batch in batches:
        texts = batch.column(batch.schema.get_field_index(column))
        for at, stop in text_bounds(texts):
            yield batch.slice(at, stop - at), texts.slice(at, stop - at).to_pylist()


def row_slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches in parts of at most SLICE_ROWS rows."""
    for batch in batches:
        for at in range(0, batch.num_rows, SLICE_ROWS):
            yield batch.slice(at, SLICE_ROWS)


def arrow_long(values) -> pa.Array:
    return pa.array(np.asarray(values, dtype=np.int64), type=pa.int64())


def words_of(text: str | None) -> list[bytes]:
    """Words are runs of bytes other than space and 0x09-0x0D; bytes.split() cuts at exactly those."""
    return text.encode("utf-8").split() if text else []


def id_remainder(doc_id, divisor: int = 3):
    """crc32 of the id written as text, modulo the divisor; null for a null id."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(divisor))


def hash_sample(df: DataFrame, rows: int, *keys: str) -> DataFrame:
    """``rows`` rows (all, if there are fewer): those of the least hashes. ``df`` must be stable (a checkpoint or table).

    The hash is of the keys and of a row's place, so equal rows are drawn one by one. A threshold a little above the share
    wanted comes first: every task sends about its share, and no more than ``rows`` rows reach the driver.
    """
    total = df.count()
    if total <= rows:
        return df
    share = min(1.0, (rows + 6 * rows**0.5 + 20) / total)
    drawn = df.withColumn("_draw", F.xxhash64(F.lit("sample"), F.monotonically_increasing_id(), *keys))
    near = drawn.where(F.pmod("_draw", F.lit(1 << 31)) < int(share * (1 << 31)))
    return near.orderBy(F.pmod("_draw", F.lit(1 << 31)), "_draw").limit(rows).drop("_draw")


#: Keys that are joined by broadcast because each has over 1/HUBS of all rows: there are fewer than HUBS of them.
HUBS = 200


def join_with_hubs(rows: DataFrame, keyed: DataFrame, key: str, count: str) -> DataFrame:
    """Inner join of rows with a table of one row a key, which says how many of ``rows`` have the key.

    Keys with more than 1/HUBS of the rows would fill one task of a shuffled join. There are fewer than HUBS such keys whatever
    the data, so they are broadcast and their rows stay where they are; all other keys are joined by a shuffle. Both tables should be stable.
    """
    most = (keyed.agg(F.sum(count)).first()[0] or 0) / HUBS
    hubs = F.broadcast(keyed.where(F.col(count) > most).drop(count))
    rest = rows.join(hubs.select(key), key, "left_anti").join(keyed.where(F.col(count) <= most).drop(count), key)
    return rows.join(hubs, key).unionByName(rest)
