"""Merkle fixity audit of record archives.

A replica's records are hashed, ordered by their offsets within each archive, and hashed again in ranges of
``FANOUT`` children up to one root per archive. Roots of two replicas are compared first; only children of
nodes that differ are looked at on the way down, so an audit of sound copies reads one row per archive.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from veilgrid.llm.common import materialise

FANOUT = 16
#: Records of one archive file; bounds the ordered ranges that one group holds.
ARCHIVE_RECORDS = 4096


@dataclass(frozen=True)
class Tree:
    """levels[0] has a row per record (archive, at, record_id, offset, length, hash); levels[-1] one per archive."""

    levels: tuple[DataFrame, ...]


def warc_record(uri: Column, body: Column) -> Column:
    """Bytes of a WARC 1.1 resource record; a null uri or body counts as empty."""
    body = F.coalesce(body.cast("binary"), F.lit(b""))
    head = F.concat(F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Target-URI: "), F.coalesce(uri, F.lit("")), F.lit("\r\nContent-Length: "), F.octet_length(body).cast("string"), F.lit("\r\n\r\n"))
    return F.concat(head.cast("binary"), body, F.lit(b"\r\n\r\n"))


def leaves(records: DataFrame, id_col: str, record_col: str, archive_records: int = ARCHIVE_RECORDS) -> DataFrame:
    """Record hashes with their place. Archives take ranges of ids; equal ids are ordered by hash; null ids are spread by content."""
    spread = -1 - F.pmod(F.xxhash64(record_col), F.lit(archive_records))
    archive = F.coalesce(F.floor(F.col(id_col) / F.lit(archive_records)), spread).cast("long")
    hashed = records.select(archive.alias("archive"), F.col(id_col).cast("long").alias("record_id"), F.octet_length(record_col).cast("long").alias("length"), F.sha2(record_col, 256).alias("hash"))
    order = Window.partitionBy("archive").orderBy("record_id", "hash")
    offset = F.coalesce(F.sum("length").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return hashed.select("archive", (F.row_number().over(order) - 1).cast("long").alias("at"), "record_id", offset.alias("offset"), "length", "hash")


#: What every record starts with, in versions 1.0 and 1.1.
MARK = b"WARC/1."
_LENGTH = re.compile(rb"\r\ncontent-length:[ \t]*([0-9]+)[ \t]*\r\n", re.IGNORECASE)


def split_records(data: bytes) -> Iterator[tuple[int, int]]:
    """(offset, length) of an archive's records; what can't be read as a record is one last range, so that damage to a header shows."""
    at = 0
    while at < len(data):
        head = data.find(b"\r\n\r\n", at)
        found = _LENGTH.search(data, at, head + 2) if head >= 0 else None
        stop = head + 4 + int(found[1]) + 4 if found else len(data)
        if stop > len(data) or not data.startswith(b"WARC/", at):
            stop = len(data)
        yield at, stop - at
        at = stop


def file_leaves(spark: SparkSession, folder: str, pattern: str = "*.warc*") -> DataFrame:
    """Record hashes of the archive files in a folder, by file name and in file order; plain or compressed (.gz).

    Files are read in ranges that start at record marks, so plain files of any size are split over tasks, compressed ones stream, and a task
    holds records and not files. Offsets count uncompressed bytes. A mark inside a record's body cuts it in both replicas
    alike. Empty files have no records and are the same as files that aren't there.
    """
    names = ["archive", "block", "row", "part", "length", "hash"]
    types = [pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            rows = []
            for k in range(batch.num_rows):
                name, block, row, data = (batch.column(c)[k].as_py() for c in range(4))
                before_marks, last = block == 0 and name != last, name  # a file's first block is read in order by one task
                whole = data if before_marks else MARK + data
                rows += [(name, block, row, i, n, hashlib.sha256(whole[at : at + n]).hexdigest()) for i, (at, n) in enumerate(split_records(whole))]
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], type=t) for c, t in enumerate(types)], names=names)

    files = spark.read.option("lineSep", MARK.decode()).option("pathGlobFilter", pattern).text(folder)
    pieces = files.select(F.substring_index("_metadata.file_path", "/", -1).alias("archive"), F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("row"), F.col("value").cast("binary").alias("data"))
    hashed = pieces.mapInArrow(run, "archive string, block long, row long, part int, length long, hash string")
    order = Window.partitionBy("archive").orderBy("block", "row", "part")
    offset = F.coalesce(F.sum("length").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return hashed.select("archive", (F.row_number().over(order) - 1).cast("long").alias("at"), F.lit(None).cast("long").alias("record_id"), offset.alias("offset"), "length", "hash")


def audit_folders(spark: SparkSession, primary: str, replica: str, pattern: str = "*.warc*", fanout: int = FANOUT) -> DataFrame:
    """Audit of two folders of archive files, record by record in file order; a record that is lost shifts those after it, which show as corrupt places."""
    sides = [materialise(file_leaves(spark, x, pattern)) for x in (primary, replica)]
    fullest = max((x.agg(F.max("at")).first()[0] or 0) + 1 for x in sides)
    return audit(*(build_tree(x, tree_height(fullest, fanout), fanout) for x in sides), fanout)


def build_tree(leaf_rows: DataFrame, height: int, fanout: int = FANOUT) -> Tree:
    """Each level hashes the ordered hashes of up to ``fanout`` children."""
    levels = [materialise(leaf_rows)]
    for _ in range(height):
        child = levels[-1]
        parent = F.floor(F.col("at") / F.lit(fanout)).cast("long")
        members = F.sort_array(F.collect_list(F.struct("at", "hash")))
        levels.append(materialise(child.groupBy("archive", parent.alias("at")).agg(F.sha2(F.array_join(F.transform(members, lambda x: x["hash"]), ""), 256).alias("hash"))))
    return Tree(tuple(levels))


def tree_height(archive_records: int, fanout: int = FANOUT) -> int:
    height, reach = 0, 1
    while reach < archive_records:
        height, reach = height + 1, reach * fanout
    return max(1, height)


def audit(primary: Tree, replica: Tree, fanout: int = FANOUT) -> DataFrame:
    """(archive, at, record_id, offset, length, replica_record_id, replica_offset, replica_length, state) per record place that differs.

    state is ``corrupt`` (same record, other bytes), ``moved`` (another record at this place), ``missing`` or ``extra``
    (the place exists in one replica only). Trees of different heights and archives that one replica lacks are handled by
    the outer comparison at the top; sound replicas and empty tables give no rows.
    """
    if len(primary.levels) != len(replica.levels):
        raise ValueError("trees differ in height")
    open_nodes = None
    for k in range(len(primary.levels) - 1, -1, -1):
        a, b = primary.levels[k], replica.levels[k]
        if open_nodes is not None:
            parent = F.floor(F.col("at") / F.lit(fanout)).cast("long")
            nodes = open_nodes.withColumnRenamed("at", "parent")
            a, b = (x.withColumn("parent", parent).join(nodes, ["archive", "parent"], "left_semi").drop("parent") for x in (a, b))
        both = a.alias("a").join(b.alias("b"), ["archive", "at"], "full_outer").where(~F.col("a.hash").eqNullSafe(F.col("b.hash")))
        if k:
            open_nodes = materialise(both.select("archive", "at"))
    state = F.when(F.col("b.hash").isNull(), "missing").when(F.col("a.hash").isNull(), "extra").when(F.col("a.record_id").eqNullSafe(F.col("b.record_id")), "corrupt").otherwise("moved")
    return both.select("archive", "at", *[F.col(f"a.{c}").alias(c) for c in ("record_id", "offset", "length")], *[F.col(f"b.{c}").alias(f"replica_{c}") for c in ("record_id", "offset", "length")], state.alias("state"))


def audit_replicas(primary: DataFrame, replica: DataFrame, id_col: str, record_col: str, archive_records: int = ARCHIVE_RECORDS, fanout: int = FANOUT) -> DataFrame:
    """Build both trees over (id, record bytes) and locate what differs. Null records hash as absent content and differ from any bytes.

    Archives are ranges of ids; one whose ids repeat may hold more than ``archive_records`` rows, so the height allows for the fullest one.
    """
    sides = [materialise(leaves(x, id_col, record_col, archive_records).withColumn("hash", F.coalesce("hash", F.lit("")))) for x in (primary, replica)]
    fullest = max(x.agg(F.coalesce(F.max("at"), F.lit(0))).first()[0] + 1 for x in sides)
    height = tree_height(max(fullest, archive_records), fanout)
    return audit(*(build_tree(x, height, fanout) for x in sides), fanout)
