"""Global shuffle into shards in two passes.

Pass one deals every row by seeded hashes: its shard is the highest of one hash per shard (so one more shard takes rows
only into itself), its bucket within the shard is another hash. The number of buckets follows the total size, so that
one fits in a task's memory. Pass two opens each bucket once, Fisher-Yates shuffles it (Spark's array shuffle
draws its permutation that way) and places it after the buckets before it. Rows that stand in the table so often that their
copies would overfill a bucket are counted instead of moved: one of them is kept, and as many copies are made anew, each with a bucket of its
own. DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from veilgrid.llm.common import materialise

SHARDS = 8
SEED = 17
#: Bytes of text that one bucket is sized for; a task of the second pass holds one bucket.
BUCKET_BYTES = 128 << 20
#: Tasks of the second pass; buckets beyond it share tasks (128 TB in buckets of 128 MB are a million).
MAX_TASKS = 1_000_000
#: Buckets whose offsets (24 bytes each) are broadcast; beyond that they are joined by a shuffle.
MAX_BROADCAST = 2_000_000
#: Copies of a hot row that one task makes.
CHUNK = 100_000


def shard_of(key: Column, shards: int, seed: int = SEED) -> Column:
    """The shard with the highest hash of (seed, shard, key)."""
    draws = F.array(*[F.struct(F.xxhash64(F.lit(seed), F.lit(s), key).alias("h"), F.lit(s).alias("s")) for s in range(shards)])
    return F.array_max(draws)["s"]


def text_size(text: Column) -> Column:
    """UTF-8 bytes of the text (none for null) plus one."""
    return (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long")


def _row_hash(seed: int, columns: list[str]) -> Column:
    return F.xxhash64(F.lit(seed), *[x for c in columns for x in (F.col(c).isNull(), F.col(c))])


def _copies(hot: DataFrame, buckets: int, seed: int) -> DataFrame:
    """Adds a bucket to each of the ``n`` copies of every hot row; a task makes at most CHUNK of them at a time."""
    chunks = hot.withColumn("_chunk", F.explode(F.sequence(F.lit(0), F.floor((F.col("_n") - 1) / CHUNK)))).repartition("_h1", "_chunk")
    last = F.least(F.col("_n"), (F.col("_chunk") + 1) * CHUNK) - 1
    numbered = chunks.withColumn("_copy", F.explode(F.sequence(F.col("_chunk") * CHUNK, last)))
    return numbered.withColumn("_bucket", F.pmod(F.xxhash64(F.lit(seed + 3), "_h1", "_copy"), F.lit(buckets))).drop("_chunk", "_copy", "_n")


def shuffle_into_shards(rows: DataFrame, key: str, size: str, shards: int = SHARDS, seed: int = SEED, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """The input's columns with shard, grown_shard and slot (gapless from 0 in each shard).

    The placement is a function of the rows, the seed and the total size alone, so a task that is run again gives the same rows.
    Law ``key``: the key and the shard count decide the shard. Null keys are one key; rows with equal
    keys share a shard but are spread over its buckets by their other columns, and fully equal rows, once their copies take over a quarter of
    a bucket, by the copy's number. An empty table gives no rows. Every column must be orderable (no maps).
    """
    columns = rows.columns
    hashes = {"_h1": _row_hash(seed + 1, columns), "_h2": _row_hash(seed + 2, columns)}
    dealt = rows.select("*", shard_of(F.col(key), shards, seed).alias("_shard"), shard_of(F.col(key), shards + 1, seed).alias("_grown"), *[h.alias(n) for n, h in hashes.items()])
    narrow = materialise(dealt.select(F.col(size).alias("size"), "_shard", "_h1", "_h2"))  # sizes, hot rows and bucket counts need no text
    total = narrow.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    buckets = max(1, -(-total // (shards * bucket_bytes)))
    found = narrow.groupBy("_shard", "_h1", "_h2").agg(F.count("*").alias("_n"), F.max("size").alias("size"))
    hot = materialise(found.where((F.col("_n") > 1) & (F.col("_n") * F.col("size") * 4 > bucket_bytes)).select("_shard", "_h1", "_h2", "_n"))
    few = hot.count()  # at most four for each bucket
    plain = F.pmod("_h1", F.lit(buckets)).alias("_bucket")
    moved, numbers = dealt.select("*", plain), narrow.select("_shard", plain, "_h1", "_h2")
    if few:
        keys = hot.select("_h1", "_h2")
        keys = F.broadcast(keys) if few <= MAX_BROADCAST else keys
        one = moved.drop("_bucket").join(keys, ["_h1", "_h2"], "left_semi").dropDuplicates(["_h1", "_h2"]).join(hot.select("_h1", "_h2", "_n"), ["_h1", "_h2"])
        moved = moved.join(keys, ["_h1", "_h2"], "left_anti").unionByName(_copies(one, buckets, seed))
        numbers = numbers.join(keys, ["_h1", "_h2"], "left_anti").select("_shard", "_bucket").unionByName(_copies(hot, buckets, seed).select("_shard", "_bucket"))
    counts = materialise(numbers.groupBy("_shard", "_bucket").count())
    before = Window.partitionBy("_shard").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("_shard", F.col("_bucket").alias("bucket"), F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    tasks = min(shards * buckets, MAX_TASKS)
    at = F.pmod(F.col("_shard") * F.lit(buckets) + F.col("bucket"), F.lit(tasks)).cast("int")
    packed = moved.select(F.struct(*columns).alias("row"), "_grown", "_shard", F.col("_bucket").alias("bucket"))
    grouped = (packed.repartitionById(tasks, at) if tasks > 1 else packed).groupBy("_shard", "bucket")
    arrays = grouped.agg(F.sort_array(F.collect_list(F.struct("row", "_grown"))).alias("rows"))
    shuffled = arrays.select("_shard", "bucket", F.shuffle("rows", F.lit(seed)).alias("rows"))
    small = F.broadcast(offsets) if shards * buckets <= MAX_BROADCAST else offsets
    placed = shuffled.join(small, ["_shard", "bucket"]).select("_shard", "first", F.posexplode("rows").alias("pos", "r"))
    return placed.select(*[F.col("r.row")[c].alias(c) for c in columns], F.col("_shard").cast("int").alias("shard"), (F.col("first") + F.col("pos")).alias("slot"), F.col("r._grown").cast("int").alias("grown_shard"))


def write_shards(placed: DataFrame, path: str) -> None:
    """One folder a shard, rows in slot order within each file."""
    placed.sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
