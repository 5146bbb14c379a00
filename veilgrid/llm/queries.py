"""The registered queries of this subpackage: each operator over its whole intended table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.llm import bpe, isolation, license_scan, lsh_forest, merkle, packing, pu_classifier, sharding, simhash, url_filter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_files():
    """Paths of the public vocabulary files and the splitting pattern."""
    import public_tokenizers as public

    return {"json": public.path("byte_bpe_50k.json"), "ranks": public.path("byte_bpe_50k.tiktoken"), "pattern": public.PATTERN}


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op2_lsh_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lsh_forest.nearest_neighbours(_table(spark, sf_dir, "embeddings"), lambda vec_id: vec_id % 100 == 0)


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(_table(spark, sf_dir, "pages"), url_filter.labelled_urls(spark))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts are placed; the checksum is taken from the placed ones."""
    text = F.col("text")
    rows = _table(spark, sf_dir, "documents").select("doc_id", sharding.text_size(text).alias("size"), "text")
    placed = sharding.shuffle_into_shards(rows, "doc_id", "size")
    return placed.select("doc_id", "size", F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"), F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(_table(spark, sf_dir, "documents"))


#: Records of an archive in the audit query.
AUDITED_RECORDS = 256


def op6_merkle_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as WARC records against a replica with planted faults: flipped bytes, cut records, lost records (those after one in its archive
    have moved) and records that only the replica has."""
    pages = _table(spark, sf_dir, "pages")
    body, page = F.col("html"), F.col("page_id")
    flipped = F.concat(F.lit("~"), F.substring(body, 2, 1 << 30))
    harmed = F.when(page % 997 == 5, flipped).when(page % 1499 == 7, F.substring(body, 1, 100)).otherwise(body)
    whole = pages.select(page, merkle.warc_record(F.col("url"), body).alias("record"))
    kept = pages.where((page % 1601 != 203) | page.isNull()).select(page, merkle.warc_record(F.col("url"), harmed).alias("record"))
    added = pages.where(page % 2003 == 11).select((-1 - page).alias("page_id"), merkle.warc_record(F.col("url"), body).alias("record"))
    return merkle.audit_replicas(whole, kept.unionByName(added), "page_id", "record", AUDITED_RECORDS)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return isolation.quality_rules(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ids themselves are placed; the checksum is taken from the placed ones."""
    files = tokenizer_files()
    return packing.placed_checksums(packing.pack_documents(_table(spark, sf_dir, "documents"), files["json"], files["pattern"], with_ids=True))


def op9_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = tokenizer_files()
    return bpe.round_trip(_table(spark, sf_dir, "documents"), files["ranks"], files["pattern"])


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pu_classifier.quality_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def queries():
    from corpus_pipeline import run

    own = (op1_simhash, op2_lsh_forest, op3_url_filter, op4_sharding, op5_license_scan, op6_merkle_audit, op7_quality_rules, op8_packing, op9_bpe_round_trip, op10_quality_classifier)
    return {f.__name__: f for f in own} | {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    from veilgrid.llm import oracles

    return oracles.ORACLES
