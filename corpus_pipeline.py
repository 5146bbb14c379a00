"""A corpus pipeline of the operators in veilgrid.llm: rules, classifier, near-duplicates, packing."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from veilgrid.llm import isolation, packing, pu_classifier, simhash
from veilgrid.llm.common import ensure_checkpoint_dir
from veilgrid.llm.queries import tokenizer_files


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules keep."""
    return isolation.keep_good_rows(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier keeps."""
    return pu_classifier.keep_quality_rows(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near-duplicates, whatever the ids: the one with the smallest id, null ids last."""
    return simhash.keep_one_each(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the remaining documents with their ids, packed into sequences."""
    files = tokenizer_files()
    return packing.pack_documents(docs, files["json"], files["pattern"], with_ids=True)


STAGES = [("quality rules", quality_rules), ("quality classifier", quality_classifier), ("simhash near-dedup", near_duplicates), ("packing", packing_stage)]

#: The stages are a trained forest, a trained model, fingerprints and a tokenizer: no SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet in the shared folder and read again by the next."""
    ensure_checkpoint_dir(spark)
    base = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{k}")
        docs = spark.read.parquet(f"{base}/{k}")
    return docs
