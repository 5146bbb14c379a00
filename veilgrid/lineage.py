"""Reliable checkpoints: lineage is cut into the shared folder that the cluster names."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder in spark.checkpoint.dir. Where none is named a local session gets a temporary one; a cluster gets an error,
    since its executors don't share the driver's disk."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not (context.master or "").split("[")[0] == "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))


#: Rows of a narrow table that one file of a checkpoint holds at least, where a bound of the rows is given.
FILE_ROWS = 1 << 18


def materialise(df: DataFrame, rows: int | None = None) -> DataFrame:
    """A stable copy that survives lost executors. With a bound of its rows, small tables are written to few files."""
    ensure_checkpoint_dir(df.sparkSession)
    return (df if rows is None else df.coalesce(max(1, -(-rows // FILE_ROWS)))).checkpoint(eager=True)
