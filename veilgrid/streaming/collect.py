"""Collection of an unbounded flow of reports.

The stateless reporter runs before anything is kept; windows, sessions and joins carry watermarks, so state is bounded by
event time; a ledger adds up what each user has spent and refuses reports above a cap.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import DoubleType, StructField, StructType

from veilgrid.domain import GridSpec, assign_cells
from veilgrid.estimate import invert_counts
from veilgrid.mechanisms.area import AreaMechanism


def read_points(spark: SparkSession, folder: str, schema: StructType, files_per_batch: int = 1) -> DataFrame:
    """Parquet files that arrive in a folder, in order of arrival."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def report_stream(points: DataFrame, grid: GridSpec, mech: AreaMechanism, mode: str = "secure", keep: tuple[str, ...] = ("ts",), **options) -> DataFrame:
    """points(user_id, ts, x, y) -> (keep..., ox, oy): map only, append mode."""
    return mech.report(assign_cells(points, grid), mode, keep=keep, **options)


def windowed_counts(reports: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, ox, oy, n) by tumbling or sliding windows of ts; rows older than the watermark are dropped and counted by Spark."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return reports.withWatermark("ts", late).groupBy(window.alias("w"), "ox", "oy").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "ox", "oy", "n")


def user_sessions(points: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return points.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def one_report_each(points: DataFrame, late: str = "1 hour") -> DataFrame:
    """Repeats of a user within the watermark are dropped before they can be reported."""
    return points.withWatermark("ts", late).dropDuplicatesWithinWatermark(["user_id"])


def with_attributes(reports: DataFrame, static: DataFrame, keys: list[str]) -> DataFrame:
    """A stream against a static table of checked small size is a broadcast join without state."""
    return reports.join(static, keys, "left")


def clicks_before_purchases(events: DataFrame, within: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(purchase_id, click_id): both sides carry watermarks, so old state is dropped."""
    side = lambda kind, name: events.where(F.col("event_type") == kind).select(F.col("event_id").alias(f"{name}_id"), F.col("user_id").alias(f"{name}_user"), F.col("ts").alias(f"{name}_ts")).withWatermark(f"{name}_ts", late)
    p, c = side("purchase", "purchase"), side("click", "click")
    near = (F.col("click_ts") <= F.col("purchase_ts")) & (F.col("click_ts") >= F.col("purchase_ts") - F.expr(f"INTERVAL {within}"))
    return p.join(c, (F.col("purchase_user") == F.col("click_user")) & near).select("purchase_id", "click_id")


class BudgetLedger(StatefulProcessor):
    """Adds up the budgets of a user's reports in order; a report that would pass the cap is refused (accepted = false)."""

    def __init__(self, cap: float, ttl_ms: int | None = None):
        self.cap, self.ttl_ms = cap, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.spent = handle.getValueState("spent", StructType([StructField("eps", DoubleType())]), self.ttl_ms)

    def handleInputRows(self, key, rows, timerValues):  # noqa: N802, N803
        used = self.spent.get()[0] if self.spent.exists() else 0.0
        for pdf in rows:
            kept = []
            for eps in pdf.sort_values("ts").eps:
                fits = used + eps <= self.cap + 1e-12
                used += eps if fits else 0.0
                kept.append(fits)
            ordered = pdf.sort_values("ts")
            yield pd.DataFrame({"user_id": ordered.user_id, "ts": ordered.ts, "eps": ordered.eps, "accepted": kept, "spent": used})
        self.spent.update((used,))

    def close(self) -> None:
        pass


LEDGER_SCHEMA = "user_id long, ts timestamp, eps double, accepted boolean, spent double"


def ledger(requests: DataFrame, cap: float, ttl_ms: int | None = None) -> DataFrame:
    """requests(user_id, ts, eps) -> the same with accepted and the user's total so far. Needs the RocksDB state store."""
    return requests.groupBy("user_id").transformWithStateInPandas(statefulProcessor=BudgetLedger(cap, ttl_ms), outputStructType=LEDGER_SCHEMA, outputMode="Append", timeMode="ProcessingTime" if ttl_ms else "None")


class RunningEstimate:
    """foreachBatch sink: adds each batch's counts (outputs rows, not users) to a stored total and inverts it, starting from the last estimate.

    The total after a batch is a folder named by the batch's number, made from the one before: a batch that is offered again, after a
    failure or a restart from the query's checkpoint, writes the same total anew, so nothing is lost or counted twice. The two newest are kept.
    ``folder`` must be as durable as the query's checkpoint.
    """

    def __init__(self, mech: AreaMechanism, folder: str, on_update: Callable[[int, np.ndarray], None] | None = None, **options):
        self.mech, self.folder, self.options, self.on_update = mech, folder.rstrip("/"), options, on_update
        self.mass: np.ndarray | None = None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        counted = batch.groupBy("ox", "oy").agg(F.count("*").alias("n"))
        if batch_id:
            if not self._files(spark, batch_id - 1)[2]:
                raise RuntimeError(f"no total of batch {batch_id - 1} in {self.folder}: the counts before it would be lost")
            counted = counted.unionByName(spark.read.parquet(self._path(batch_id - 1))).groupBy("ox", "oy").agg(F.sum("n").alias("n"))
        counted.coalesce(1).write.mode("overwrite").parquet(self._path(batch_id))
        rows = {(r.ox, r.oy): r.n for r in spark.read.parquet(self._path(batch_id)).collect()}  # at most mech.outputs rows
        if batch_id > 1:
            files, old, there = self._files(spark, batch_id - 2)
            if there:
                files.delete(old, True)
        if rows:
            self.mass = invert_counts(self.mech, rows, start=self.mass, **self.options).mass
            if self.on_update:
                self.on_update(batch_id, self.mass)

    def _path(self, batch_id: int) -> str:
        return f"{self.folder}/total-{batch_id}"

    def _files(self, spark: SparkSession, batch_id: int):
        path = spark._jvm.org.apache.hadoop.fs.Path(self._path(batch_id))
        files = path.getFileSystem(spark._jsc.hadoopConfiguration())
        return files, path, files.exists(spark._jvm.org.apache.hadoop.fs.Path(path, "_SUCCESS"))
