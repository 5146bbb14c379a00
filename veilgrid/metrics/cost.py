"""Measured time and memory of an action: wall clock, the stages it ran, and the peak of Python's allocations on the driver."""

from __future__ import annotations

import time
import tracemalloc
import uuid
from collections.abc import Callable
from typing import Any

from pyspark.sql import SparkSession

#: Columns of a measurement.
COSTS = "wall_s double, task_s double, shuffle_bytes long, rows_read long, peak_task_bytes long, driver_peak_bytes long"


def timed(spark: SparkSession, action: Callable[[], Any]) -> tuple[Any, tuple]:
    """(result, measurement): sums over the stages of the jobs that the action started, as Spark's status store has them."""
    context, group = spark.sparkContext, f"timed-{uuid.uuid4().hex}"
    context.setJobGroup(group, "timed")
    tracemalloc.start()
    began = time.perf_counter()
    try:
        result = action()
        wall, peak = time.perf_counter() - began, tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
        context.setLocalProperty("spark.jobGroup.id", None)
        context.setLocalProperty("spark.job.description", None)
    scala, tracker = context._jsc.sc(), context.statusTracker()
    scala.listenerBus().waitUntilEmpty()
    stages = sorted({s for j in tracker.getJobIdsForGroup(group) if (job := tracker.getJobInfo(j)) for s in job.stageIds})
    task_ms = shuffle = rows = most = 0
    for s in stages:
        try:
            stage = scala.statusStore().lastStageAttempt(s)
        except Exception:  # a skipped stage has no attempt
            continue
        task_ms, shuffle, rows = task_ms + stage.executorRunTime(), shuffle + stage.shuffleWriteBytes(), rows + stage.inputRecords()
        most = max(most, stage.peakExecutionMemory())
    return result, (wall, task_ms / 1000, shuffle, rows, most, peak)
