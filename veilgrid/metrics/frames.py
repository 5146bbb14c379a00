"""Measures as DataFrame plans over histograms (cx, cy, mass)."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilgrid.metrics.transport import pointwise_errors, sinkhorn_cost as sinkhorn_array, sliced_wasserstein as sliced_array, wasserstein_exact


def paired(a: DataFrame, b: DataFrame) -> DataFrame:
    """(cx, cy, a, b), cells of either side, missing masses zero."""
    joined = a.withColumnRenamed("mass", "a").join(b.withColumnRenamed("mass", "b"), ["cx", "cy"], "full_outer")
    return joined.select("cx", "cy", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("b", F.lit(0.0)).alias("b"))


def pointwise(a: DataFrame, b: DataFrame, cells: int, smoothing: float = 1e-9) -> DataFrame:
    total = 1 + cells * smoothing
    p = paired(a, b).withColumns({"pa": (F.col("a") + smoothing) / total, "pb": (F.col("b") + smoothing) / total, "e": F.col("a") - F.col("b")})
    mid = (F.col("pa") + F.col("pb")) / 2
    part = lambda x: F.sum(F.col(x) * F.log(F.col(x) / mid))
    return p.agg(
        F.round(F.sum(F.abs("e")), 6).alias("l1"), F.round(F.avg(F.abs("e")), 6).alias("mae"), F.round(F.avg(F.col("e") * F.col("e")), 8).alias("mse"), F.round(0.5 * F.sum(F.abs("e")), 6).alias("tv"),
        F.round(F.sum(F.col("pa") * F.log(F.col("pa") / F.col("pb"))), 6).alias("kl"), F.round(0.5 * part("pa") + 0.5 * part("pb"), 6).alias("js"),
    )


def wasserstein_1d(a: DataFrame, b: DataFrame, p: int = 1) -> DataFrame:
    """(distance): W_p^p of two masses (t, mass) on the line.

    p = 1 sums gaps times the difference of the distribution functions; else both are cut at the same quantiles and
    pieces that overlap are joined. The inputs are reduced to positions, so one window over them is small.
    """
    if p == 1:
        both = a.withColumn("m", F.col("mass")).unionByName(b.withColumn("m", -F.col("mass"))).groupBy("t").agg(F.sum("m").alias("m"))
        order = Window.orderBy("t")
        steps = both.select((F.lead("t").over(order) - F.col("t")).alias("gap"), F.sum("m").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("f"))
        return steps.agg(F.sum(F.col("gap") * F.abs("f")).alias("distance"))
    cut = lambda h, n: h.select(F.col("t").alias(f"t{n}"), F.sum("mass").over(Window.orderBy("t").rowsBetween(Window.unboundedPreceding, 0)).alias(f"hi{n}"), F.col("mass").alias(f"m{n}")).withColumn(f"lo{n}", F.col(f"hi{n}") - F.col(f"m{n}"))
    x, y = cut(a, 1), cut(b, 2)
    overlap = F.least("hi1", "hi2") - F.greatest("lo1", "lo2")
    return x.join(y, overlap > 0).agg(F.sum(F.pow(F.abs(F.col("t1") - F.col("t2")), p) * overlap).alias("distance"))


def radon(a: DataFrame, b: DataFrame, angles: int = 64) -> DataFrame:
    """(k, t, a, b): masses of both histograms projected on direction 2 pi k / angles; cells are multiplied by the angles, nothing else is."""
    k = F.explode(F.sequence(F.lit(0), F.lit(angles - 1))).alias("k")
    p = paired(a, b).select("cx", "cy", "a", "b", k)
    theta = 2 * math.pi * F.col("k") / angles
    t = F.round(F.col("cx") * F.cos(theta) + F.col("cy") * F.sin(theta), 9) + 0
    return p.groupBy("k", t.alias("t")).agg(F.sum("a").alias("a"), F.sum("b").alias("b"))


def sliced_by_angle(a: DataFrame, b: DataFrame, angles: int = 64) -> DataFrame:
    """(k, w1) per direction: windows by angle run in parallel."""
    order = Window.partitionBy("k").orderBy("t")
    steps = radon(a, b, angles).select("k", (F.lead("t").over(order) - F.col("t")).alias("gap"), F.sum(F.col("a") - F.col("b")).over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("f"))
    return steps.groupBy("k").agg(F.sum(F.col("gap") * F.abs("f")).alias("w1"))


def sliced_wasserstein(a: DataFrame, b: DataFrame, angles: int = 64, normalise: bool = False) -> DataFrame:
    scale = 1 / angles if normalise else 2 * math.pi / angles
    return sliced_by_angle(a, b, angles).agg((F.sum("w1") * scale).alias("sw1"))


def sinkhorn_cost(a: DataFrame, b: DataFrame, d: int, reg: float, iterations: int) -> DataFrame:
    """Scaling rounds as relational sums; the kernel splits by axis, so each half step is two equi-joins of d^3 rows."""
    spark = a.sparkSession
    side = spark.range(d).select(F.col("id").cast("int").alias("i")).crossJoin(F.broadcast(spark.range(d).select(F.col("id").cast("int").alias("j"))))
    gap = F.pow((F.col("i") - F.col("j")).cast("double"), 2)
    kernel = side.select("i", "j", F.exp(-gap / reg).alias("k"), (gap * F.exp(-gap / reg)).alias("kc"))

    def apply(h, first="k", second="k"):
        rows = h.join(F.broadcast(kernel), h.cx == kernel.j).groupBy(F.col("i").alias("cx"), "cy").agg(F.sum(F.col("m") * F.col(first)).alias("m"))
        return rows.join(F.broadcast(kernel), rows.cy == kernel.j).groupBy("cx", F.col("i").alias("cy")).agg(F.sum(F.col("m") * F.col(second)).alias("m"))

    v = b.select("cx", "cy", F.lit(1.0).alias("m"))
    for _ in range(iterations):
        u = a.join(apply(v), ["cx", "cy"]).select("cx", "cy", (F.col("mass") / F.col("m")).alias("m"))
        v = b.join(apply(u), ["cx", "cy"]).select("cx", "cy", (F.col("mass") / F.col("m")).alias("m"))
    costs = apply(v, "kc", "k").unionByName(apply(v, "k", "kc")).groupBy("cx", "cy").agg(F.sum("m").alias("c"))
    return u.join(costs, ["cx", "cy"]).agg(F.sum(F.col("m") * F.col("c")).alias("cost"))


def grid_distances(a: DataFrame, b: DataFrame, d: int, exact: bool = True) -> DataFrame:
    """One row of all distances of two histograms over d x d cells, in one task."""
    def measure(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y = np.zeros(d * d), np.zeros(d * d)
        at = (pdf.cy * d + pdf.cx).to_numpy()
        x[at], y[at] = pdf.a, pdf.b
        w2 = wasserstein_exact(x, y, d) if exact else max(0.0, sinkhorn_array(x, y, d)) ** 0.5
        return pd.DataFrame([{"w2": w2, "sw1": sliced_array(x, y, d), **{k: v for k, v in pointwise_errors(x, y).items() if k in ("mae", "kl")}}])

    return paired(a, b).withColumn("one", F.lit(1)).groupBy("one").applyInPandas(measure, "w2 double, sw1 double, mae double, kl double")


def plan_cost(a: DataFrame, b: DataFrame, d: int, reg: float, rounds: int) -> DataFrame:
    """(cost) of the array form's plan after a fixed number of rounds, in one task."""
    def measure(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y = np.zeros(d * d), np.zeros(d * d)
        at = (pdf.cy * d + pdf.cx).to_numpy()
        x[at], y[at] = pdf.a, pdf.b
        return pd.DataFrame([{"cost": sinkhorn_array(x, y, d, reg, rounds, 0.0)}])

    return paired(a, b).withColumn("one", F.lit(1)).groupBy("one").applyInPandas(measure, "cost double")


def local_privacy(channel: DataFrame, n: int) -> DataFrame:
    """(lp) under a uniform prior: a self-join on the output cell. Rows are outputs x n^2, for small domains."""
    a, b = channel.alias("a"), channel.alias("b")
    dist = F.hypot(F.col("a.cx") - F.col("b.cx"), F.col("a.cy") - F.col("b.cy"))
    pairs = a.join(b, (F.col("a.ox") == F.col("b.ox")) & (F.col("a.oy") == F.col("b.oy"))).groupBy(F.col("a.ox").alias("ox"), F.col("a.oy").alias("oy")).agg(F.sum(F.col("a.prob") * F.col("b.prob") * dist).alias("part"))
    totals = channel.groupBy("ox", "oy").agg(F.sum("prob").alias("total"))
    return pairs.join(totals, ["ox", "oy"]).agg((F.sum(F.col("part") / F.col("total")) / n).alias("lp"))
