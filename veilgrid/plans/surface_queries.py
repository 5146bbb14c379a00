"""Queries on the function surface and on costs: vectorised, grouped, co-grouped and mapped Python, area sampling, continuous estimates, cost table."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec, assign_cells
from veilgrid.estimate import count_reports, estimate_by, estimate_from_reports, invert_counts
from veilgrid.geometry import disk_stencil, grid_constants, grid_radius
from veilgrid.mechanisms import DiskMechanism, SubsetExponentialMechanism
from veilgrid.mechanisms.subset import default_size
from veilgrid.metrics.cost import COSTS, timed
from veilgrid.metrics.transport import wasserstein_exact
from veilgrid.noise import hash_uniform
from veilgrid.operators.sampling import draw_from, report_by_areas
from veilgrid.plans import sql_text as S
from veilgrid.plans.method_queries import _AROUND, _BUDGET_SQL, _SHAPES_SQL, _TOUCHED, ASKED_SQL, asked, by_row
from veilgrid.plans.method_queries import _subset_members as subset_members_sql
from veilgrid.registry import query, table
from veilgrid.sources.datasets import POINT_SETS, uniform_sql

HASH = {"mode": "hash", "unsafe_deterministic": True}
_UNIT = GridSpec(0.0, 0.0, 1.0, 1.0, 5)


def _cells(spark, sf, name="taxi_like", d=5):
    return assign_cells(POINT_SETS[name].read(spark, sf), POINT_SETS[name].grid(d))


_W = S.disk_weights(1, 3.5)
_BORDER = "SELECT dx, dy, 1 - s + s * exp(CAST(3.5 AS DOUBLE)) AS w FROM (" + S.stencil(1) + ") WHERE kind = 'border'"


@query("disk_report_areas", f"""SELECT kind, count(*) AS n FROM (SELECT CASE WHEN t < low THEN 'low' WHEN t < low + rim THEN 'border' ELSE 'pure' END AS kind
FROM (SELECT {uniform_sql('user_id', 0)} * (low + rim + high) AS t, low, rim FROM ({S.cells('taxi_like', 5)}), (SELECT (SELECT count(*) FROM ({S.outputs(5, 1)})) - (SELECT count(*) FROM ({S.stencil(1)})) AS low, (SELECT sum(w) FROM ({_BORDER})) AS rim, (SELECT count(*) FROM ({S.stencil(1)}) WHERE kind = 'pure') * exp(CAST(3.5 AS DOUBLE)) AS high))) GROUP BY kind""")
def disk_report_areas(spark, sf):
    """Reports by areas, counted by the area that their displacement lies in."""
    mech = DiskMechanism(3.5, _UNIT)
    out = report_by_areas(_cells(spark, sf), mech, hash_uniform(F.col("user_id"), 0), hash_uniform(F.col("user_id"), 1))
    kinds = F.broadcast(spark.createDataFrame([(c.dx, c.dy, c.kind) for c in mech.stencil.cells], "dx int, dy int, kind string"))
    moved = out.select((F.col("ox") - F.col("cx")).alias("dx"), (F.col("oy") - F.col("cy")).alias("dy"))
    return moved.join(kinds, ["dx", "dy"], "left").groupBy(F.coalesce("kind", F.lit("low")).alias("kind")).agg(F.count("*").alias("n"))


@query("weighted_draw", f"SELECT CAST(k AS INTEGER) AS k, count(*) AS n FROM (SELECT CASE WHEN u * 4 - floor(u * 4) < keep THEN at ELSE other END AS k FROM (SELECT {uniform_sql('event_id', 0)} AS u FROM events) JOIN (VALUES (0, CAST(0.4 AS DOUBLE), 3), (1, CAST(0.8 AS DOUBLE), 3), (2, CAST(0.8 AS DOUBLE), 3), (3, CAST(1 AS DOUBLE), 3)) v(at, keep, other) ON floor(u * 4) = at) GROUP BY k".replace(" at", " place").replace("(at,", "(place,"))
def weighted_draw(spark, sf):
    """Weights 1, 2, 2, 5 by the alias method."""
    return table(spark, sf, "events").select(draw_from([1.0, 2.0, 2.0, 5.0], hash_uniform(F.col("event_id"), 0)).alias("k")).groupBy("k").agg(F.count("*").alias("n"))


_B15 = grid_radius(3.5, 15)
_CONTINUOUS = f"""WITH k AS (SELECT CAST({_B15} AS DOUBLE) / 15 AS b), c AS (SELECT b, 1 / (pi() * b * b * exp(CAST(3.5 AS DOUBLE)) + 4 * b + 1) AS q FROM k),
t AS (SELECT p.*, c.b, c.q * (pi() * b * b + 4 * b + 1) AS background, (u / c.q - 1) / b AS strip, b * sqrt(w) * cos(2 * pi() * v) AS dx, b * sqrt(w) * sin(2 * pi() * v) AS dy FROM (SELECT user_id, (x - 0) / 500000 AS x, y / 2410 AS y, {uniform_sql('user_id', 0)} AS u, {uniform_sql('user_id', 1)} AS v, {uniform_sql('user_id', 2)} AS w FROM ({POINT_SETS['taxi_like'].sql})) p, c)
SELECT CASE WHEN u >= background THEN x + dx WHEN strip < 0 THEN v WHEN strip < 2 THEN strip - floor(strip) WHEN strip < 3 THEN -b * v WHEN strip < 4 THEN 1 + b * v WHEN dx > 0 THEN 1 + dx ELSE dx END AS rx,
CASE WHEN u >= background THEN y + dy WHEN strip < 0 THEN w WHEN strip < 1 THEN -b * v WHEN strip < 2 THEN 1 + b * v WHEN strip < 4 THEN strip - floor(strip) WHEN dy > 0 THEN 1 + dy ELSE dy END AS ry FROM t"""
_CONTINUOUS_COUNTS = f"SELECT ox, oy, count(*) AS n FROM (SELECT CAST(floor(rx * 15) AS INTEGER) AS ox, CAST(floor(ry * 15) AS INTEGER) AS oy FROM ({_CONTINUOUS})) SEMI JOIN ({S.outputs(15, _B15)}) USING (ox, oy) GROUP BY ox, oy"


@query("estimate_disk_continuous", f"SELECT cx, cy, round(mass, 6) AS mass FROM ({S.em_steps(S.channel(15, _B15, S.disk_weights(_B15, 3.5)), _CONTINUOUS_COUNTS, 225, 5)})")
def estimate_disk_continuous(spark, sf):
    """Continuous reports put into output cells and inverted by the grid channel, which approximates their law."""
    d = 15
    grid = GridSpec(0.0, 0.0, 1.0, 1.0, d)
    x0, y0, w, h = POINT_SETS["taxi_like"].domain
    scaled = POINT_SETS["taxi_like"].read(spark, sf).select("user_id", ((F.col("x") - x0) / w).alias("x"), ((F.col("y") - y0) / h).alias("y"))
    mech = DiskMechanism(3.5, grid)
    reports = DiskMechanism.report_continuous(scaled, 3.5, mech.b_hat / d, **HASH)
    cells = reports.select(F.floor(F.col("rx") * d).cast("int").alias("ox"), F.floor(F.col("ry") * d).cast("int").alias("oy"))
    inside = cells.join(F.broadcast(spark.createDataFrame(mech.output_list, "ox int, oy int")), ["ox", "oy"], "left_semi")
    return estimate_from_reports(inside, mech, max_iter=5, tol=-1.0).withColumn("mass", F.round("mass", 6))


def _w2_of(a, b, cx, cy, d=5):
    x, y = np.zeros(d * d), np.zeros(d * d)
    x[(cy * d + cx).to_numpy()], y[(cy * d + cx).to_numpy()] = a, b
    return wasserstein_exact(x, y, d)


@query("udaf_w2_by_part")
def udaf_w2_by_part(spark, sf):
    """A grouped-aggregate function: exact distance of each part's histogram from the whole's."""
    @F.pandas_udf("double")
    def w2(a: pd.Series, b: pd.Series, cx: pd.Series, cy: pd.Series) -> float:
        return _w2_of(a, b, cx, cy)

    counts = _cells(spark, sf).groupBy("part", "cx", "cy").agg(F.count("*").alias("n"))
    whole = counts.groupBy("cx", "cy").agg(F.sum("n").alias("m"))
    return counts.join(whole, ["cx", "cy"]).groupBy("part").agg(w2(F.col("n").cast("double"), F.col("m").cast("double"), F.col("cx"), F.col("cy")).alias("w2"))


@query("cogroup_truth_estimate")
def cogroup_truth_estimate(spark, sf):
    """Truth and estimate of each part met in one task."""
    points = POINT_SETS["taxi_like"].read(spark, sf)
    truth = _cells(spark, sf).groupBy("part", "cx", "cy").agg(F.count("*").alias("n"))
    estimate = estimate_by(points, POINT_SETS["taxi_like"].grid(5), DiskMechanism(3.5, _UNIT), ("part",), **HASH)

    def measure(key, t, e):
        x, y = np.zeros(25), np.zeros(25)
        x[(t.cy * 5 + t.cx).to_numpy()], y[(e.cy * 5 + e.cx).to_numpy()] = t.n, e.mass
        return pd.DataFrame([{"part": key[0], "users": int(t.n.sum()), "w2": wasserstein_exact(x, y, 5)}])

    return truth.groupBy("part").cogroup(estimate.groupBy("part")).applyInPandas(measure, "part string, users long, w2 double")


@query("map_in_pandas_subset", f"SELECT array_to_string(members, ',') AS members, count(*) AS n FROM ({subset_members_sql(2.0, 2, 'nearest', S.cells('taxi_like', 5))}) GROUP BY members")
def map_in_pandas_subset(spark, sf):
    """The subset sampler as a map over batches, from uniforms of each user."""
    mech = SubsetExponentialMechanism(2.0, _UNIT, 2)

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"members": list(mech.sample_from((pdf.cy * 5 + pdf.cx).to_numpy(), pdf[["u", "v"]].to_numpy()))})

    drawn = _cells(spark, sf).select("cx", "cy", hash_uniform(F.col("user_id"), 0).alias("u"), hash_uniform(F.col("user_id"), 1).alias("v"))
    sets = drawn.mapInPandas(run, "members array<int>").select(F.array_join(F.col("members").cast("array<string>"), ",").alias("members"))
    return sets.groupBy("members").agg(F.count("*").alias("n"))


@query("udf_contrast", "SELECT event_id, CAST(least(floor(value / 60), 4) AS INTEGER) AS built_in, CAST(least(floor(value / 60), 4) AS INTEGER) AS by_arrow FROM events")
def udf_contrast(spark, sf):
    """A cell by built-in functions and by an Arrow-batched scalar function; only for contrast."""
    @F.udf(returnType="int", useArrow=True)
    def cell(v):
        return min(math.floor(v / 60), 4)

    return table(spark, sf, "events").select("event_id", F.least(F.floor(F.col("value") / 60), F.lit(4)).cast("int").alias("built_in"), cell("value").alias("by_arrow"))


_SIDES_SQL = "CAST(5 * (1 + l_linenumber % 4) AS INTEGER) AS d"


@query("cost_table", f"""WITH shapes AS MATERIALIZED {_SHAPES_SQL.format(ASKED_SQL.format(f'{_BUDGET_SQL}, {_SIDES_SQL}'))}
SELECT d, eps, n, b AS b_hat, stencil_cells, outputs, CAST(d * d AS BIGINT) * outputs AS dense_step, CAST(d * d AS BIGINT) * stencil_cells AS stencil_step, CAST(least(d * d, greatest(1, floor(d * d / exp(eps) + 0.5))) AS INTEGER) AS subset_size FROM shapes
JOIN (SELECT d, b, count(DISTINCT dx * 1000003 + dy) AS stencil_cells, count(DISTINCT (x + dx) * 1000003 + y + dy) AS outputs FROM (SELECT DISTINCT d, b FROM shapes), {_AROUND}, unnest(range(d)) u(x), unnest(range(d)) w(y) WHERE {_TOUCHED} GROUP BY d, b) USING (d, b)""")
def cost_table(spark, sf):
    """Sizes that set the costs of what line items ask for: cells looked at per report, outputs counted, work of a dense and of a stencil EM step, the subset size."""
    def sizes(d, eps):
        b = grid_radius(eps, d)
        cells, m = len(disk_stencil(b).cells), grid_constants(d, b, eps).outputs
        return b, cells, m, d * d * m, d * d * cells, default_size(eps, d * d)

    schema = "b_hat int, stencil_cells long, outputs long, dense_step long, stencil_step long, subset_size int"
    return asked(spark, sf, eps="q / 10", d="CAST(5 * (1 + line % 4) AS INT)").withColumn("at", by_row(sizes, schema)("d", "eps")).select("d", "eps", "n", "at.*")


@query("explain_report")
def explain_report(spark, sf):
    """What the count of reports plans: shuffles, a filter that reaches the scan, Python; and what it counts."""
    counts = count_reports(DiskMechanism(3.5, _UNIT).report(_cells(spark, sf), **HASH))
    plan = counts._jdf.queryExecution().executedPlan().toString()
    facts = [F.lit(plan.count("Exchange")).alias("exchanges"), F.lit("PushedFilters: [IsNotNull" in plan).alias("pushed"), F.lit("Python" in plan).alias("python")]
    return counts.agg(F.count("*").alias("cells"), F.sum("n").alias("reports")).select(*facts, "cells", "reports")


@query("measured_costs")
def measured_costs(spark, sf):
    """Measured wall time, task time, shuffle, rows and memory of collecting reports, and of each form of inversion, on two grids."""
    rows = []
    for d in (5, 15):
        mech, grid = DiskMechanism(3.5, GridSpec(0.0, 0.0, 1.0, 1.0, d)), POINT_SETS["taxi_big"].grid(d)
        cells = assign_cells(POINT_SETS["taxi_big"].read(spark, sf), grid)
        counted, cost = timed(spark, lambda: count_reports(mech.report(cells, **HASH)).collect())
        rows.append(("report and count", d, mech.outputs, 0, *cost))
        counts = {(r.ox, r.oy): r.n for r in counted}
        for method in ("dense", "stencil", "fft"):
            fit, cost = timed(spark, lambda: invert_counts(mech, counts, 50, -1.0, method=method))
            rows.append((f"inversion, {method}", d, mech.outputs, fit.iterations, *cost))
    return spark.createDataFrame(rows, f"step string, d int, outputs long, iterations int, {COSTS}")


@query("histogram_map_display", f"SELECT part, CAST(count(*) AS BIGINT) AS cells, CAST(sum(n) AS BIGINT) AS users FROM (SELECT part, cx, cy, count(*) AS n FROM ({S.cells('taxi_like', 5)}) GROUP BY ALL) GROUP BY part")
def histogram_map_display(spark, sf):
    """A histogram as one map column per part, as reports show it."""
    counts = _cells(spark, sf).groupBy("part", (F.col("cy") * 5 + F.col("cx")).alias("cell")).agg(F.count("*").alias("n"))
    maps = counts.groupBy("part").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("cell", "n")))).alias("m"))
    return maps.select("part", F.size("m").cast("long").alias("cells"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("users"))

