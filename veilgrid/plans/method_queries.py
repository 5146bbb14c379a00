"""Registered queries: domain and geometry, mechanisms, inversion, baselines and measures, each with its SQL."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilgrid import geometry as geo
from veilgrid.domain import GridSpec, assign_cells, distance_set, fill_histogram, input_cells, output_cells, true_histogram
from veilgrid.em import clip_normalise, em_frame, em_stencil_frame, project_simplex
from veilgrid.estimate import count_reports, estimate_axes, estimate_by, estimate_distribution, estimate_from_reports, to_histogram
from veilgrid.mechanisms import AxisWaveMechanism, CategoricalOracle, DecayMechanism, DiskMechanism, SquareWave, SubsetExponentialMechanism
from veilgrid.lineage import materialise
from veilgrid.metrics import frames, transport
from veilgrid.noise import hash_uniform
from veilgrid.plans import sql_text as S
from veilgrid.privacy import local_privacy, local_privacy_subset, match_privacy, privacy_loss
from veilgrid.registry import ORACLES, QUERIES, query, table
from veilgrid.sources.datasets import POINT_SETS, event_points, uniform_sql

#: Budgets and sides of the experiments.
EPS = (0.7, 1.4, 2.1, 2.8, 3.5, 5.0, 6.0, 7.0, 8.0, 9.0)
FACTORS = (0.33, 0.67, 1.0, 1.33, 1.67)
HASH = {"mode": "hash", "unsafe_deterministic": True}
_EPS_SQL = "(SELECT CAST(unnest([" + ", ".join(map(str, EPS)) + "]) AS DOUBLE) AS eps)"


def points(spark, sf, name: str) -> DataFrame:
    return POINT_SETS[name].read(spark, sf)


def unit_grid(d: int) -> GridSpec:
    return GridSpec(0.0, 0.0, 1.0, 1.0, d)


def r6(c, digits: int = 6):
    return F.round(c, digits)


def eps_frame(spark):
    return spark.createDataFrame([(e,) for e in EPS], "eps double")


#: Line items as collections that are asked for: a tenth of the quantity is the budget (or its whole part the radius), the line number the side.
ASKED_SQL = "(SELECT {}, count(*) AS n FROM lineitem WHERE l_quantity > 0 AND l_quantity < CAST('inf' AS DOUBLE) AND l_linenumber > 0 GROUP BY ALL)"
_BUDGET_SQL, _SIDE_SQL, _RADIUS_SQL = "l_quantity / 10 AS eps", "CAST(l_linenumber AS INTEGER) AS d", "CAST(floor(l_quantity) AS INTEGER) AS b"


def asked(spark, sf, **columns) -> DataFrame:
    """(columns..., n): what line items ask for, each once, and by how many; ``columns`` are expressions of q (quantity) and line."""
    rows = table(spark, sf, "lineitem").select(F.col("l_quantity").alias("q"), F.col("l_linenumber").alias("line"))
    rows = rows.where((F.col("q") > 0) & (F.col("q") < float("inf")) & (F.col("line") > 0))
    return rows.groupBy(*[F.expr(e).alias(c) for c, e in columns.items()]).agg(F.count("*").alias("n"))


def by_row(function, schema: str):
    """A function of plain numbers as an Arrow-batched one that gives a struct; for the few distinct rows of an aggregate."""
    names = [c.split()[0] for c in schema.split(", ")]

    @F.pandas_udf(schema)
    def run(*columns: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([function(*[v.item() for v in row]) for row in zip(*[c.to_numpy() for c in columns], strict=True)], columns=names)

    return run


def inhabited(spark, sf, name: str, d: int) -> DataFrame:
    """(cx, cy, n): the cells that points lie in."""
    return assign_cells(points(spark, sf, name), POINT_SETS[name].grid(d)).groupBy("cx", "cy").agg(F.count("*").alias("n"))


def inhabited_sql(name: str, d: int) -> str:
    return f"(SELECT cx, cy, count(*) AS n FROM ({S.cells(name, d)}) GROUP BY cx, cy)"


# ---- domain ----

@query("grid_bounds", "SELECT part, min(x) AS lo_x, max(x) AS hi_x, min(y) AS lo_y, max(y) AS hi_y, count(*) AS n FROM (" + POINT_SETS["taxi_like"].sql + ") GROUP BY part")
def grid_bounds(spark, sf):
    return points(spark, sf, "taxi_like").groupBy("part").agg(F.min("x").alias("lo_x"), F.max("x").alias("hi_x"), F.min("y").alias("lo_y"), F.max("y").alias("hi_y"), F.count("*").alias("n"))


@query("cell_assign", S.cells("crime_like", 15))
def cell_assign(spark, sf):
    return assign_cells(points(spark, sf, "crime_like"), POINT_SETS["crime_like"].grid(15)).select("user_id", "part", "cx", "cy")


def _register_hist(name: str, d: int):
    sql = f"SELECT g.cx, g.cy, round(coalesce(h.n, 0) / CAST((SELECT count(*) FROM ({S.cells(name, d)})) AS DOUBLE), 9) AS mass FROM ({S.grid_cells(d)}) g LEFT JOIN (SELECT cx, cy, count(*) AS n FROM ({S.cells(name, d)}) GROUP BY cx, cy) h ON h.cx = g.cx AND h.cy = g.cy"
    query(f"true_hist_{name}", sql)(lambda spark, sf: true_histogram(points(spark, sf, name), POINT_SETS[name].grid(d)).withColumn("mass", r6(F.col("mass"), 9)))


for _name in POINT_SETS:
    _register_hist(_name, 15)
QUERIES["true_hist"], ORACLES["true_hist"] = QUERIES["true_hist_taxi_like"], ORACLES["true_hist_taxi_like"]


@query("out_cells", S.outputs(15, 3))
def out_cells(spark, sf):
    return output_cells(spark, unit_grid(15), geo.disk_stencil(3))


@query("distance_set", f"SELECT c.cx, c.cy, c.n, o.ox, o.oy FROM {inhabited_sql('crime_like', 8)} c, ({S.outputs(8, 3)}) o WHERE (o.ox - c.cx) * (o.ox - c.cx) + (o.oy - c.cy) * (o.oy - c.cy) <= 6.25")
def distance_sets(spark, sf):
    """Cells near each cell that events lie in."""
    centres = inhabited(spark, sf, "crime_like", 8)
    return distance_set(output_cells(spark, unit_grid(8), geo.disk_stencil(3)), centres, 2.5).join(centres, ["cx", "cy"])


@query("radius_table", f"SELECT eps, side, round({S.radius('eps', 'side')}, 9) AS radius FROM {_EPS_SQL}, (SELECT CAST(unnest([1, 15]) AS DOUBLE) AS side)")
def radius_table(spark, sf):
    sides = spark.createDataFrame([(1.0,), (15.0,)], "side double")
    return eps_frame(spark).crossJoin(F.broadcast(sides)).select("eps", "side", r6(geo.optimal_radius_col(F.col("eps"), F.col("side")), 9).alias("radius"))


def _bound_frame(spark):
    return eps_frame(spark).crossJoin(F.broadcast(spark.range(1, 31).select((F.col("id") / 20).alias("b")))).crossJoin(F.broadcast(spark.createDataFrame([(1.0,), (2.0,)], "side double")))


_BOUND = "(SELECT eps, CAST(r.range AS DOUBLE) / 20 AS b, side FROM " + _EPS_SQL + ", range(1, 31) r, (SELECT CAST(unnest([1, 2]) AS DOUBLE) AS side))"
_H = "pi() * b * b * exp(eps)"
_R = "(4 * side * b + side * side)"
_G = f"(log2((pi() * b * b + {_R}) / ({_H} + {_R})) + {_H} * eps * log2(exp(1)) / ({_H} + {_R}))"


@query("info_bound_sweep", f"SELECT eps, b, side, round({_G}, 8) AS bits FROM {_BOUND}")
def info_bound_sweep(spark, sf):
    return _bound_frame(spark).select("eps", "b", "side", r6(geo.info_bound_col(F.col("b"), F.col("eps"), F.col("side")), 8).alias("bits"))


@query("info_best_radius", f"SELECT eps, side, any_value(n) AS n, arg_max(b, bits) AS best_b FROM (SELECT eps, b, side, n, round({_G}, 12) AS bits FROM (SELECT eps, CAST(d AS DOUBLE) AS side, n, CAST(r.range AS DOUBLE) / 20 AS b FROM {ASKED_SQL.format(f'{_BUDGET_SQL}, {_SIDE_SQL}')}, range(1, 31) r)) GROUP BY eps, side")
def info_best_radius(spark, sf):
    """The best of thirty radii for each budget and side that line items ask for."""
    tried = asked(spark, sf, eps="q / 10", side="CAST(line AS DOUBLE)").crossJoin(F.broadcast(spark.range(1, 31).select((F.col("id") / 20).alias("b"))))
    scored = tried.select("eps", "b", "side", "n", r6(geo.info_bound_col(F.col("b"), F.col("eps"), F.col("side")), 12).alias("bits"))
    return scored.groupBy("eps", "side").agg(F.first("n").alias("n"), F.max_by("b", "bits").alias("best_b"))


_M1, _M2 = "(exp(eps) - 1 - eps)", "(1 - exp(eps) + eps * exp(eps))"


@query("info_grad", f"SELECT eps, b, side, round(2 * pi() * side * b * (2 * b + side) * (side * side * {_M2} + 4 * side * {_M2} * b - pi() * exp(eps) * {_M1} * b * b) / ((pi() * b * b + {_R}) * ({_H} + {_R}) * ({_H} + {_R}) * ln(2)), 8) AS slope FROM {_BOUND}")
def info_grad(spark, sf):
    return _bound_frame(spark).select("eps", "b", "side", r6(geo.info_gradient_col(F.col("b"), F.col("eps"), F.col("side")), 8).alias("slope"))


@query("radius_grid_sweep", f"SELECT eps, d, factor, CAST(floor({S.radius('eps')} * factor * d) AS INTEGER) AS b_hat FROM {_EPS_SQL}, (SELECT CAST(unnest([1, 2, 3, 4, 5, 10, 15, 20]) AS INTEGER) AS d), (SELECT CAST(unnest([0.33, 0.67, 1, 1.33, 1.67]) AS DOUBLE) AS factor)")
def radius_grid_sweep(spark, sf):
    rows = [(e, d, f, geo.grid_radius(e, d, f)) for e in EPS for d in (1, 2, 3, 4, 5, 10, 15, 20) for f in FACTORS]
    return spark.createDataFrame(rows, "eps double, d int, factor double, b_hat int")


# ---- geometry ----

def _per_b(statement, bs):
    return " UNION ALL ".join(f"SELECT {b} AS b, * FROM ({statement(b)})" for b in bs)


@query("stencil", _per_b(lambda b: f"SELECT dx, dy, kind, round(s, 9) AS s FROM ({S.stencil(b)})", range(0, 9)))
def stencil_query(spark, sf):
    rows = [(b, c.dx, c.dy, c.kind, c.share) for b in range(0, 9) for c in geo.disk_stencil(b).cells]
    return spark.createDataFrame(rows, "b int, dx int, dy int, kind string, s double").withColumn("s", r6(F.col("s"), 9))


_AROUND = "unnest(range(-b - 1, b + 2)) s(dx), unnest(range(-b - 1, b + 2)) t(dy)"
_TOUCHED = f"({S.crossed('dx', 'dy', 'b')} OR dx = 0 AND dy = 0)"


@query("area_low", f"SELECT b, CAST(5 AS INTEGER) AS d, n, count(DISTINCT (cx + dx) * 1000003 + cy + dy) - count(DISTINCT dx * 1000003 + dy) AS area FROM (SELECT b, n, CAST(dx AS BIGINT) AS dx, CAST(dy AS BIGINT) AS dy FROM {ASKED_SQL.format(_RADIUS_SQL)}, {_AROUND}), ({S.grid_cells(5)}) WHERE {_TOUCHED} GROUP BY b, n")
def area_low(spark, sf):
    """Low area of 5 x 5 cells for each radius that line items ask for."""
    return asked(spark, sf, b="CAST(floor(q) AS INT)").select("b", F.lit(5).alias("d"), "n", geo.pure_low_area(F.lit(5).cast("long"), F.col("b").cast("long")).alias("area"))


@query("octant_border", _per_b(lambda b: f"SELECT dx, dy, round(s, 9) AS s FROM ({S.stencil(b)}) WHERE kind = 'border' AND dy > 0 AND dx > dy", range(1, 13)))
def octant_border(spark, sf):
    rows = [(b, x, y, geo.border_share(x, y, b)) for b in range(1, 13) for x, y in geo.octant_border(b)]
    return spark.createDataFrame(rows, "b int, dx int, dy int, s double").withColumn("s", r6(F.col("s"), 9))


@query("octant_pure", _per_b(lambda b: f"SELECT count(*) AS cells FROM ({S.stencil(b)}) WHERE kind = 'pure' AND dy > 0 AND dx > dy", range(1, 13)))
def octant_pure(spark, sf):
    return spark.createDataFrame([(b, geo.octant_pure_count(b)) for b in range(1, 13)], "b int, cells long")


@query("diagonal_share", f"""SELECT b, n, count(*) FILTER (2 * k * k <= b * b) AS whole, round(coalesce(sum({S.share('k', 'k', 'b')}) FILTER (2 * k * k > b * b AND {S.crossed('k', 'k', 'b')}), 0), 9) AS share
FROM (SELECT CAST(b AS BIGINT) AS b, n, unnest(range(1, CAST(b AS BIGINT) + 2)) AS k FROM {ASKED_SQL.format(_RADIUS_SQL)}) GROUP BY b, n""".replace("SELECT b, n, count", "SELECT CAST(b AS INTEGER) AS b, n, count", 1))
def diagonal_share(spark, sf):
    """The diagonal of each disk that line items ask for."""
    found = asked(spark, sf, b="CAST(floor(q) AS INT)").withColumn("at", by_row(geo.diagonal_cells, "whole long, share double")("b"))
    return found.select("b", "n", "at.whole", r6(F.col("at.share"), 9).alias("share"))


_FLOOR_RADIUS = f"CAST(floor({S.radius('eps')} * d) AS INTEGER)"
_SHAPES_SQL = f"(SELECT d, eps, n, {_FLOOR_RADIUS} AS b FROM {{}})"


@query("grid_constants", f"""SELECT d, b, eps, n, shrink, m, round(high, 8) AS high, round(exp(eps) / (high * exp(eps) + m - high), 10) AS p, round(1 / (high * exp(eps) + m - high), 10) AS q
FROM (SELECT d, b, eps, n, sum(CASE WHEN dx * dx + dy * dy <= b * b THEN 1 WHEN shrink THEN {S.share('dx', 'dy', 'b')} ELSE 0 END) AS high, shrink FROM {_SHAPES_SQL.format(ASKED_SQL.format(f'{_BUDGET_SQL}, {_SIDE_SQL}'))}, {_AROUND}, (VALUES (true), (false)) v(shrink) WHERE {_TOUCHED} GROUP BY d, b, eps, n, shrink)
JOIN (SELECT d, b, count(DISTINCT (x + dx) * 1000003 + y + dy) AS m FROM (SELECT DISTINCT d, b FROM {_SHAPES_SQL.format(ASKED_SQL.format(f'{_BUDGET_SQL}, {_SIDE_SQL}'))}), {_AROUND}, unnest(range(d)) u(x), unnest(range(d)) w(y) WHERE {_TOUCHED} GROUP BY d, b) USING (d, b)""")
def grid_constants(spark, sf):
    """Constants of the disk for each budget and side that line items ask for, with and without shrinkage."""
    def constants(d, eps, shrink):
        b = geo.grid_radius(eps, d)
        c = geo.grid_constants(d, b, eps, shrink)
        return b, c.outputs, c.high, c.p, c.q

    shapes = asked(spark, sf, eps="q / 10", d="CAST(line AS INT)").withColumn("shrink", F.explode(F.array(F.lit(True), F.lit(False))))
    frame = shapes.withColumn("at", by_row(constants, "b int, m long, high double, p double, q double")("d", "eps", "shrink")).select("d", "at.b", "eps", "n", "shrink", "at.m", "at.high", "at.p", "at.q")
    return frame.withColumns({"high": r6(F.col("high"), 8), "p": r6(F.col("p"), 10), "q": r6(F.col("q"), 10)})


@query("continuous_constants", f"""SELECT eps, n, round(b, 8) AS b, round(exp(eps) / (pi() * b * b * exp(eps) + 4 * b + 1), 8) AS disk_p, round(1 / (pi() * b * b * exp(eps) + 4 * b + 1), 8) AS disk_q, round(eps * eps / (2 * pi() * (exp(eps) - 1 - eps) * b * b + 4 * eps * eps * b + eps * eps), 8) AS decay_q FROM (SELECT eps, n, {S.radius('eps')} AS b FROM {ASKED_SQL.format(_BUDGET_SQL)})""")
def continuous_constants(spark, sf):
    """Constants of the continuous mechanisms for each budget that line items ask for."""
    def constants(eps):
        b = geo.optimal_radius(eps)
        return b, *geo.continuous_constants("disk", b, eps), geo.continuous_constants("decay", b, eps)[1]

    found = asked(spark, sf, eps="q / 10").withColumn("at", by_row(constants, "b double, disk_p double, disk_q double, decay_q double")("eps"))
    return found.select("eps", "n", *[r6(F.col(f"at.{c}"), 8).alias(c) for c in ("b", "disk_p", "disk_q", "decay_q")])


@query("polar", f"SELECT user_id, round(sqrt(x * x + y * y), 6) AS r, round(atan2(y, x), 6) AS theta, round(sqrt(x * x + y * y) * cos(atan2(y, x)), 6) + 0 AS x_back FROM ({POINT_SETS['normal_nat'].sql})")
def polar(spark, sf):
    p = points(spark, sf, "normal_nat").withColumns({"r": F.hypot("x", "y"), "theta": F.atan2("y", "x")})
    return p.select("user_id", r6(F.col("r")).alias("r"), r6(F.col("theta")).alias("theta"), (r6(F.col("r") * F.cos("theta")) + 0).alias("x_back"))


@query("p_norms", "SELECT vec_id, round(list_sum(list_transform(v, lambda x: abs(x))), 6) AS n1, round(sqrt(list_sum(list_transform(v, lambda x: x * x))), 6) AS n2, round(pow(list_sum(list_transform(v, lambda x: abs(x * x * x))), 1 / CAST(3 AS DOUBLE)), 6) AS n3, round(list_max(list_transform(v, lambda x: abs(x))), 6) AS n_max, round(list_sum(list_transform(range(1, 64), lambda i: v[i] * v[i + 1])), 6) AS neighbour_dot FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)")
def p_norms(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    total = lambda arr: F.aggregate(arr, F.lit(0.0), lambda a, x: a + x)
    norm = lambda p: F.pow(total(F.transform("v", lambda x: F.pow(F.abs(x), p))), 1.0 / p)
    shifted = F.zip_with(F.slice("v", 1, 63), F.slice("v", 2, 63), lambda a, b: a * b)
    return e.select("vec_id", r6(norm(1)).alias("n1"), r6(norm(2)).alias("n2"), r6(norm(3)).alias("n3"), r6(F.array_max(F.transform("v", lambda x: F.abs(x)))).alias("n_max"), r6(total(shifted)).alias("neighbour_dot"))


# ---- mechanisms ----

def _mechs(d):
    g = unit_grid(d)
    return {"disk": DiskMechanism(3.5, g), "disk_noshrink": DiskMechanism(3.5, g, shrink=False), "decay": DecayMechanism(3.5, g), "decay_center": DecayMechanism(3.5, g, profile="center")}


def _weights_sql(kind, b, eps=3.5):
    return {"disk": S.disk_weights(b, eps), "disk_noshrink": S.disk_weights(b, eps, False), "decay": S.ring_weights(b, eps), "decay_center": S.center_weights(b, eps)}[kind]


def _register_report(kind: str, name: str, d: int, key: str):
    b = geo.grid_radius(3.5, d)

    def run(spark, sf):
        mech = _mechs(d)[kind]
        return count_reports(mech.report(assign_cells(points(spark, sf, name), POINT_SETS[name].grid(d)), keep=("part",), **HASH), ("part",))

    query(key, f"SELECT part, CAST(ox AS INTEGER) AS ox, CAST(oy AS INTEGER) AS oy, count(*) AS n FROM ({S.reports(name, d, b, _weights_sql(kind, b))}) GROUP BY part, ox, oy")(run)


for _kind, _key in (("disk", "disk_report"), ("disk_noshrink", "disk_noshrink_report"), ("decay", "decay_report"), ("decay_center", "decay_center_report")):
    _register_report(_kind, "taxi_like", 15, _key)
_register_report("disk", "taxi_big", 15, "disk_report_volume")
_register_report("disk", "crime_like", 5, "disk_report_small")


@query("disk_channel", f"SELECT cx, cy, n, ox, oy, round(prob, 9) AS prob FROM ({S.channel(5, 1, S.disk_weights(1, 3.5))}) JOIN {inhabited_sql('taxi_like', 5)} USING (cx, cy)")
def disk_channel(spark, sf):
    """The channel's rows for the cells that orders lie in, with their numbers."""
    return DiskMechanism(3.5, unit_grid(5)).channel(spark).join(inhabited(spark, sf, "taxi_like", 5), ["cx", "cy"]).withColumn("prob", r6(F.col("prob"), 9))


@query("decay_channel", f"SELECT cx, cy, n, ox, oy, round(prob, 9) AS prob FROM ({S.channel(6, 2, S.ring_weights(2, 2.0))}) JOIN {inhabited_sql('crime_like', 6)} USING (cx, cy)")
def decay_channel(spark, sf):
    """The channel's rows for the cells that events lie in, with their numbers."""
    return DecayMechanism(2.0, unit_grid(6), 2).channel(spark).join(inhabited(spark, sf, "crime_like", 6), ["cx", "cy"]).withColumn("prob", r6(F.col("prob"), 9))


@query("ldp_ratio", f"SELECT ox, oy, round(max(prob) / min(prob), 6) AS ratio, max(prob) / min(prob) <= exp(CAST(3.5 AS DOUBLE)) * (1 + 1e-9) AS private FROM ({S.channel(5, 1, S.disk_weights(1, 3.5))}) GROUP BY ox, oy")
def ldp_ratio(spark, sf):
    ratio = F.max("prob") / F.min("prob")
    return DiskMechanism(3.5, unit_grid(5)).channel(spark).groupBy("ox", "oy").agg(r6(ratio).alias("ratio"), (ratio <= math.exp(3.5) * (1 + 1e-9)).alias("private"))


_B35 = geo.optimal_radius(3.5)
_Q35 = geo.continuous_constants("disk", _B35, 3.5)[1]
_SCALED = f"SELECT user_id, (x - 0) / 500000 AS x, y / 2410 AS y, {uniform_sql('user_id', 0)} AS u, {uniform_sql('user_id', 1)} AS v, {uniform_sql('user_id', 2)} AS w FROM ({POINT_SETS['taxi_like'].sql})"


@query("disk_continuous", f"""WITH k AS (SELECT b, 1 / (pi() * b * b * exp(CAST(3.5 AS DOUBLE)) + 4 * b + 1) AS q FROM (SELECT {S.radius('CAST(3.5 AS DOUBLE)')} AS b)),
t AS (SELECT p.*, k.b, k.q * (pi() * b * b + 4 * b + 1) AS background, (u / (k.q * (pi() * b * b + 4 * b + 1)) * (pi() * b * b + 4 * b + 1) - 1) / b AS strip, b * sqrt(w) * cos(2 * pi() * v) AS dx, b * sqrt(w) * sin(2 * pi() * v) AS dy FROM ({_SCALED}) p, k)
SELECT user_id, round(CASE WHEN u >= background THEN x + dx WHEN strip < 0 THEN v WHEN strip < 2 THEN strip - floor(strip) WHEN strip < 3 THEN -b * v WHEN strip < 4 THEN 1 + b * v WHEN dx > 0 THEN 1 + dx ELSE dx END, 6) AS rx,
round(CASE WHEN u >= background THEN y + dy WHEN strip < 0 THEN w WHEN strip < 1 THEN -b * v WHEN strip < 2 THEN 1 + b * v WHEN strip < 4 THEN strip - floor(strip) WHEN dy > 0 THEN 1 + dy ELSE dy END, 6) AS ry FROM t""")
def disk_continuous(spark, sf):
    scaled = points(spark, sf, "taxi_like").select("user_id", (F.col("x") / 500000).alias("x"), (F.col("y") / 2410).alias("y"))
    return DiskMechanism.report_continuous(scaled, 3.5, **HASH).select("user_id", r6(F.col("rx")).alias("rx"), r6(F.col("ry")).alias("ry"))


_QD35 = geo.continuous_constants("decay", _B35, 3.5)[1]
_TABLE_STEPS = 4096
#: Cumulative law of the decay's excess radius by trapezoids: (m0, m1, r0) per step.
_RADII = f"""SELECT sum(g) OVER (ORDER BY j) / sum(g) OVER () - g / sum(g) OVER () AS m0, sum(g) OVER (ORDER BY j) / sum(g) OVER () AS m1, {S.num(_B35)} * j / {_TABLE_STEPS} AS r0
FROM (SELECT j, h(j) + h(j + 1) AS g FROM (SELECT CAST(range AS DOUBLE) AS j FROM range({_TABLE_STEPS})))""".replace("h(j + 1)", f"(exp(3.5 * (1 - (j + 1) / {_TABLE_STEPS})) - 1) * (j + 1)").replace("h(j)", f"(exp(3.5 * (1 - j / {_TABLE_STEPS})) - 1) * j").replace("3.5 *", "CAST(3.5 AS DOUBLE) *")


@query("decay_continuous", f"""WITH k AS (SELECT {S.num(_B35)} AS b, {S.num(_QD35)} AS q), r AS MATERIALIZED ({_RADII}),
n AS (SELECT p.*, r0 + (w - m0) / (m1 - m0) * {S.num(_B35 / _TABLE_STEPS)} AS near FROM ({_SCALED}) p JOIN r ON w >= m0 AND w < m1),
t AS (SELECT p.*, k.b, k.q * (pi() * b * b + 4 * b + 1) AS background, (u / (k.q * (pi() * b * b + 4 * b + 1)) * (pi() * b * b + 4 * b + 1) - 1) / b AS strip, b * sqrt(w) * cos(2 * pi() * v) AS dx, b * sqrt(w) * sin(2 * pi() * v) AS dy FROM n p, k)
SELECT user_id, round(CASE WHEN u >= background THEN x + near * cos(2 * pi() * v) WHEN strip < 0 THEN v WHEN strip < 2 THEN strip - floor(strip) WHEN strip < 3 THEN -b * v WHEN strip < 4 THEN 1 + b * v WHEN dx > 0 THEN 1 + dx ELSE dx END, 6) + 0 AS rx,
round(CASE WHEN u >= background THEN y + near * sin(2 * pi() * v) WHEN strip < 0 THEN w WHEN strip < 1 THEN -b * v WHEN strip < 2 THEN 1 + b * v WHEN strip < 4 THEN strip - floor(strip) WHEN dy > 0 THEN 1 + dy ELSE dy END, 6) + 0 AS ry FROM t""")
def decay_continuous(spark, sf):
    scaled = points(spark, sf, "taxi_like").select("user_id", (F.col("x") / 500000).alias("x"), (F.col("y") / 2410).alias("y"))
    return DecayMechanism.report_continuous(scaled, 3.5, steps=_TABLE_STEPS, **HASH).select("user_id", (r6(F.col("rx")) + 0).alias("rx"), (r6(F.col("ry")) + 0).alias("ry"))


_E3 = "exp(CAST(3 AS DOUBLE))"


@query("special_cases", f"""SELECT 'no budget' AS limit_of, CAST(81 - 4 * 1 AS BIGINT) AS outputs, round(1 / CAST(77 AS DOUBLE), 9) AS least, round(1 / CAST(77 AS DOUBLE), 9) AS most UNION ALL
SELECT 'no radius', 25, round(1 / ({_E3} + 24), 9), round({_E3} / ({_E3} + 24), 9) UNION ALL SELECT 'one cell', 1, CAST(1 AS DOUBLE), CAST(1 AS DOUBLE) UNION ALL
SELECT 'large budget', 25, round(1 / (exp(CAST(30 AS DOUBLE)) + 24), 9), round(exp(CAST(30 AS DOUBLE)) / (exp(CAST(30 AS DOUBLE)) + 24), 9)""")
def special_cases(spark, sf):
    """Limits with closed forms: without budget every output is alike (a 5 x 5 grid grown by radius 2, less its corners), without radius it is k-ary
    response, a single cell tells nothing, and a large budget tells all."""
    found = {"no budget": DiskMechanism(0.0, unit_grid(5), 2), "no radius": DiskMechanism(3.0, unit_grid(5), 0), "one cell": DiskMechanism(3.0, unit_grid(1), 0), "large budget": DiskMechanism(30.0, unit_grid(5))}
    out = None
    for name, mech in found.items():
        row = mech.channel(spark).agg(F.count_distinct("ox", "oy").alias("outputs"), r6(F.min("prob"), 9).alias("least"), r6(F.max("prob"), 9).alias("most")).withColumn("limit_of", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query("secure_report_totals", f"SELECT part, count(*) AS reports, true AS inside FROM ({S.cells('taxi_like', 15)}) GROUP BY part")
def secure_report_totals(spark, sf):
    """Reports drawn from the operating system's randomness: they differ each time, but every user of a part sends one, inside the output cells."""
    mech = DiskMechanism(3.5, unit_grid(15))
    cells = assign_cells(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(15))
    inside = F.broadcast(output_cells(spark, unit_grid(15), mech.stencil).withColumn("known", F.lit(True)))
    reports = mech.report(cells, keep=("part",)).join(inside, ["ox", "oy"], "left")
    return reports.groupBy("part").agg(F.count("*").alias("reports"), F.every(F.coalesce("known", F.lit(False))).alias("inside"))


# ---- estimates ----

STEPS = 20


def _counts_sql(name, d, kind="disk"):
    b = geo.grid_radius(3.5, d)
    return f"SELECT ox, oy, count(*) AS n FROM ({S.reports(name, d, b, _weights_sql(kind, b))}) GROUP BY ox, oy"


def _estimate_sql(name, d, kind="disk", steps=STEPS, digits=6):
    b = geo.grid_radius(3.5, d)
    return f"SELECT cx, cy, round(mass, {digits}) AS mass FROM ({S.em_steps(S.channel(d, b, _weights_sql(kind, b)), _counts_sql(name, d, kind), d * d, steps)})"


def _register_estimate(key, name, kind, d=5):
    def run(spark, sf):
        mech = _mechs(d)[kind]
        return estimate_distribution(points(spark, sf, name), POINT_SETS[name].grid(d), mech, max_iter=STEPS, tol=-1.0, **HASH).withColumn("mass", r6(F.col("mass")))

    query(key, _estimate_sql(name, d, kind))(run)


_register_estimate("estimate_disk", "taxi_like", "disk")
_register_estimate("estimate_disk_noshrink", "taxi_like", "disk_noshrink")
_register_estimate("estimate_decay", "taxi_like", "decay")
_register_estimate("estimate_disk_crime", "crime_like", "disk")
_register_estimate("estimate_disk_volume", "taxi_big", "disk")


_B5 = geo.grid_radius(3.5, 5)
_PART_CHANNEL = f"SELECT part AS grp, cx, cy, ox, oy, prob FROM ({S.channel(5, _B5, S.disk_weights(_B5, 3.5))}), (SELECT DISTINCT part FROM ({S.cells('taxi_like', 5)}))"
_PART_COUNTS = f"SELECT part AS grp, ox, oy, count(*) AS n FROM ({S.reports('taxi_like', 5, _B5, S.disk_weights(_B5, 3.5))}) GROUP BY part, ox, oy"


@query("estimate_by_part", f"SELECT grp AS part, cx, cy, round(mass / sum(mass) OVER (PARTITION BY grp), 6) AS mass FROM ({S.em_steps(_PART_CHANNEL, _PART_COUNTS, 25, STEPS, 'grp, cx, cy', 'grp, ox, oy')})")
def estimate_by_part(spark, sf):
    found = estimate_by(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(5), DiskMechanism(3.5, unit_grid(5)), ("part",), max_iter=STEPS, tol=-1.0, **HASH)
    return found.withColumn("mass", r6(F.col("mass")))


_RUN_CHANNEL = f"SELECT part || '/' || run AS grp, cx, cy, ox, oy, prob FROM ({S.channel(5, _B5, S.disk_weights(_B5, 3.5))}), (SELECT DISTINCT part FROM ({S.cells('taxi_like', 5)})), (SELECT CAST(range AS VARCHAR) AS run FROM range(3))"
_RUN_COUNTS = f"SELECT part || '/' || CAST(user_id % 3 AS VARCHAR) AS grp, ox, oy, count(*) AS n FROM ({S.reports('taxi_like', 5, _B5, S.disk_weights(_B5, 3.5))}) GROUP BY ALL"


@query("em_batched", f"SELECT split_part(grp, '/', 1) AS part, CAST(split_part(grp, '/', 2) AS BIGINT) AS run, cx, cy, round(mass / sum(mass) OVER (PARTITION BY grp), 6) AS mass FROM ({S.em_steps(_RUN_CHANNEL, _RUN_COUNTS, 25, STEPS, 'grp, cx, cy', 'grp, ox, oy')})")
def em_batched(spark, sf):
    """Inversions of every part and run at once: one count, one task an inversion."""
    rows = points(spark, sf, "taxi_like").withColumn("run", F.col("user_id") % 3)
    found = estimate_by(rows, POINT_SETS["taxi_like"].grid(5), DiskMechanism(3.5, unit_grid(5)), ("part", "run"), max_iter=STEPS, tol=-1.0, **HASH)
    return found.withColumn("mass", r6(F.col("mass")))


def _estimate_15(spark, sf, method):
    return estimate_distribution(points(spark, sf, "crime_like"), POINT_SETS["crime_like"].grid(15), DiskMechanism(3.5, unit_grid(15)), method=method, max_iter=5, tol=-1.0, **HASH).withColumn("mass", r6(F.col("mass")))


query("em_local", _estimate_sql("crime_like", 15, steps=5))(lambda spark, sf: _estimate_15(spark, sf, "dense"))
query("em_stencil_local", _estimate_sql("crime_like", 15, steps=5))(lambda spark, sf: _estimate_15(spark, sf, "stencil"))
query("em_fft_local", _estimate_sql("crime_like", 15, steps=5))(lambda spark, sf: _estimate_15(spark, sf, "fft"))


@query("em_fft")
def em_fft_query(spark, sf):
    """The transform on a fine grid; em_fft_local is the same code on one that SQL can follow."""
    return estimate_distribution(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(60), DiskMechanism(3.5, unit_grid(60)), method="fft", max_iter=200, **HASH)


def _disk_counts(spark, sf, name="taxi_like", d=5):
    return count_reports(_mechs(d)["disk"].report(assign_cells(points(spark, sf, name), POINT_SETS[name].grid(d)), **HASH))


@query("em_df", _estimate_sql("taxi_like", 5, steps=3))
def em_df(spark, sf):
    return em_frame(_disk_counts(spark, sf), DiskMechanism(3.5, unit_grid(5)).channel(spark), 25, 3).withColumn("mass", r6(F.col("mass")))


@query("em_stencil", _estimate_sql("taxi_like", 5, steps=2))
def em_stencil_query(spark, sf):
    mech = DiskMechanism(3.5, unit_grid(5))
    return em_stencil_frame(_disk_counts(spark, sf), input_cells(spark, unit_grid(5)), mech.excess_frame(spark), mech.q, 2).withColumn("mass", r6(F.col("mass")))


_SMOOTH_PAIRS = "SELECT f.cx, f.cy, CAST(least(greatest(f.cx + a.k, 0), 4) AS INTEGER) AS sx, CAST(least(greatest(f.cy + b.k, 0), 4) AS INTEGER) AS sy, a.w * b.w AS w FROM f, w a, w b"


@query("em_smooth", f"""WITH f AS MATERIALIZED (SELECT * FROM ({S.em_steps(S.channel(5, 1, S.disk_weights(1, 3.5)), _counts_sql('taxi_like', 5), 25, 1)})), w AS (SELECT CAST(unnest([-1, 0, 1]) AS INTEGER) AS k, CAST(unnest([0.25, 0.5, 0.25]) AS DOUBLE) AS w)
SELECT p.cx, p.cy, round(sum(p.w * g.mass) / (SELECT sum(q.w * h.mass) FROM ({_SMOOTH_PAIRS}) q JOIN f h ON h.cx = q.sx AND h.cy = q.sy), 6) AS mass FROM ({_SMOOTH_PAIRS}) p JOIN f g ON g.cx = p.sx AND g.cy = p.sy GROUP BY p.cx, p.cy""")
def em_smooth(spark, sf):
    return estimate_from_reports(DiskMechanism(3.5, unit_grid(5)).report(assign_cells(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(5)), **HASH), DiskMechanism(3.5, unit_grid(5)), max_iter=1, tol=-1.0, smooth=True).withColumn("mass", r6(F.col("mass")))


# ---- baselines ----

_WAVE = SquareWave(1.75, 15)


@query("sw_report", f"SELECT CAST(o AS INTEGER) AS o, count(*) AS n FROM (SELECT {S.wave_axis('cx', uniform_sql('user_id', 0), 15, _WAVE.b, 1.75)} AS o FROM ({S.cells('taxi_like', 15)})) GROUP BY o")
def sw_report(spark, sf):
    cells = assign_cells(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(15))
    return cells.select(_WAVE.report(F.col("cx"), hash_uniform(F.col("user_id"), 0)).alias("o")).groupBy("o").agg(F.count("*").alias("n"))


_AXIS = f"SELECT {S.wave_axis('cx', uniform_sql('user_id', 0), 15, _WAVE.b, 1.75)} AS ox, {S.wave_axis('cy', uniform_sql('user_id', 1), 15, _WAVE.b, 1.75)} AS oy FROM ({S.cells('taxi_like', 15)})"


@query("axis_report", f"SELECT ox, oy, count(*) AS n FROM ({_AXIS}) GROUP BY ox, oy")
def axis_report(spark, sf):
    return count_reports(AxisWaveMechanism(3.5, unit_grid(15)).report(assign_cells(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(15)), **HASH))


@query("axis_marginals", f"SELECT 'x' AS axis, ox AS o, count(*) AS n FROM ({_AXIS}) GROUP BY ox UNION ALL SELECT 'y', oy, count(*) FROM ({_AXIS}) GROUP BY oy")
def axis_marginals(spark, sf):
    mech = AxisWaveMechanism(3.5, unit_grid(15))
    return mech.count_axes(mech.report(assign_cells(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(15)), **HASH))



def _axis_counts(cell: str, draw: int) -> str:
    report = S.wave_axis(cell, uniform_sql("user_id", draw), 5, SquareWave(1.75, 5).b, 1.75)
    return f"SELECT ox, CAST(0 AS INTEGER) AS oy, count(*) AS n FROM (SELECT {report} AS ox FROM ({S.cells('taxi_like', 5)})) GROUP BY ox"


def _axis_channel(d, b, eps):
    return f"SELECT cx, cy, ox, oy, w / sum(w) OVER (PARTITION BY cx) AS prob FROM (SELECT CAST(c.range AS INTEGER) AS cx, CAST(0 AS INTEGER) AS cy, CAST(o.range AS INTEGER) AS ox, CAST(0 AS INTEGER) AS oy, CASE WHEN abs(c.range - o.range) <= {b} THEN exp({S.num(eps)}) ELSE CAST(1 AS DOUBLE) END AS w FROM range({d}) c, range({-b}, {d + b}) o)"


@query("axis_estimate", f"SELECT x.cx, y.cx AS cy, round(x.mass * y.mass, 6) AS mass FROM ({S.em_steps(_axis_channel(5, SquareWave(1.75, 5).b, 1.75), _axis_counts("cx", 0), 5, STEPS)}) x, ({S.em_steps(_axis_channel(5, SquareWave(1.75, 5).b, 1.75), _axis_counts("cy", 1), 5, STEPS)}) y")
def axis_estimate(spark, sf):
    return estimate_axes(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(5), AxisWaveMechanism(3.5, unit_grid(5)), max_iter=STEPS, tol=-1.0, **HASH).withColumn("mass", r6(F.col("mass")))


_AXIS5 = SquareWave(1.75, 5)
_PAIR_CHANNEL = f"SELECT x.cx, y.cx AS cy, x.ox, y.ox AS oy, x.prob * y.prob AS prob FROM ({_axis_channel(5, _AXIS5.b, 1.75)}) x, ({_axis_channel(5, _AXIS5.b, 1.75)}) y"
_PAIR_COUNTS = f"SELECT ox, oy, count(*) AS n FROM (SELECT {S.wave_axis('cx', uniform_sql('user_id', 0), 5, _AXIS5.b, 1.75)} AS ox, {S.wave_axis('cy', uniform_sql('user_id', 1), 5, _AXIS5.b, 1.75)} AS oy FROM ({S.cells('taxi_like', 5)})) GROUP BY ox, oy"


@query("axis_estimate_joint", f"SELECT cx, cy, round(mass, 6) AS mass FROM ({S.em_steps(_PAIR_CHANNEL, _PAIR_COUNTS, 25, STEPS)})")
def axis_estimate_joint(spark, sf):
    return estimate_axes(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(5), AxisWaveMechanism(3.5, unit_grid(5), merge="joint"), max_iter=STEPS, tol=-1.0, **HASH).withColumn("mass", r6(F.col("mass")))


def _axis_counts_of(cell: str, draw: int, b: int) -> str:
    return f"SELECT ox, CAST(0 AS INTEGER) AS oy, count(*) AS n FROM (SELECT {S.wave_axis(cell, uniform_sql('user_id', draw), 5, b, 1.75)} AS ox FROM ({S.cells('taxi_like', 5)})) GROUP BY ox"


@query("axis_estimate_own_radius", f"SELECT x.cx, y.cx AS cy, round(x.mass * y.mass, 6) AS mass FROM ({S.em_steps(_axis_channel(5, 2, 1.75), _axis_counts_of('cx', 0, 2), 5, STEPS)}) x, ({S.em_steps(_axis_channel(5, 2, 1.75), _axis_counts_of('cy', 1, 2), 5, STEPS)}) y")
def axis_estimate_own_radius(spark, sf):
    """Axes with a radius of their own instead of the best one."""
    mech = AxisWaveMechanism(3.5, unit_grid(5), b_hat=2)
    return estimate_axes(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(5), mech, max_iter=STEPS, tol=-1.0, **HASH).withColumn("mass", r6(F.col("mass")))


def _one_axis(cell: str, draw: int, chosen: str) -> str:
    report = S.wave_axis(cell, uniform_sql("user_id", draw), 5, SquareWave(3.5, 5).b, 3.5)
    return f"SELECT ox, CAST(0 AS INTEGER) AS oy, count(*) AS n FROM (SELECT {report} AS ox FROM ({S.cells('taxi_like', 5)}) WHERE {uniform_sql('user_id', 2)} {chosen} 0.5) GROUP BY ox"


@query("axis_estimate_sample", f"SELECT x.cx, y.cx AS cy, round(x.mass * y.mass, 6) AS mass FROM ({S.em_steps(_axis_channel(5, SquareWave(3.5, 5).b, 3.5), _one_axis('cx', 0, '<'), 5, STEPS)}) x, ({S.em_steps(_axis_channel(5, SquareWave(3.5, 5).b, 3.5), _one_axis('cy', 1, '>='), 5, STEPS)}) y")
def axis_estimate_sample(spark, sf):
    return estimate_axes(points(spark, sf, "taxi_like"), POINT_SETS["taxi_like"].grid(5), AxisWaveMechanism(3.5, unit_grid(5), budget="sample"), max_iter=STEPS, tol=-1.0, **HASH).withColumn("mass", r6(F.col("mass")))


_DIST = "sqrt(CAST((a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy) AS DOUBLE))"
_RANKS = f"SELECT a.cy * 3 + a.cx AS cell, row_number() OVER (PARTITION BY a.cx, a.cy ORDER BY {_DIST}, b.cy * 3 + b.cx) - 1 AS rank, b.cy * 3 + b.cx AS other, {_DIST} AS dist FROM ({S.grid_cells(3)}) a, ({S.grid_cells(3)}) b"


@query("subset_rank_table", f"""SELECT CAST(cell AS INTEGER) AS cell, CAST(rank AS INTEGER) AS rank, CAST(other AS INTEGER) AS other, round(dist, 6) AS dist, round(w / sum(w) OVER (PARTITION BY cell), 8) AS prob
FROM (SELECT *, (CASE WHEN 8 - rank >= 2 THEN (8 - rank) * (7 - rank) / 2 ELSE 0 END) * exp(-0.5 * dist) AS w FROM ({_RANKS}))""")
def subset_rank_table(spark, sf):
    return SubsetExponentialMechanism(1.0, unit_grid(3), 3).rank_table(spark).select("cell", "rank", "other", r6(F.col("dist")).alias("dist"), r6(F.col("prob"), 8).alias("prob"))


@query("exp_mech_channel", f"SELECT a.cx, a.cy, a.n, b.cx AS ox, b.cy AS oy, round(exp(-1.0 * {_DIST}) / sum(exp(-1.0 * {_DIST})) OVER (PARTITION BY a.cx, a.cy), 8) AS prob FROM {inhabited_sql('taxi_big', 5)} a, ({S.grid_cells(5)}) b")
def exp_mech_channel(spark, sf):
    """Rows for the cells that line items lie in, with their numbers."""
    a, b = inhabited(spark, sf, "taxi_big", 5), input_cells(spark, unit_grid(5)).select(F.col("cx").alias("ox"), F.col("cy").alias("oy"))
    pairs = a.crossJoin(F.broadcast(b)).withColumn("w", F.exp(-F.hypot(F.col("cx") - F.col("ox"), F.col("cy") - F.col("oy"))))
    return pairs.select("cx", "cy", "n", "ox", "oy", r6(F.col("w") / F.sum("w").over(Window.partitionBy("cx", "cy")), 8).alias("prob"))


_EPS_SUBSET = 2.366
#: Ways to choose the other members once the nearest one has a rank (k = 1, 3 on 25 cells; 2 for the sampler's query).
_WAYS = {1: "1", 2: "(24 - rank)", 3: "((24 - rank) * (23 - rank) / 2)"}


def _near_law(eps: float, k: int) -> str:
    """(cell, rank, other, w): cells by distance from each cell, with the weight of sets whose nearest member has that rank."""
    ranked = f"SELECT a.cy * 5 + a.cx AS cell, row_number() OVER (PARTITION BY a.cx, a.cy ORDER BY {_DIST}, b.cy * 5 + b.cx) - 1 AS rank, b.cy * 5 + b.cx AS other, {_DIST} AS dist FROM ({S.grid_cells(5)}) a, ({S.grid_cells(5)}) b"
    return f"SELECT *, {_WAYS[k]} * exp(-0.5 * {S.num(eps)} * dist) AS w FROM ({ranked})"


def _sum_law(eps: float) -> str:
    return f"SELECT a.cy * 5 + a.cx AS cell, b.cy * 5 + b.cx AS rank, b.cy * 5 + b.cx AS other, {_DIST} AS dist, exp(-0.5 * {S.num(eps)} * {_DIST}) AS w FROM ({S.grid_cells(5)}) a, ({S.grid_cells(5)}) b"


def _subset_members(eps: float, k: int, score: str, rows: str, user: str = "user_id") -> str:
    """(members): one uniform picks a rank of the user's cell, the next ones pick evenly among the places that may follow."""
    law = _near_law(eps, k) if score == "nearest" else _sum_law(eps)
    base = f"SELECT u.*, l.rank, l.other FROM (SELECT cy * 5 + cx AS own, {', '.join(f'{uniform_sql(user, j)} AS u{j}' for j in range(k))} FROM ({rows})) u JOIN (SELECT cell, rank, other, (sum(w) OVER o - w) / sum(w) OVER a AS lo, sum(w) OVER o / sum(w) OVER a AS hi FROM ({law}) WINDOW o AS (PARTITION BY cell ORDER BY rank), a AS (PARTITION BY cell)) l ON l.cell = u.own AND u.u0 >= l.lo AND u.u0 < l.hi"
    if k == 1:
        return f"SELECT [other] AS members FROM ({base})"
    left = "(24 - rank)" if score == "nearest" else "24"
    picks = f"SELECT *, CAST(floor(u1 * {left}) AS INTEGER) AS i" + (f", CAST(floor(u2 * ({left} - 1)) AS INTEGER) AS j0" if k == 3 else "") + f" FROM ({base})"
    if k == 3:
        picks = f"SELECT *, j0 + CASE WHEN j0 >= i THEN 1 ELSE 0 END AS j FROM ({picks})"
    if score == "sum":
        return f"SELECT list_sort([other, i + CASE WHEN i >= other THEN 1 ELSE 0 END, j + CASE WHEN j >= other THEN 1 ELSE 0 END]) AS members FROM ({picks})"
    joins = f"JOIN ({law}) x ON x.cell = p.own AND x.rank = p.rank + 1 + p.i" + (f" JOIN ({law}) y ON y.cell = p.own AND y.rank = p.rank + 1 + p.j" if k == 3 else "")
    return f"SELECT list_sort([p.other, x.other{', y.other' if k == 3 else ''}]) AS members FROM ({picks}) p {joins}"


def _subset_em(eps: float, k: int, score: str, rows: str, user: str = "user_id") -> str:
    """EM over distinct sets; a set's chance comes from its distances to a cell."""
    counts = f"SELECT members, count(*) AS n FROM ({_subset_members(eps, k, score, rows, user)}) GROUP BY members"
    law = _near_law(eps, k) if score == "nearest" else _sum_law(eps)
    total = f"SELECT cell, sum(w){'' if score == 'nearest' else f' * {math.comb(24, k - 1)}'} AS z FROM ({law}) GROUP BY cell"
    weight = f"exp(-0.5 * {S.num(eps)} * min(d.dist))" if score == "nearest" else f"sum(exp(-0.5 * {S.num(eps)} * d.dist))"
    channel = f"SELECT s.members, d.cell, {weight} / any_value(z.z) AS prob FROM (SELECT members, unnest(members) AS m FROM ({counts})) s JOIN ({law}) d ON d.other = s.m JOIN ({total}) z ON z.cell = d.cell GROUP BY s.members, d.cell"
    return S.em_steps(channel, counts, 25, STEPS, "cell", "members")


def _subset_sql(k: int, score: str = "nearest") -> str:
    rows = S.cells("taxi_like", 5)
    return f"SELECT CAST(cell % 5 AS INTEGER) AS cx, CAST(cell // 5 AS INTEGER) AS cy, round(mass, 6) AS mass, (SELECT count(DISTINCT members) FROM ({_subset_members(_EPS_SUBSET, k, score, rows)})) AS sets FROM ({_subset_em(_EPS_SUBSET, k, score, rows)})"


def _subset_estimate(spark, sf, k, score="nearest"):
    """Reports by ranks, counts of canonical sets, EM over the distinct sets (their number is returned with the estimate)."""
    grid = POINT_SETS["taxi_like"].grid(5)
    mech = SubsetExponentialMechanism(_EPS_SUBSET, grid, k, score)
    counts = materialise(mech.count(mech.report(assign_cells(points(spark, sf, "taxi_like"), grid), **HASH)))
    mass = mech.estimate(counts, STEPS, -1.0).mass
    return to_histogram(spark, mass, 5).withColumn("mass", r6(F.col("mass"))).withColumn("sets", F.lit(counts.count()).cast("long"))


for _key, _k, _score in (("subset_estimate_k1", 1, "nearest"), ("subset_estimate_k3", 3, "nearest"), ("subset_estimate_sum", 3, "sum")):
    query(_key, _subset_sql(_k, _score))(lambda spark, sf, k=_k, score=_score: _subset_estimate(spark, sf, k, score))


_GRID5 = "taxi_like"


def _cells5(spark, sf):
    return assign_cells(points(spark, sf, _GRID5), POINT_SETS[_GRID5].grid(5))


_N5 = f"(SELECT count(*) FROM ({S.cells(_GRID5, 5)}))"


def _oracle(kind, eps=2.0):
    return CategoricalOracle(kind, eps, unit_grid(5))


_GRR = _oracle("grr")
_GRR_SQL = f"SELECT CAST(CASE WHEN u < {S.num(_GRR.p)} OR false THEN own ELSE floor(v * 24) + CASE WHEN floor(v * 24) >= own THEN 1 ELSE 0 END END AS INTEGER) AS cell FROM (SELECT cy * 5 + cx AS own, {uniform_sql('user_id', 0)} AS u, {uniform_sql('user_id', 1)} AS v FROM ({S.cells(_GRID5, 5)}))"


@query("grr_report", f"SELECT cell, count(*) AS n FROM ({_GRR_SQL}) GROUP BY cell")
def grr_report(spark, sf):
    return _GRR.support(_GRR.report(_cells5(spark, sf), **HASH))


def _unbiased_sql(support, o):
    return f"SELECT g.cx, g.cy, round((coalesce(s.n, 0) - {_N5} * {S.num(o.q)}) / ({_N5} * {S.num(o.p - o.q)}), 6) AS mass FROM ({S.grid_cells(5)}) g LEFT JOIN ({support}) s ON s.cell = g.cy * 5 + g.cx"


def _estimate_oracle(kind, spark, sf):
    o, cells = _oracle(kind), _cells5(spark, sf)
    return o.estimate(o.support(o.report(cells, **HASH)), cells.count()).withColumn("mass", r6(F.col("mass")))


@query("grr_estimate", _unbiased_sql(f"SELECT cell, count(*) AS n FROM ({_GRR_SQL}) GROUP BY cell", _GRR))
def grr_estimate(spark, sf):
    return _estimate_oracle("grr", spark, sf)


def _bits_sql(o):
    return f"SELECT cell, count(*) AS n FROM (SELECT g.cell FROM (SELECT user_id, cy * 5 + cx AS own FROM ({S.cells(_GRID5, 5)})) p, (SELECT CAST(range AS INTEGER) AS cell FROM range(25)) g WHERE {uniform_sql('p.user_id', 'g.cell')} < CASE WHEN g.cell = p.own THEN {S.num(o.p)} ELSE {S.num(o.q)} END) GROUP BY cell"


for _k in ("oue", "sue"):
    query(f"{_k}_estimate", _unbiased_sql(_bits_sql(_oracle(_k)), _oracle(_k)))(lambda spark, sf, k=_k: _estimate_oracle(k, spark, sf))

_OLH = _oracle("olh")


def _olh_sql(user, cell):
    return f"(CAST(concat('0x', substr(md5(CAST({user} AS VARCHAR) || ':' || CAST({cell} AS VARCHAR)), 1, 13)) AS BIGINT) % {_OLH.hashes})"


_OLH_REPORT = f"SELECT user_id, CASE WHEN u < {S.num(_OLH.p)} THEN own ELSE floor(v * {_OLH.hashes - 1}) + CASE WHEN floor(v * {_OLH.hashes - 1}) >= own THEN 1 ELSE 0 END END AS value FROM (SELECT user_id, {_olh_sql('user_id', 'cy * 5 + cx')} AS own, {uniform_sql('user_id', 0)} AS u, {uniform_sql('user_id', 1)} AS v FROM ({S.cells(_GRID5, 5)}))"
_OLH_SUPPORT = f"SELECT g.cell, count(*) AS n FROM ({_OLH_REPORT}) r, (SELECT CAST(range AS INTEGER) AS cell FROM range(25)) g WHERE {_olh_sql('r.user_id', 'g.cell')} = r.value GROUP BY g.cell"


@query("olh_support", _OLH_SUPPORT)
def olh_support(spark, sf):
    return _OLH.support(_OLH.report(_cells5(spark, sf), **HASH))


@query("olh_estimate", _unbiased_sql(_OLH_SUPPORT, _OLH))
def olh_estimate(spark, sf):
    return _estimate_oracle("olh", spark, sf)


_SEL = _oracle("subset")
#: k cells by the order of a hash, the true one first with probability p and else left out.
_SEL_MEMBERS = f"""SELECT cell FROM (SELECT cell, u, own, row_number() OVER (PARTITION BY user_id, cell = own ORDER BY h) AS place, cell = own AS is_own
FROM (SELECT p.user_id, p.own, g.cell, p.u, md5('42:' || CAST(p.user_id AS VARCHAR) || ':' || CAST(g.cell + 2 AS VARCHAR)) AS h FROM (SELECT user_id, cy * 5 + cx AS own, {uniform_sql('user_id', 0)} AS u FROM ({S.cells(_GRID5, 5)})) p, (SELECT CAST(range AS INTEGER) AS cell FROM range(25)) g))
WHERE CASE WHEN is_own THEN u < {S.num(_SEL.p)} ELSE place <= {_SEL.size} - CASE WHEN u < {S.num(_SEL.p)} THEN 1 ELSE 0 END END"""


@query("subset_selection_estimate", _unbiased_sql(f"SELECT cell, count(*) AS n FROM ({_SEL_MEMBERS}) GROUP BY cell", _SEL))
def subset_selection_estimate(spark, sf):
    return _estimate_oracle("subset", spark, sf)


@query("grr_projected", f"""WITH e AS MATERIALIZED ({_unbiased_sql(f"SELECT cell, count(*) AS n FROM ({_GRR_SQL}) GROUP BY cell", _GRR)}), o AS (SELECT mass, row_number() OVER (ORDER BY mass DESC) AS k, sum(mass) OVER (ORDER BY mass DESC ROWS UNBOUNDED PRECEDING) AS total FROM e),
cut AS (SELECT arg_max((total - 1) / k, k) AS level FROM o WHERE mass - (total - 1) / k > 0)
SELECT cx, cy, round(greatest(mass - level, 0), 6) AS projected, round(greatest(mass, 0) / (SELECT sum(greatest(mass, 0)) FROM e), 6) AS clipped FROM e, cut""")
def grr_projected(spark, sf):
    """The linear estimate made a distribution by projection, and by clipping."""
    rows = sorted(_estimate_oracle("grr", spark, sf).collect(), key=lambda r: (r.cy, r.cx))
    v = np.array([r.mass for r in rows])
    both = to_histogram(spark, project_simplex(v), 5).withColumnRenamed("mass", "projected").join(to_histogram(spark, clip_normalise(v), 5).withColumnRenamed("mass", "clipped"), ["cx", "cy"])
    return both.select("cx", "cy", r6(F.col("projected")).alias("projected"), r6(F.col("clipped")).alias("clipped"))


@query("uniform_baseline", f"SELECT cx, cy, CAST(0.04 AS DOUBLE) AS mass FROM ({S.grid_cells(5)})")
def uniform_baseline(spark, sf):
    return input_cells(spark, unit_grid(5)).withColumn("mass", F.lit(1.0 / 25))


_EVENTS_STEPS = f"SELECT user_id, cy * 5 + cx AS cell, lag(cy * 5 + cx) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM (SELECT e.user_id, e.ts, e.event_id, c.cx, c.cy FROM ({S.cells('crime_like', 5)}) c JOIN events e ON e.event_id = c.user_id)"


@query("transition_counts", f"SELECT CAST(before AS INTEGER) AS before, CAST(cell AS INTEGER) AS cell, count(*) AS n FROM ({_EVENTS_STEPS}) WHERE before IS NOT NULL GROUP BY before, cell")
def transition_counts(spark, sf):
    from veilgrid.mechanisms.trajectory import trajectories, transitions

    return transitions(trajectories(spark, sf, 5))


@query("trajectory_markov")
def trajectory_markov(spark, sf):
    from veilgrid.mechanisms.trajectory import markov_estimate, trajectories

    return markov_estimate(trajectories(spark, sf, 5), unit_grid(5), 3.5, **HASH)


_CHOSEN = f"SELECT *, event_id AS point FROM (SELECT e.event_id, c.cx, c.cy, row_number() OVER (PARTITION BY e.user_id ORDER BY {uniform_sql('e.event_id', 7)}, e.event_id) AS nth FROM ({S.cells('crime_like', 5)}) c JOIN events e ON e.event_id = c.user_id) WHERE nth <= 4"


@query("trajectory_pivot", f"SELECT CAST(cell % 5 AS INTEGER) AS cx, CAST(cell // 5 AS INTEGER) AS cy, round(mass, 6) AS mass FROM ({_subset_em(3.5 / 4, 1, 'nearest', _CHOSEN, 'point')})")
def trajectory_pivot(spark, sf):
    from veilgrid.mechanisms.trajectory import pivot_estimate, trajectories

    return pivot_estimate(trajectories(spark, sf, 5), unit_grid(5), 3.5, 4, STEPS, -1.0, **HASH).withColumn("mass", r6(F.col("mass")))


# ---- measures ----

def _hist_pair(spark, sf, d=5):
    """Truth of the event set against the uniform guess."""
    truth = true_histogram(points(spark, sf, "crime_like"), POINT_SETS["crime_like"].grid(d))
    return truth, input_cells(spark, unit_grid(d)).withColumn("mass", F.lit(1.0 / (d * d)))


def _truth_sql(d=5):
    return f"SELECT g.cx, g.cy, coalesce(h.n, 0) / CAST((SELECT count(*) FROM ({S.cells('crime_like', d)})) AS DOUBLE) AS a, CAST({1 / (d * d)!r} AS DOUBLE) AS b FROM ({S.grid_cells(d)}) g LEFT JOIN (SELECT cx, cy, count(*) AS n FROM ({S.cells('crime_like', d)}) GROUP BY cx, cy) h ON h.cx = g.cx AND h.cy = g.cy"


@query("pointwise", f"""SELECT round(sum(abs(a - b)), 6) AS l1, round(avg(abs(a - b)), 6) AS mae, round(avg((a - b) * (a - b)), 8) AS mse, round(0.5 * sum(abs(a - b)), 6) AS tv, round(sum(pa * ln(pa / pb)), 6) AS kl, round(0.5 * sum(pa * ln(2 * pa / (pa + pb))) + 0.5 * sum(pb * ln(2 * pb / (pa + pb))), 6) AS js
FROM (SELECT a, b, (a + 1e-9) / (1 + 25e-9) AS pa, (b + 1e-9) / (1 + 25e-9) AS pb FROM ({_truth_sql()}))""")
def pointwise(spark, sf):
    return frames.pointwise(*_hist_pair(spark, sf), cells=25)


@query("w1_1d", f"SELECT round(sum(abs(fa - fb)), 8) AS w1 FROM (SELECT cx, sum(sum(a)) OVER (ORDER BY cx) AS fa, sum(sum(b)) OVER (ORDER BY cx) AS fb FROM ({_truth_sql()}) GROUP BY cx)")
def w1_1d(spark, sf):
    a, b = (h.groupBy(F.col("cx").cast("double").alias("t")).agg(F.sum("mass").alias("mass")) for h in _hist_pair(spark, sf))
    return frames.wasserstein_1d(a, b, 1).select(r6(F.col("distance"), 8).alias("w1"))


_CDFS = f"SELECT cx, sum(sum(a)) OVER (ORDER BY cx) AS fa, sum(sum(b)) OVER (ORDER BY cx) AS fb, sum(a) AS a, sum(b) AS b FROM ({_truth_sql()}) GROUP BY cx"


@query("w2_1d", f"SELECT round(sum((x.cx - y.cx) * (x.cx - y.cx) * (least(x.fa, y.fb) - greatest(x.fa - x.a, y.fb - y.b))), 8) AS w2_squared FROM ({_CDFS}) x JOIN ({_CDFS}) y ON least(x.fa, y.fb) > greatest(x.fa - x.a, y.fb - y.b)")
def w2_1d(spark, sf):
    a, b = (h.groupBy(F.col("cx").cast("double").alias("t")).agg(F.sum("mass").alias("mass")) for h in _hist_pair(spark, sf))
    return frames.wasserstein_1d(a, b, 2).select(r6(F.col("distance"), 8).alias("w2_squared"))


_ANGLES = 16
_RADON = f"SELECT k, round(cx * cos(2 * pi() * k / {_ANGLES}) + cy * sin(2 * pi() * k / {_ANGLES}), 9) + 0 AS t, sum(a) AS a, sum(b) AS b FROM ({_truth_sql()}), (SELECT CAST(range AS INTEGER) AS k FROM range({_ANGLES})) GROUP BY ALL"


@query("radon", f"SELECT k, round(t, 6) + 0 AS t, round(a, 9) AS a, round(b, 9) AS b FROM ({_RADON})")
def radon(spark, sf):
    return frames.radon(*_hist_pair(spark, sf), angles=_ANGLES).select("k", (r6(F.col("t")) + 0).alias("t"), r6(F.col("a"), 9).alias("a"), r6(F.col("b"), 9).alias("b"))


@query("sliced_w1", f"SELECT round(sum(gap * abs(fa - fb)) * 2 * pi() / {_ANGLES}, 6) AS sw1 FROM (SELECT k, lead(t) OVER (PARTITION BY k ORDER BY t) - t AS gap, sum(a) OVER (PARTITION BY k ORDER BY t) AS fa, sum(b) OVER (PARTITION BY k ORDER BY t) AS fb FROM ({_RADON}))")
def sliced_w1(spark, sf):
    return frames.sliced_wasserstein(*_hist_pair(spark, sf), angles=_ANGLES).select(r6(F.col("sw1")).alias("sw1"))


@query("w2_exact")
def w2_exact(spark, sf):
    return frames.grid_distances(*_hist_pair(spark, sf), d=5)


@query("w2_exact_line", f"SELECT round(sqrt(sum((x.cx - y.cx) * (x.cx - y.cx) * (least(x.fa, y.fb) - greatest(x.fa - x.a, y.fb - y.b)))), 6) AS w2 FROM ({_CDFS}) x JOIN ({_CDFS}) y ON least(x.fa, y.fb) > greatest(x.fa - x.a, y.fb - y.b)")
def w2_exact_line(spark, sf):
    """Exact transport over the cells where the answer is known in closed form: both histograms summed to one row of cells."""
    a, b = (h.groupBy("cx").agg(F.sum("mass").alias("mass")).withColumn("cy", F.lit(0)) for h in _hist_pair(spark, sf))
    return frames.grid_distances(a, b, d=5).select(r6(F.col("w2")).alias("w2"))


@query("w2_sinkhorn")
def w2_sinkhorn(spark, sf):
    return frames.grid_distances(*_hist_pair(spark, sf, 20), d=20, exact=False)


_K = "exp(-CAST((a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy) AS DOUBLE))"


def _sinkhorn_sql():
    """Two rounds of scaling from v = 1 with a kernel of width one, then the plan's cost."""
    base = f"WITH h AS MATERIALIZED (SELECT cx, cy, a AS p, b AS q FROM ({_truth_sql(4)}))"
    step = base + ", v0 AS (SELECT cx, cy, CAST(1 AS DOUBLE) AS v FROM h)"
    for k in (1, 2):
        step += f", u{k} AS MATERIALIZED (SELECT a.cx, a.cy, any_value(a.p) / sum({_K} * b.v) AS u FROM h a, v{k - 1} b GROUP BY a.cx, a.cy), v{k} AS MATERIALIZED (SELECT b.cx, b.cy, any_value(b.q) / sum({_K} * a.u) AS v FROM h b, u{k} a GROUP BY b.cx, b.cy)"
    return step + f" SELECT round(sum(a.u * {_K} * b.v * ((a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy))), 6) AS cost FROM u2 a, v2 b"


@query("sinkhorn_df", _sinkhorn_sql())
def sinkhorn_df(spark, sf):
    return frames.sinkhorn_cost(*_hist_pair(spark, sf, 4), d=4, reg=1.0, iterations=2).select(r6(F.col("cost")).alias("cost"))


@query("w2_sinkhorn_rounds", _sinkhorn_sql())
def w2_sinkhorn_rounds(spark, sf):
    """The array form that the studies use, stopped after the same two rounds as the relational one."""
    return frames.plan_cost(*_hist_pair(spark, sf, 4), d=4, reg=1.0, rounds=2).select(r6(F.col("cost")).alias("cost"))


_SEP = f"SELECT k, cos(2 * pi() * k / 8) AS c, sin(2 * pi() * k / 8) AS s FROM (SELECT CAST(range AS INTEGER) AS k FROM range(8))"


@query("report_separation", f"""WITH m AS MATERIALIZED ({S.channel(6, 2, S.disk_weights(2, 2.0))}), p AS (SELECT k, round(o.ox * c + o.oy * s, 9) + 0 AS t, sum(o.prob) FILTER (o.cx = 0 AND o.cy = 0) AS a, sum(o.prob) FILTER (o.cx = 3 AND o.cy = 1) AS b FROM m o, ({_SEP}) WHERE (o.cx = 0 AND o.cy = 0) OR (o.cx = 3 AND o.cy = 1) GROUP BY ALL)
SELECT k, round(sum(gap * abs(fa - fb)), 6) + 0 AS numeric_slope, round(abs(3 * cos(2 * pi() * k / 8) + sin(2 * pi() * k / 8)) * (1 - (SELECT count(*) FROM (SELECT DISTINCT ox, oy FROM m)) * (SELECT min(prob) FROM m)), 6) + 0 AS closed_slope FROM (SELECT k, lead(t) OVER (PARTITION BY k ORDER BY t) - t AS gap, sum(a) OVER (PARTITION BY k ORDER BY t) AS fa, sum(b) OVER (PARTITION BY k ORDER BY t) AS fb FROM p) GROUP BY k""")
def report_separation(spark, sf):
    """Distance of two inputs' report laws along an angle: numeric, and the closed form step * (1 - m q)."""
    mech = DiskMechanism(2.0, unit_grid(6), 2)
    channel = mech.channel(spark)
    law = lambda x, y: channel.where((F.col("cx") == x) & (F.col("cy") == y)).select(F.col("ox").alias("cx"), F.col("oy").alias("cy"), F.col("prob").alias("mass"))
    sliced = frames.sliced_by_angle(law(0, 0), law(3, 1), angles=8)
    angle = 2 * math.pi * F.col("k") / 8
    closed = F.abs(3 * F.cos(angle) + F.sin(angle)) * (1 - mech.outputs * mech.q)
    return sliced.select("k", (r6(F.col("w1")) + 0).alias("numeric_slope"), (r6(closed) + 0).alias("closed_slope"))


_LPC = S.channel(4, 1, S.disk_weights(1, 2.0))


@query("local_privacy", f"""WITH m AS MATERIALIZED ({_LPC}) SELECT round(sum(part / 16 / total), 6) AS lp FROM (SELECT a.ox, a.oy, sum(a.prob * b.prob * {_DIST}) AS part FROM m a JOIN m b ON a.ox = b.ox AND a.oy = b.oy GROUP BY a.ox, a.oy) JOIN (SELECT ox, oy, sum(prob) AS total FROM m GROUP BY ox, oy) USING (ox, oy)""")
def local_privacy_query(spark, sf):
    return frames.local_privacy(DiskMechanism(2.0, unit_grid(4), 1).channel(spark), 16).select(r6(F.col("lp")).alias("lp"))


@query("privacy_loss", " UNION ALL ".join(f"SELECT '{k}' AS mechanism, round(max(loss), 6) AS loss FROM (SELECT ln(max(prob) / min(prob)) AS loss FROM ({S.channel(15, 3, _weights_sql(k, 3))}) GROUP BY ox, oy)" for k in ("disk", "disk_noshrink", "decay", "decay_center")))
def privacy_loss_query(spark, sf):
    out = None
    for kind, mech in _mechs(15).items():
        loss = mech.channel(spark).groupBy("ox", "oy").agg(F.log(F.max("prob") / F.min("prob")).alias("loss")).agg(r6(F.max("loss")).alias("loss")).select(F.lit(kind).alias("mechanism"), "loss")
        out = loss if out is None else out.unionByName(loss)
    return out


@query("distance_loss", f"SELECT round(max(abs(ln(x.prob / y.prob)) / {_DIST.replace('a.c', 'x.i').replace('b.c', 'y.i')}), 6) AS loss FROM (SELECT a.cx AS ix, a.cy AS iy, b.cx AS ox, b.cy AS oy, exp(-0.75 * {_DIST}) / sum(exp(-0.75 * {_DIST})) OVER (PARTITION BY a.cx, a.cy) AS prob FROM {inhabited_sql('taxi_like', 4)} a, ({S.grid_cells(4)}) b) x JOIN (SELECT a.cx AS ix, a.cy AS iy, b.cx AS ox, b.cy AS oy, exp(-0.75 * {_DIST}) / sum(exp(-0.75 * {_DIST})) OVER (PARTITION BY a.cx, a.cy) AS prob FROM {inhabited_sql('taxi_like', 4)} a, ({S.grid_cells(4)}) b) y ON x.ox = y.ox AND x.oy = y.oy WHERE NOT (x.ix = y.ix AND x.iy = y.iy)")
def distance_loss_query(spark, sf):
    """Distance-scaled loss of the one-member subset mechanism at eps' = 1.5, by a self-join on outputs, over the cells that orders lie in."""
    table_ = SubsetExponentialMechanism(1.5, unit_grid(4)).rank_table(spark).join(inhabited(spark, sf, "taxi_like", 4).select((F.col("cy") * 4 + F.col("cx")).alias("cell")), "cell").select("cell", "other", "prob")
    a, b = table_.alias("a"), table_.alias("b")
    dist = F.hypot(F.col("a.cell") % 4 - F.col("b.cell") % 4, F.floor(F.col("a.cell") / 4) - F.floor(F.col("b.cell") / 4))
    return a.join(b, F.col("a.other") == F.col("b.other")).where(F.col("a.cell") != F.col("b.cell")).agg(r6(F.max(F.abs(F.log(F.col("a.prob") / F.col("b.prob"))) / dist)).alias("loss"))


_BUDGETS_SUBSET = (0.5, 1.0, 2.0, 4.0)


def _privacy_of_sets(k: int) -> str:
    """Local privacy under the uniform prior over all sets of k of 25 cells."""
    cells = [f"(SELECT CAST(range AS INTEGER) AS c{j} FROM range(25)) t{j}" for j in range(k)]
    sets = f"SELECT [{', '.join(f'c{j}' for j in range(k))}] AS members FROM {', '.join(cells)}" + (" WHERE " + " AND ".join(f"c{j} < c{j + 1}" for j in range(k - 1)) if k > 1 else "")
    pairs = f"SELECT a.cy * 5 + a.cx AS cell, b.cy * 5 + b.cx AS other, {_DIST} AS dist FROM ({S.grid_cells(5)}) a, ({S.grid_cells(5)}) b"
    near = f"SELECT s.members, d.cell, min(d.dist) AS near FROM (SELECT members, unnest(members) AS m FROM ({sets})) s JOIN ({pairs}) d ON d.other = s.m GROUP BY s.members, d.cell"
    prob = f"SELECT e.eps, members, cell, exp(-0.5 * e.eps * near) / sum(exp(-0.5 * e.eps * near)) OVER (PARTITION BY e.eps, cell) AS prob FROM ({near}), (SELECT CAST(unnest({list(_BUDGETS_SUBSET)}) AS DOUBLE) AS eps) e"
    return f"""SELECT CAST({k} AS INTEGER) AS k, eps AS eps_prime, round(sum(part / total) / 25, 6) AS lp, CAST(0 AS DOUBLE) AS standard_error FROM (SELECT x.eps, x.members, sum(x.prob * y.prob * d.dist) AS part FROM p{k} x JOIN p{k} y ON x.eps = y.eps AND x.members = y.members JOIN d ON d.cell = x.cell AND d.other = y.cell GROUP BY x.eps, x.members)
JOIN (SELECT eps, members, sum(prob) AS total FROM p{k} GROUP BY eps, members) USING (eps, members) GROUP BY eps""", f"p{k} AS MATERIALIZED ({prob})", f"d AS MATERIALIZED ({pairs})"


_SETS = [_privacy_of_sets(k) for k in (1, 2, 3)]


@query("local_privacy_subset", f"WITH {_SETS[0][2]}, {', '.join(x[1] for x in _SETS)} " + " UNION ALL ".join(x[0] for x in _SETS))
def local_privacy_subset_query(spark, sf):
    rows = [(k, e, *local_privacy_subset(SubsetExponentialMechanism(e, unit_grid(5), k))) for k in (1, 2, 3) for e in _BUDGETS_SUBSET]
    return spark.createDataFrame(rows, "k int, eps_prime double, lp double, standard_error double").withColumn("lp", r6(F.col("lp")))


def _matched(eps):
    grid = unit_grid(5)
    distances = SubsetExponentialMechanism(1.0, grid).distances
    lp = local_privacy(DiskMechanism(eps, grid).channel_matrix(), distances)
    return lp, match_privacy(lp, grid)


@query("match_privacy")
def match_privacy_query(spark, sf):
    """Equal-privacy pairs (eps of the disk, eps' of the subset mechanism) under the uniform prior."""
    return spark.createDataFrame([(e, *_matched(e)) for e in EPS[:6]], "eps double, lp double, eps_prime double")


def _disk_privacy_sql(eps):
    m = S.channel(5, geo.grid_radius(eps, 5), S.disk_weights(geo.grid_radius(eps, 5), eps))
    return f"SELECT CAST({eps} AS DOUBLE) AS eps, round(sum(part / 25 / total), 5) AS disk_lp, round(sum(part / 25 / total), 5) AS subset_lp FROM (SELECT a.ox, a.oy, sum(a.prob * b.prob * {_DIST}) AS part FROM ({m}) a JOIN ({m}) b ON a.ox = b.ox AND a.oy = b.oy GROUP BY a.ox, a.oy) JOIN (SELECT ox, oy, sum(prob) AS total FROM ({m}) GROUP BY ox, oy) USING (ox, oy)"


@query("match_privacy_check", " UNION ALL ".join(_disk_privacy_sql(e) for e in EPS[:6]))
def match_privacy_check(spark, sf):
    """What matching is for: the subset mechanism at the budget found has the disk's local privacy."""
    grid = unit_grid(5)
    rows = [(e, round(lp, 5), round(local_privacy_subset(SubsetExponentialMechanism(found, grid))[0], 5)) for e in EPS[:6] for lp, found in [_matched(e)]]
    return spark.createDataFrame(rows, "eps double, disk_lp double, subset_lp double")


@query("output_space", " UNION ALL ".join(f"SELECT CAST({d} AS INTEGER) AS d, CAST({k} AS INTEGER) AS k, round(exp(lgamma({d * d + 1}) - lgamma({k + 1}) - lgamma({d * d - k + 1})), 0) AS sets, (SELECT count(*) FROM ({S.outputs(d, 1)})) AS cells" for d, k in ((3, 2), (5, 2), (5, 3), (5, 6))))
def output_space(spark, sf):
    rows = [(d, k, float(round(SubsetExponentialMechanism(1.0, unit_grid(d), k).output_space())), geo.disk_stencil(1).output_count(d)) for d, k in ((3, 2), (5, 2), (5, 3), (5, 6))]
    return spark.createDataFrame(rows, "d int, k int, sets double, cells long")


@query("rate_map", f"""SELECT g.cx, g.cy, round(1000 * coalesce(h.errors, 0) / CAST(greatest(coalesce(h.n, 0), 1) AS DOUBLE), 6) AS per_thousand, coalesce(h.n, 0) AS n FROM ({S.grid_cells(5)}) g LEFT JOIN (SELECT cx, cy, count(*) AS n, count(*) FILTER (e.event_type = 'error') AS errors FROM ({S.cells('crime_like', 5)}) c JOIN events e ON e.event_id = c.user_id GROUP BY cx, cy) h ON h.cx = g.cx AND h.cy = g.cy""")
def rate_map(spark, sf):
    cells = assign_cells(event_points(spark, sf, "event_type"), POINT_SETS["crime_like"].grid(5))
    counts = cells.groupBy("cx", "cy").agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("errors"))
    full = input_cells(spark, unit_grid(5)).join(counts, ["cx", "cy"], "left")
    return full.select("cx", "cy", r6(1000 * F.coalesce("errors", F.lit(0)) / F.greatest(F.coalesce("n", F.lit(0)), F.lit(1))).alias("per_thousand"), F.coalesce("n", F.lit(0)).alias("n"))


@query("range_extraction", f"SELECT part, CAST(y / 10 AS INTEGER) AS band, count(*) AS n FROM ({POINT_SETS['crime_like'].sql}) WHERE x BETWEEN 5 AND 25 AND y BETWEEN 20 AND 60 GROUP BY ALL")
def range_extraction(spark, sf):
    """The rectangle on both coordinates (days and value) over the whole table, then the square part."""
    kept = points(spark, sf, "crime_like").where(F.col("x").between(5, 25) & F.col("y").between(20, 60))
    return kept.groupBy("part", F.rint(F.col("y") / 10).cast("int").alias("band")).agg(F.count("*").alias("n"))
