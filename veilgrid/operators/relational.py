"""Relational operators around the methods: scans, filters, joins, aggregates, windows, sorts and set operations, each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec, assign_cells, input_cells, output_cells
from veilgrid.geometry import disk_stencil
from veilgrid.noise import hash_uniform
from veilgrid.plans import sql_text as S
from veilgrid.registry import query, table
from veilgrid.sources.datasets import POINT_SETS, uniform_sql

UNIT = lambda d: GridSpec(0.0, 0.0, 1.0, 1.0, d)


def _cells(spark, sf, name: str = "taxi_like", d: int = 5) -> DataFrame:
    return assign_cells(POINT_SETS[name].read(spark, sf), POINT_SETS[name].grid(d)).select("user_id", "part", "cx", "cy")


_C = S.cells("taxi_like", 5)
_COUNTS = f"(SELECT cx, cy, count(*) AS n FROM ({_C}) GROUP BY cx, cy)"


def _counts(spark, sf):
    return _cells(spark, sf).groupBy("cx", "cy").agg(F.count("*").alias("n"))


# ---- scans and projections ----

@query("op_scan_prune", "SELECT event_id, value FROM events")
def scan_prune(spark, sf):
    return table(spark, sf, "events").select("event_id", "value")


@query("op_scan_pushdown", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 100000 AND 200000 AND o_orderdate >= TIMESTAMP '1996-01-01' AND o_orderdate < TIMESTAMP '1997-01-01'")
def scan_pushdown(spark, sf):
    o = table(spark, sf, "orders")
    stamp = lambda s: F.lit(s).cast(o.schema["o_orderdate"].dataType)
    return o.where(F.col("o_totalprice").between(100000, 200000) & (F.col("o_orderdate") >= stamp("1996-01-01 00:00:00")) & (F.col("o_orderdate") < stamp("1997-01-01 00:00:00"))).select("o_orderkey", "o_totalprice")


@query("op_scan_html", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, length(html) AS chars FROM pages")
def scan_html(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), F.length("html").cast("long").alias("chars"))


@query("op_scan_conversations", "SELECT conv_id, CAST(max(turn) AS BIGINT) AS last_turn, CAST(sum(length(text)) AS BIGINT) AS chars FROM conversations GROUP BY conv_id")
def scan_conversations(spark, sf):
    return table(spark, sf, "conversations").groupBy("conv_id").agg(F.max("turn").cast("long").alias("last_turn"), F.sum(F.length("text")).cast("long").alias("chars"))


@query("op_view_sql", "SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY o_orderstatus")
def view_sql(spark, sf):
    table(spark, sf, "orders").createOrReplaceTempView("_orders_view")
    return spark.sql("SELECT o_orderstatus, count(*) AS n FROM _orders_view GROUP BY o_orderstatus")


@query("op_range_grid", S.grid_cells(40))
def range_grid(spark, sf):
    return input_cells(spark, UNIT(40))


@query("op_udtf_grid", S.grid_cells(7))
def udtf_grid(spark, sf):
    from veilgrid.functions.sql_surface import register

    register(spark)
    return spark.sql("SELECT * FROM ldp_grid(7)")


@query("op_udtf_stencil", f"SELECT dx, dy, round(s, 9) AS s FROM ({S.stencil(3)})")
def udtf_stencil(spark, sf):
    from veilgrid.functions.sql_surface import register

    register(spark)
    return spark.sql("SELECT dx, dy, round(s, 9) AS s FROM ldp_stencil(3)")


@query("op_sql_functions", "SELECT o_orderkey, CAST(least(floor(o_totalprice * 5 / 500000), 4) AS INTEGER) AS cx FROM orders")
def sql_functions(spark, sf):
    from veilgrid.functions.sql_surface import register

    register(spark)
    table(spark, sf, "orders").createOrReplaceTempView("_orders_view")
    return spark.sql("SELECT o_orderkey, ldp_cell(o_totalprice, 0D, 500000D, 5) AS cx FROM _orders_view")


@query("op_project_cell", _C)
def project_cell(spark, sf):
    return _cells(spark, sf)


@query("op_project_rescale", "SELECT l_orderkey, l_linenumber, round(greatest(0, least(1, l_extendedprice / 105000)), 9) AS x FROM lineitem")
def project_rescale(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("l_extendedprice") / 105000)), 9).alias("x"))


@query("op_select_expr", "SELECT event_id AS id, CAST(floor(value) AS BIGINT) AS whole, upper(event_type) AS kind FROM events")
def select_expr(spark, sf):
    return table(spark, sf, "events").selectExpr("event_id AS id", "CAST(floor(value) AS BIGINT) AS whole", "upper(event_type) AS kind")


@query("op_filter_range", "SELECT event_id FROM events WHERE value BETWEEN 10 AND 20")
def filter_range(spark, sf):
    return table(spark, sf, "events").where(F.col("value").between(10, 20)).select("event_id")


@query("op_filter_in", "SELECT o_orderkey FROM orders WHERE o_orderstatus IN ('F', 'P')")
def filter_in(spark, sf):
    return table(spark, sf, "orders").where(F.col("o_orderstatus").isin("F", "P")).select("o_orderkey")


@query("op_filter_not", "SELECT o_orderkey FROM orders WHERE NOT (o_orderstatus = 'F' OR o_totalprice > 250000)")
def filter_not(spark, sf):
    return table(spark, sf, "orders").where(~((F.col("o_orderstatus") == "F") | (F.col("o_totalprice") > 250000))).select("o_orderkey")


@query("op_filter_null_nan", "SELECT event_id, coalesce(v, -1) AS v FROM (SELECT event_id, CASE WHEN event_id % 7 = 0 THEN NULL ELSE value END AS v FROM events) WHERE v IS NULL OR v > 5")
def filter_null_nan(spark, sf):
    v = F.when(F.col("event_id") % 7 != 0, F.col("value"))
    e = table(spark, sf, "events").select("event_id", v.alias("v"))
    return e.where(F.col("v").isNull() | (~F.isnan("v") & (F.col("v") > 5))).select("event_id", F.coalesce(F.nanvl("v", F.lit(0.0)), F.lit(-1.0)).alias("v"))


@query("op_filter_like", "SELECT p_partkey FROM part WHERE p_type LIKE '%O%' OR regexp_matches(p_name, '[0-9]3') OR starts_with(p_brand, 'Brand#2')")
def filter_like(spark, sf):
    return table(spark, sf, "part").where(F.col("p_type").like("%O%") | F.col("p_name").rlike("[0-9]3") | F.col("p_brand").startswith("Brand#2")).select("p_partkey")


@query("op_case_area", f"SELECT o.ox, o.oy, coalesce(s.kind, 'low') AS area FROM ({S.outputs(9, 3)}) o LEFT JOIN ({S.stencil(3)}) s ON s.dx = o.ox - 4 AND s.dy = o.oy - 4")
def case_area(spark, sf):
    dx, dy = F.col("ox") - 4, F.col("oy") - 4
    crossed = F.pow(F.greatest(2 * F.abs(dx) - 1, F.lit(0)), 2) + F.pow(F.greatest(2 * F.abs(dy) - 1, F.lit(0)), 2) < 36
    area = F.when(dx * dx + dy * dy <= 9, "pure").when(crossed, "border").otherwise("low")
    return output_cells(spark, UNIT(9), disk_stencil(3)).select("ox", "oy", area.alias("area"))


@query("op_dedup_user", "SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events) WHERE k = 1")
def dedup_user(spark, sf):
    """One report per user: the first event, by an aggregate that combines before the shuffle (no window over a heavy user)."""
    first = F.min_by(F.col("event_id"), F.struct("ts", "event_id"))
    return table(spark, sf, "events").groupBy("user_id").agg(first.alias("event_id"))


@query("op_sample_hash", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE {uniform_sql('l_orderkey', 'l_linenumber')} < 0.1")
def sample_hash(spark, sf):
    return table(spark, sf, "lineitem").where(hash_uniform(F.col("l_orderkey"), F.col("l_linenumber")) < 0.1).select("l_orderkey", "l_linenumber")


# ---- joins ----

@query("op_join_inner_equi", "SELECT o_orderstatus, l_returnflag, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY ALL")
def join_inner_equi(spark, sf):
    o, li = table(spark, sf, "orders").select("o_orderkey", "o_orderstatus"), table(spark, sf, "lineitem").select("l_orderkey", "l_returnflag")
    return o.join(li.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus", "l_returnflag").agg(F.count("*").alias("n"))


@query("op_join_shuffle_hash", "SELECT c_nationkey, count(*) AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY c_nationkey")
def join_shuffle_hash(spark, sf):
    c = table(spark, sf, "customer").select("c_custkey", "c_nationkey").hint("shuffle_hash")
    return table(spark, sf, "orders").select("o_custkey").join(c, F.col("c_custkey") == F.col("o_custkey")).groupBy("c_nationkey").agg(F.count("*").alias("n"))


@query("op_join_broadcast", f"SELECT c.cx + s.dx AS ox, c.cy + s.dy AS oy, CAST(sum(n) AS BIGINT) AS n FROM {_COUNTS} c, ({S.stencil(2)}) s GROUP BY ALL")
def join_broadcast(spark, sf):
    """Counts spread over a stencil, whose size depends on the radius alone."""
    s = spark.createDataFrame([(c.dx, c.dy) for c in disk_stencil(2).cells], "dx int, dy int")
    moved = _counts(spark, sf).crossJoin(F.broadcast(s))
    return moved.groupBy((F.col("cx") + F.col("dx")).alias("ox"), (F.col("cy") + F.col("dy")).alias("oy")).agg(F.sum("n").alias("n"))


@query("op_join_left_zero_fill", f"SELECT g.cx, g.cy, coalesce(c.n, 0) AS n FROM ({S.grid_cells(7)}) g LEFT JOIN {_COUNTS} c ON c.cx = g.cx AND c.cy = g.cy")
def join_left_zero_fill(spark, sf):
    return input_cells(spark, UNIT(7)).join(_counts(spark, sf), ["cx", "cy"], "left").select("cx", "cy", F.coalesce("n", F.lit(0)).alias("n"))


@query("op_join_right", f"SELECT g.cx, g.cy, c.n FROM {_COUNTS} c RIGHT JOIN ({S.grid_cells(6)}) g ON c.cx = g.cx AND c.cy = g.cy")
def join_right(spark, sf):
    return _counts(spark, sf).join(input_cells(spark, UNIT(6)), ["cx", "cy"], "right").select("cx", "cy", "n")


_PART_F = f"(SELECT cx, cy, count(*) AS n FROM ({_C}) WHERE part = 'F' AND cx > 0 GROUP BY cx, cy)"
_PART_P = f"(SELECT cx, cy, count(*) AS n FROM ({_C}) WHERE part = 'P' AND cx < 4 GROUP BY cx, cy)"


@query("op_join_full_hist", f"SELECT coalesce(a.cx, b.cx) AS cx, coalesce(a.cy, b.cy) AS cy, coalesce(a.n, 0) AS n_f, coalesce(b.n, 0) AS n_p FROM {_PART_F} a FULL OUTER JOIN {_PART_P} b ON a.cx = b.cx AND a.cy = b.cy")
def join_full_hist(spark, sf):
    c = _cells(spark, sf)
    count = lambda rows, name: rows.groupBy("cx", "cy").agg(F.count("*").alias(name))
    a, b = count(c.where((F.col("part") == "F") & (F.col("cx") > 0)), "n_f"), count(c.where((F.col("part") == "P") & (F.col("cx") < 4)), "n_p")
    return a.join(b, ["cx", "cy"], "full_outer").select("cx", "cy", F.coalesce("n_f", F.lit(0)).alias("n_f"), F.coalesce("n_p", F.lit(0)).alias("n_p"))


@query("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 450000)")
def join_semi(spark, sf):
    big = table(spark, sf, "orders").where(F.col("o_totalprice") > 450000).select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf, "customer").select("c_custkey").join(big, "c_custkey", "left_semi")


@query("op_join_anti", f"SELECT ox, oy FROM ({S.outputs(9, 3)}) o WHERE NOT EXISTS (SELECT 1 FROM ({S.stencil(3)}) s WHERE s.dx = o.ox - 4 AND s.dy = o.oy - 4)")
def join_anti(spark, sf):
    near = spark.createDataFrame([(c.dx + 4, c.dy + 4) for c in disk_stencil(3).cells], "ox int, oy int")
    return output_cells(spark, UNIT(9), disk_stencil(3)).join(F.broadcast(near), ["ox", "oy"], "left_anti")


@query("op_join_cross_params", f"SELECT eps, b, cx, cy, n FROM {_COUNTS}, (SELECT CAST(unnest([1.4, 3.5]) AS DOUBLE) AS eps), (SELECT CAST(unnest([1, 2, 3]) AS INTEGER) AS b)")
def join_cross_params(spark, sf):
    params = spark.createDataFrame([(e, b) for e in (1.4, 3.5) for b in (1, 2, 3)], "eps double, b int")
    return _counts(spark, sf).crossJoin(F.broadcast(params)).select("eps", "b", "cx", "cy", "n")


@query("op_join_theta_distance", f"SELECT a.cx, a.cy, count(*) AS near FROM ({S.grid_cells(9)}) a JOIN ({S.grid_cells(9)}) b ON (a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy) <= 9 GROUP BY ALL")
def join_theta_distance(spark, sf):
    a, b = input_cells(spark, UNIT(9)), F.broadcast(input_cells(spark, UNIT(9)).select(F.col("cx").alias("x"), F.col("cy").alias("y")))
    dx, dy = F.col("cx") - F.col("x"), F.col("cy") - F.col("y")
    return a.join(b, dx * dx + dy * dy <= 9).groupBy("cx", "cy").agg(F.count("*").alias("near"))


@query("op_join_grid_neighbour", f"SELECT a.cx, a.cy, count(*) AS near FROM ({S.grid_cells(24)}) a JOIN ({S.grid_cells(24)}) b ON (a.cx - b.cx) * (a.cx - b.cx) + (a.cy - b.cy) * (a.cy - b.cy) <= 25 GROUP BY ALL")
def join_grid_neighbour(spark, sf):
    from veilgrid.domain import distance_set

    cells = input_cells(spark, UNIT(24))
    near = distance_set(cells.select(F.col("cx").alias("ox"), F.col("cy").alias("oy")), cells, 5)
    return near.groupBy("cx", "cy").agg(F.count("*").alias("near"))


_U = uniform_sql("event_id", 0)


@query("op_join_range_cdf", f"SELECT s.dx, s.dy, count(*) AS n FROM (SELECT {_U} * 9 AS u FROM events) e JOIN (SELECT dx, dy, row_number() OVER (ORDER BY dy, dx) - 1 AS lo FROM ({S.stencil(1)})) s ON e.u >= s.lo AND e.u < s.lo + 1 GROUP BY ALL")
def join_range_cdf(spark, sf):
    """Draws found in a cumulative table: an equi-join on the whole part of the draw, then the exact range."""
    rows = [(k, c.dx, c.dy) for k, c in enumerate(sorted(disk_stencil(1).cells, key=lambda c: (c.dy, c.dx)))]
    cdf = F.broadcast(spark.createDataFrame(rows, "lo int, dx int, dy int"))
    u = table(spark, sf, "events").select((hash_uniform(F.col("event_id"), 0) * 9).alias("u"))
    return u.withColumn("lo", F.floor("u").cast("int")).join(cdf, "lo").where(F.col("u") < F.col("lo") + 1).groupBy("dx", "dy").agg(F.count("*").alias("n"))


_SPANS = "SELECT user_id, event_id, CAST(epoch_us(ts) // 1000000 AS BIGINT) AS lo, CAST(epoch_us(ts) // 1000000 AS BIGINT) + 43200 AS hi FROM events"


@query("op_join_interval_overlap", f"SELECT a.user_id, count(*) AS pairs FROM ({_SPANS}) a JOIN ({_SPANS}) b ON a.user_id = b.user_id AND a.event_id < b.event_id AND a.lo < b.hi AND b.lo < a.hi GROUP BY a.user_id")
def join_interval_overlap(spark, sf):
    """Overlaps per user: spans are cut at half-day blocks, joined by (user, block), and kept in the block where the later one starts."""
    e = table(spark, sf, "events").select("user_id", "event_id", _epoch(F.col("ts")).alias("lo")).withColumn("hi", F.col("lo") + 43200)
    blocks = e.withColumn("block", F.explode(F.sequence(F.floor(F.col("lo") / 43200), F.floor((F.col("hi") - 1) / 43200))))
    a, b = blocks.alias("a"), blocks.alias("b")
    meet = (F.col("a.lo") < F.col("b.hi")) & (F.col("b.lo") < F.col("a.hi")) & (F.col("a.event_id") < F.col("b.event_id"))
    once = F.col("a.block") == F.floor(F.greatest("a.lo", "b.lo") / 43200)
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.block") == F.col("b.block"))).where(meet & once).groupBy(F.col("a.user_id").alias("user_id")).agg(F.count("*").alias("pairs"))


def _epoch(ts):
    """Whole seconds since 1970 from the fields of a zone-less time."""
    return (F.datediff(F.to_date(ts), F.lit("1970-01-01").cast("date")) * 86400 + F.hour(ts) * 3600 + F.minute(ts) * 60 + F.second(ts)).cast("long")


@query("op_join_asof", "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def join_asof(spark, sf):
    """Latest click of the same user at or before each purchase: one union and one ordered window, no pair is made."""
    e = table(spark, sf, "events").where(F.col("event_type").isin("purchase", "click"))
    order = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(order)
    return e.withColumn("view_id", last).where(F.col("event_type") == "purchase").select("event_id", "view_id")


@query("op_join_self_channel", f"SELECT a.ox, a.oy, round(sum(a.prob * b.prob), 9) AS overlap FROM ({S.channel(4, 1, S.disk_weights(1, 2.0))}) a JOIN ({S.channel(4, 1, S.disk_weights(1, 2.0))}) b ON a.ox = b.ox AND a.oy = b.oy GROUP BY ALL")
def join_self_channel(spark, sf):
    from veilgrid.mechanisms import DiskMechanism

    c = DiskMechanism(2.0, UNIT(4), 1).channel(spark)
    a, b = c.alias("a"), c.alias("b")
    return a.join(b, (F.col("a.ox") == F.col("b.ox")) & (F.col("a.oy") == F.col("b.oy"))).groupBy(F.col("a.ox").alias("ox"), F.col("a.oy").alias("oy")).agg(F.round(F.sum(F.col("a.prob") * F.col("b.prob")), 9).alias("overlap"))


@query("op_join_null_safe", "SELECT a.part, count(*) AS pairs FROM (SELECT nullif(o_orderstatus, 'P') AS part FROM orders) a JOIN (SELECT DISTINCT nullif(o_orderstatus, 'P') AS part FROM orders) b ON a.part IS NOT DISTINCT FROM b.part GROUP BY a.part")
def join_null_safe(spark, sf):
    """All orders; the other side is one row per status, so it is broadcast and no status is one task's work."""
    a = table(spark, sf, "orders").select(F.nullif(F.col("o_orderstatus"), F.lit("P")).alias("part"))
    b = F.broadcast(a.distinct().withColumnRenamed("part", "other"))
    return a.join(b, F.col("part").eqNullSafe(F.col("other"))).groupBy("part").agg(F.count("*").alias("pairs"))


@query("op_join_star", "SELECT r_name, o_orderstatus, CAST(floor(o_totalprice / 100000) AS INTEGER) AS band, count(*) AS n FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ALL")
def join_star(spark, sf):
    o = table(spark, sf, "orders").select("o_custkey", "o_orderstatus", F.floor(F.col("o_totalprice") / 100000).cast("int").alias("band"))
    c, n, r = (table(spark, sf, t) for t in ("customer", "nation", "region"))
    places = n.join(F.broadcast(r), F.col("r_regionkey") == F.col("n_regionkey")).select("n_nationkey", "r_name")
    return o.join(c.select("c_custkey", "c_nationkey"), F.col("c_custkey") == F.col("o_custkey")).join(F.broadcast(places), F.col("n_nationkey") == F.col("c_nationkey")).groupBy("r_name", "o_orderstatus", "band").agg(F.count("*").alias("n"))


@query("op_join_lateral", f"SELECT c.cx, c.cy, c.cx + k.dx AS ox, c.cy + k.dy AS oy FROM ({S.grid_cells(6)}) c, ({S.stencil(1)}) k")
def join_lateral(spark, sf):
    near = F.array(*[F.struct(F.lit(c.dx).alias("dx"), F.lit(c.dy).alias("dy")) for c in disk_stencil(1).cells])
    return input_cells(spark, UNIT(6)).select("cx", "cy", F.inline(near)).select("cx", "cy", (F.col("cx") + F.col("dx")).alias("ox"), (F.col("cy") + F.col("dy")).alias("oy"))


@query("op_join_salted", "SELECT event_type, count(*) AS n, round(sum(value * w), 4) AS total FROM events JOIN (SELECT event_type AS k, CAST(length(event_type) AS DOUBLE) AS w FROM (SELECT DISTINCT event_type FROM events)) t ON k = event_type GROUP BY event_type")
def join_salted(spark, sf):
    """A few hot keys: both sides get a salt, the small one every value of it."""
    salts = 16
    e = table(spark, sf, "events").select("event_type", "value", F.pmod(F.xxhash64("event_id"), F.lit(salts)).alias("salt"))
    kinds = table(spark, sf, "events").select("event_type").distinct().select("event_type", F.length("event_type").cast("double").alias("w"), F.explode(F.transform(F.sequence(F.lit(0), F.lit(salts - 1)), lambda k: k.cast("long"))).alias("salt"))
    part = e.join(kinds, ["event_type", "salt"]).groupBy("event_type", "salt").agg(F.count("*").alias("n"), F.sum(F.col("value") * F.col("w")).alias("total"))
    return part.groupBy("event_type").agg(F.sum("n").alias("n"), F.round(F.sum("total"), 4).alias("total"))


# ---- aggregates ----

@query("op_agg_count_cell", f"SELECT cx, cy, n FROM {_COUNTS}")
def agg_count_cell(spark, sf):
    return _counts(spark, sf)


@query("op_agg_global_bounds", "SELECT min(o_totalprice) AS lo, max(o_totalprice) AS hi FROM orders")
def agg_global_bounds(spark, sf):
    return table(spark, sf, "orders").agg(F.min("o_totalprice").alias("lo"), F.max("o_totalprice").alias("hi"))


@query("op_agg_distinct", f"SELECT c.cx, c.cy, count(DISTINCT e.user_id) AS users FROM ({S.cells('crime_like', 5)}) c JOIN events e ON e.event_id = c.user_id GROUP BY ALL")
def agg_distinct(spark, sf):
    owner = table(spark, sf, "events").select("event_id", F.col("user_id").alias("owner"))
    c = _cells(spark, sf, "crime_like").join(owner, F.col("event_id") == F.col("user_id"))
    return c.groupBy("cx", "cy").agg(F.countDistinct("owner").alias("users"))


@query("op_agg_approx_distinct")
def agg_approx_distinct(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.countDistinct("user_id").alias("exact"))


@query("op_agg_grouping_sets", f"SELECT cx, cy, CAST(grouping(cx) AS INTEGER) AS gx, count(*) AS n FROM ({_C}) GROUP BY GROUPING SETS ((cx), (cy))")
def agg_grouping_sets(spark, sf):
    c = _cells(spark, sf)
    return c.groupingSets([["cx"], ["cy"]], "cx", "cy").agg(F.grouping("cx").cast("int").alias("gx"), F.count("*").alias("n"))


@query("op_agg_rollup", f"SELECT part, cy, cx, count(*) AS n FROM ({_C}) GROUP BY ROLLUP (part, cy, cx)")
def agg_rollup(spark, sf):
    return _cells(spark, sf).rollup("part", "cy", "cx").agg(F.count("*").alias("n"))


@query("op_agg_cube", f"SELECT cx, cy, count(*) AS n FROM ({_C}) GROUP BY CUBE (cx, cy)")
def agg_cube(spark, sf):
    return _cells(spark, sf).cube("cx", "cy").agg(F.count("*").alias("n"))


_PIVOT = ", ".join(f"count(*) FILTER (cx = {k}) AS c{k}" for k in range(5))


@query("op_agg_pivot", f"SELECT cy, {_PIVOT} FROM ({_C}) GROUP BY cy")
def agg_pivot(spark, sf):
    p = _cells(spark, sf).groupBy("cy").pivot("cx", list(range(5))).agg(F.count(F.lit(1)))
    return p.select("cy", *[F.coalesce(F.col(str(k)), F.lit(0)).alias(f"c{k}") for k in range(5)])


@query("op_agg_unpivot", "SELECT p_partkey, 'p_size' AS field, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def agg_unpivot(spark, sf):
    p = table(spark, sf, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return p.unpivot("p_partkey", ["p_size", "p_retailprice"], "field", "v")


@query("op_agg_moments", f"SELECT part, round(avg(x), 6) AS mean, round(var_pop(x), 6) AS var_p, round(var_samp(x), 6) AS var_s, round(stddev_pop(y), 6) AS sd_p, round(corr(x, y), 6) AS corr, round(covar_pop(x, y), 6) AS cov, round(skewness_pop, 4) AS skew FROM (SELECT *, avg((x - mx) * (x - mx) * (x - mx)) OVER (PARTITION BY part) / pow(var_pop(x) OVER (PARTITION BY part), 1.5) AS skewness_pop FROM (SELECT *, avg(x) OVER (PARTITION BY part) AS mx FROM ({POINT_SETS['normal_nat'].sql}))) GROUP BY part, skewness_pop")
def agg_moments(spark, sf):
    r = F.round
    return POINT_SETS["normal_nat"].read(spark, sf).groupBy("part").agg(r(F.avg("x"), 6).alias("mean"), r(F.var_pop("x"), 6).alias("var_p"), r(F.var_samp("x"), 6).alias("var_s"), r(F.stddev_pop("y"), 6).alias("sd_p"), r(F.corr("x", "y"), 6).alias("corr"), r(F.covar_pop("x", "y"), 6).alias("cov"), r(F.skewness("x"), 4).alias("skew"))


@query("op_agg_percentiles", "SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(median(value), 6) AS mid, round(quantile_cont(value, 0.9), 6) AS q9 FROM events GROUP BY event_type")
def agg_percentiles(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.25)), 6).alias("q1"), F.round(F.median("value"), 6).alias("mid"), F.round(F.percentile("value", F.lit(0.9)), 6).alias("q9"))


@query("op_agg_percentile_approx")
def agg_percentile_approx(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.percentile_approx("value", [0.25, 0.5, 0.9], 10000).alias("q"))


@query("op_agg_filter_clause", "SELECT user_id, count(*) FILTER (event_type = 'error') AS errors, count(*) AS n FROM events GROUP BY user_id")
def agg_filter_clause(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "error").alias("errors"), F.count("*").alias("n"))


@query("op_agg_max_by", "SELECT user_id, max(event_id) FILTER (value = hi) AS top_event, min(event_id) FILTER (value = lo) AS low_event FROM (SELECT *, max(value) OVER (PARTITION BY user_id) AS hi, min(value) OVER (PARTITION BY user_id) AS lo FROM events) GROUP BY user_id")
def agg_max_by(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top_event"), F.min_by("event_id", F.struct("value", "event_id")).alias("low_event"))


@query("op_agg_bool", "SELECT o_orderstatus, bool_and(o_totalprice > 1000) AS all_over, bool_or(o_totalprice > 499000) AS any_over FROM orders GROUP BY o_orderstatus")
def agg_bool(spark, sf):
    return table(spark, sf, "orders").groupBy("o_orderstatus").agg(F.every(F.col("o_totalprice") > 1000).alias("all_over"), F.some(F.col("o_totalprice") > 499000).alias("any_over"))


@query("op_agg_collect", f"SELECT part, array_to_string(list_sort(list(DISTINCT cx)), ',') AS columns FROM ({_C}) GROUP BY part")
def agg_collect(spark, sf):
    return _cells(spark, sf).groupBy("part").agg(F.array_join(F.sort_array(F.collect_set("cx")), ",").alias("columns"))


@query("op_agg_product", "SELECT event_type, round(exp(sum(ln(1 + value / 1e5))), 6) AS growth FROM events GROUP BY event_type")
def agg_product(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.round(F.exp(F.sum(F.log1p(F.col("value") / 1e5))), 6).alias("growth"))


@query("op_agg_having", f"SELECT cx, cy, n FROM {_COUNTS} WHERE n > (SELECT avg(n) FROM {_COUNTS})")
def agg_having(spark, sf):
    c = _counts(spark, sf)
    return c.where(F.col("n") > c.select(F.avg("n")).scalar())


@query("op_agg_bit_or", "SELECT user_id, CAST(bit_or(1 << (event_id % 25)) AS BIGINT) AS seen, CAST(bit_count(bit_or(1 << (event_id % 25))) AS INTEGER) AS kinds FROM (SELECT user_id, CAST(event_id AS BIGINT) AS event_id FROM events) GROUP BY user_id")
def agg_bit_or(spark, sf):
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("event_id") % 25).cast("int"))
    return table(spark, sf, "events").groupBy("user_id").agg(F.bit_or(bit).alias("seen")).select("user_id", "seen", F.bit_count("seen").alias("kinds"))


@query("op_agg_histogram_numeric")
def agg_histogram_numeric(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.histogram_numeric("value", F.lit(10)).alias("bins"))


@query("op_agg_count_min_sketch")
def agg_count_min_sketch(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.95), F.lit(7)).alias("sketch"))


# ---- windows ----

@query("op_win_row_number", f"SELECT cx, cy, n, CAST(row_number() OVER (ORDER BY n DESC, cy, cx) AS INTEGER) AS k FROM {_COUNTS}")
def win_row_number(spark, sf):
    return _counts(spark, sf).withColumn("k", F.row_number().over(Window.orderBy(F.desc("n"), "cy", "cx")))


@query("op_win_rank_dense_ntile", f"SELECT cx, cy, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, CAST(ntile(4) OVER (ORDER BY cx, cy) AS INTEGER) AS quarter FROM {_COUNTS} WINDOW w AS (ORDER BY cx)")
def win_rank_dense_ntile(spark, sf):
    w = Window.orderBy("cx")
    return _counts(spark, sf).select("cx", "cy", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(Window.orderBy("cx", "cy")).alias("quarter"))


@query("op_win_cumsum", f"SELECT cx, cy, CAST(sum(n) OVER (PARTITION BY cy ORDER BY cx) AS BIGINT) AS upto FROM {_COUNTS}")
def win_cumsum(spark, sf):
    return _counts(spark, sf).select("cx", "cy", F.sum("n").over(Window.partitionBy("cy").orderBy("cx").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))


@query("op_win_share", f"SELECT cx, cy, round(n / CAST(sum(n) OVER () AS DOUBLE), 9) AS mass FROM {_COUNTS}")
def win_share(spark, sf):
    c = _counts(spark, sf)
    return c.select("cx", "cy", F.round(F.col("n") / c.select(F.sum("n")).scalar(), 9).alias("mass"))


@query("op_win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_lead(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@query("op_win_rows_smooth", f"SELECT cx, cy, CAST(n * 2 + coalesce(lag(n) OVER w, n) + coalesce(lead(n) OVER w, n) AS BIGINT) AS smooth FROM {_COUNTS} WINDOW w AS (PARTITION BY cy ORDER BY cx)")
def win_rows_smooth(spark, sf):
    w = Window.partitionBy("cy").orderBy("cx")
    return _counts(spark, sf).select("cx", "cy", (F.col("n") * 2 + F.coalesce(F.lag("n").over(w), F.col("n")) + F.coalesce(F.lead("n").over(w), F.col("n"))).alias("smooth"))


@query("op_win_range_axis", f"SELECT cx, cy, CAST(sum(n) OVER (PARTITION BY cy ORDER BY cx RANGE BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS near FROM {_COUNTS}")
def win_range_axis(spark, sf):
    return _counts(spark, sf).select("cx", "cy", F.sum("n").over(Window.partitionBy("cy").orderBy("cx").rangeBetween(-1, 1)).alias("near"))


@query("op_win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS last_day FROM (SELECT event_id, user_id, CAST(epoch_us(ts) // 1000000 AS BIGINT) AS s FROM events)")
def win_range_interval(spark, sf):
    e = table(spark, sf, "events").select("event_id", "user_id", _epoch(F.col("ts")).alias("s"))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("last_day"))


@query("op_win_first_last", "SELECT event_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
def win_first_last(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    grow, whole = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf, "events").select("event_id", F.first("event_id").over(grow).alias("first_id"), F.last("event_id").over(whole).alias("last_id"), F.nth_value("event_id", 2).over(grow).alias("second_id"))


@query("op_win_topk_part", f"SELECT part, cx, cy, n FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY n DESC, cy, cx) AS k FROM (SELECT part, cx, cy, count(*) AS n FROM ({_C}) GROUP BY ALL)) WHERE k <= 3")
def win_topk_part(spark, sf):
    c = _cells(spark, sf).groupBy("part", "cx", "cy").agg(F.count("*").alias("n"))
    return c.withColumn("k", F.row_number().over(Window.partitionBy("part").orderBy(F.desc("n"), "cy", "cx"))).where("k <= 3").drop("k")


# ---- sorts, limits, sets ----

@query("op_topk_cells", f"SELECT cx, cy, n FROM {_COUNTS} ORDER BY n DESC, cy, cx LIMIT 5")
def topk_cells(spark, sf):
    return _counts(spark, sf).orderBy(F.desc("n"), "cy", "cx").limit(5)


@query("op_topk_offset", f"SELECT cx, cy, n FROM {_COUNTS} ORDER BY n DESC, cy, cx LIMIT 5 OFFSET 5")
def topk_offset(spark, sf):
    return _counts(spark, sf).orderBy(F.desc("n"), "cy", "cx").offset(5).limit(5)


@query("op_sort_multi", f"SELECT cx, cy, n FROM {_COUNTS}")
def sort_multi(spark, sf):
    return _counts(spark, sf).orderBy(F.asc_nulls_last("cy"), F.desc_nulls_last("cx"))


@query("op_sort_within_partitions", f"SELECT cx, cy, n FROM {_COUNTS}")
def sort_within_partitions(spark, sf):
    return _counts(spark, sf).repartitionByRange(4, "cy").sortWithinPartitions("cy", "cx")


_BITS = " + ".join(f"((cx >> {k}) & 1) * {4 ** k} + ((cy >> {k}) & 1) * {2 * 4 ** k}" for k in range(5))


@query("op_morton_sort", f"SELECT cx, cy, CAST({_BITS} AS INTEGER) AS z FROM ({S.grid_cells(20)})")
def morton_sort(spark, sf):
    from veilgrid.functions.columns import morton

    return input_cells(spark, UNIT(20)).withColumn("z", morton("cx", "cy", 5)).sortWithinPartitions("z")


@query("op_set_union_all", "SELECT o_custkey AS k FROM orders UNION ALL SELECT c_custkey FROM customer")
def set_union_all(spark, sf):
    return table(spark, sf, "orders").select(F.col("o_custkey").alias("k")).union(table(spark, sf, "customer").select("c_custkey"))


@query("op_set_union_by_name", "SELECT o_custkey AS k, o_orderstatus AS status, NULL::VARCHAR AS segment FROM orders UNION ALL SELECT c_custkey, NULL, c_mktsegment FROM customer")
def set_union_by_name(spark, sf):
    a = table(spark, sf, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderstatus").alias("status"))
    return a.unionByName(table(spark, sf, "customer").select(F.col("c_mktsegment").alias("segment"), F.col("c_custkey").alias("k")), allowMissingColumns=True)


_IN, _OUT = f"SELECT cx AS ox, cy AS oy FROM ({S.grid_cells(9)})", S.outputs(9, 3)


def _in_out(spark):
    return input_cells(spark, UNIT(9)).select(F.col("cx").alias("ox"), F.col("cy").alias("oy")), output_cells(spark, UNIT(9), disk_stencil(3))


@query("op_set_intersect", f"({_IN}) INTERSECT ({_OUT})")
def set_intersect(spark, sf):
    a, b = _in_out(spark)
    return a.intersect(b)


@query("op_set_except", f"({_OUT}) EXCEPT ({_IN})")
def set_except(spark, sf):
    a, b = _in_out(spark)
    return b.exceptAll(a)


@query("op_set_intersect_all", "(SELECT o_custkey AS k FROM orders) INTERSECT ALL (SELECT c_custkey FROM customer)")
def set_intersect_all(spark, sf):
    return table(spark, sf, "orders").select(F.col("o_custkey").alias("k")).intersectAll(table(spark, sf, "customer").select("c_custkey"))


@query("op_set_except_all", "(SELECT o_custkey AS k FROM orders) EXCEPT ALL (SELECT c_custkey FROM customer)")
def set_except_all(spark, sf):
    return table(spark, sf, "orders").select(F.col("o_custkey").alias("k")).exceptAll(table(spark, sf, "customer").select("c_custkey"))


@query("op_set_distinct", "SELECT DISTINCT p_size, p_brand FROM part")
def set_distinct(spark, sf):
    return table(spark, sf, "part").select("p_size", "p_brand").distinct()


# ---- batch twins of the streams ----

@query("op_win_tumbling", "SELECT CAST(date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS INTEGER) AS day, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY day")
def win_tumbling(spark, sf):
    w = table(spark, sf, "events").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return w.select(F.datediff(F.to_date("w.start"), F.lit("1970-01-01").cast("date")).alias("day"), "n", "total")


@query("op_win_sliding", "SELECT CAST(k AS BIGINT) AS slot, count(*) AS n FROM (SELECT s // 21600 - unnest(range(4)) AS k FROM (SELECT epoch_us(ts) // 1000000 AS s FROM events)) GROUP BY k")
def win_sliding(spark, sf):
    w = table(spark, sf, "events").groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return w.select(F.floor(_epoch(F.col("w.start")) / 21600).alias("slot"), "n")


@query("op_win_session", "SELECT user_id, CAST(floor(min(s)) AS BIGINT) AS began, count(*) AS n FROM (SELECT user_id, s, sum(fresh) OVER (PARTITION BY user_id ORDER BY s, event_id) AS k FROM (SELECT *, CASE WHEN s - lag(s) OVER (PARTITION BY user_id ORDER BY s, event_id) < 21600 THEN 0 ELSE 1 END AS fresh FROM (SELECT user_id, event_id, epoch_us(ts) / 1000000.0 AS s FROM events))) GROUP BY user_id, k")
def win_session(spark, sf):
    w = table(spark, sf, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return w.select("user_id", _epoch(F.col("w.start")).alias("began"), "n")


@query("op_join_click_purchase", "SELECT p.event_id AS purchase_id, count(*) AS clicks FROM events p JOIN events c ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 DAY GROUP BY p.event_id")
def join_click_purchase(spark, sf):
    e = table(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    p, c = e.where(F.col("event_type") == "purchase").alias("p"), e.where(F.col("event_type") == "click").alias("c")
    when = (F.col("c.ts") <= F.col("p.ts")) & (F.col("c.ts") >= F.col("p.ts") - F.expr("INTERVAL 1 DAY"))
    return p.join(c, (F.col("c.user_id") == F.col("p.user_id")) & when).groupBy(F.col("p.event_id").alias("purchase_id")).agg(F.count("*").alias("clicks"))
