"""Small queries over the scalar functions that the methods lean on, each with its SQL."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from veilgrid.plans.sql_text import num
from veilgrid.registry import query, table

R = F.round
_P = "(SELECT p_partkey, CAST(p_size AS DOUBLE) AS s, p_retailprice AS r FROM part)"


def _part(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.col("p_size").cast("double").alias("s"), F.col("p_retailprice").alias("r"))


@query("fn_math", f"SELECT p_partkey, CAST(floor(r / 7) AS BIGINT) AS fl, CAST(ceil(r / 7) AS BIGINT) AS ce, round(sqrt(s), 6) AS sq, round(cbrt(s), 6) AS cb, round(exp(s / 50), 6) AS ex, round(exp(s / 50) - 1, 6) AS em, round(ln(s), 6) AS l, round(ln(1 + s), 6) AS l1, round(log2(s), 6) AS l2, round(log10(s), 6) AS l10, round(pow(s, 1.5), 5) AS pw, abs(25 - s) AS ab, CAST(sign(25 - s) AS DOUBLE) AS sg, CAST(p_partkey % 7 AS BIGINT) AS md FROM {_P}")
def fn_math(spark, sf):
    return _part(spark, sf).select("p_partkey", F.floor(F.col("r") / 7).alias("fl"), F.ceil(F.col("r") / 7).alias("ce"), R(F.sqrt("s"), 6).alias("sq"), R(F.cbrt("s"), 6).alias("cb"), R(F.exp(F.col("s") / 50), 6).alias("ex"), R(F.expm1(F.col("s") / 50), 6).alias("em"), R(F.log("s"), 6).alias("l"), R(F.log1p("s"), 6).alias("l1"), R(F.log2("s"), 6).alias("l2"), R(F.log10("s"), 6).alias("l10"), R(F.pow("s", F.lit(1.5)), 5).alias("pw"), F.abs(25 - F.col("s")).alias("ab"), F.signum(25 - F.col("s")).alias("sg"), F.pmod("p_partkey", F.lit(7)).alias("md"))


@query("fn_trig", f"SELECT p_partkey, round(sin(s), 6) + 0 AS si, round(cos(s), 6) + 0 AS co, round(atan2(s, r), 6) AS at, round(sqrt(s * s + r * r), 6) AS hy, round(degrees(s), 5) AS de, round(radians(s), 6) AS ra, round(s * pi(), 6) AS pi_s FROM {_P}")
def fn_trig(spark, sf):
    return _part(spark, sf).select("p_partkey", (R(F.sin("s"), 6) + 0).alias("si"), (R(F.cos("s"), 6) + 0).alias("co"), R(F.atan2("s", "r"), 6).alias("at"), R(F.hypot("s", "r"), 6).alias("hy"), R(F.degrees("s"), 5).alias("de"), R(F.radians("s"), 6).alias("ra"), R(F.col("s") * F.pi(), 6).alias("pi_s"))


@query("fn_bits", "SELECT p_partkey, p_partkey << 3 AS sl, p_partkey >> 2 AS sr, p_partkey & 29 AS an, p_partkey | 32 AS o, xor(p_partkey, 21) AS x, CAST(bit_count(p_partkey) AS INTEGER) AS bc, printf('%X', p_partkey) AS hx FROM part")
def fn_bits(spark, sf):
    k = F.col("p_partkey")
    return table(spark, sf, "part").select("p_partkey", F.shiftleft(k, 3).alias("sl"), F.shiftright(k, 2).alias("sr"), k.bitwiseAND(F.lit(29)).alias("an"), k.bitwiseOR(F.lit(32)).alias("o"), k.bitwiseXOR(F.lit(21)).alias("x"), F.bit_count(k).alias("bc"), F.hex(k).alias("hx"))


@query("fn_hash", "SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS s, CAST(concat('0x', substr(md5(p_name), 1, 13)) AS BIGINT) AS digits FROM part")
def fn_hash(spark, sf):
    m = F.md5(F.col("p_name").cast("binary"))
    return table(spark, sf, "part").select("p_partkey", m.alias("m"), F.sha2(F.col("p_name").cast("binary"), 256).alias("s"), F.conv(F.substring(m, 1, 13), 16, 10).cast("long").alias("digits"))


@query("fn_hash_native")
def fn_hash_native(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.xxhash64("p_name").alias("xx"), F.crc32(F.col("p_name").cast("binary")).alias("crc"))


@query("fn_width_bucket", "SELECT o_orderkey, CAST(CASE WHEN o_totalprice < 0 THEN 0 WHEN o_totalprice >= 500000 THEN 16 ELSE floor(o_totalprice / 500000 * 15) + 1 END AS BIGINT) AS slot, greatest(o_custkey, o_orderkey) AS hi, least(o_custkey, o_orderkey) AS lo FROM orders")
def fn_width_bucket(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", F.width_bucket("o_totalprice", F.lit(0.0), F.lit(500000.0), F.lit(15)).alias("slot"), F.greatest("o_custkey", "o_orderkey").alias("hi"), F.least("o_custkey", "o_orderkey").alias("lo"))


@query("fn_cast", "SELECT event_id, CAST(floor(value) AS INTEGER) AS i, TRY_CAST(event_type AS INTEGER) AS none, CAST(event_id AS VARCHAR) AS t, CAST(CAST(value AS DECIMAL(12, 1)) AS VARCHAR) AS dec FROM events")
def fn_cast(spark, sf):
    return table(spark, sf, "events").select("event_id", F.col("value").cast("int").alias("i"), F.col("event_type").try_cast("int").alias("none"), F.col("event_id").cast("string").alias("t"), F.col("value").cast("decimal(12,1)").cast("string").alias("dec"))


@query("fn_date", "SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(extract(year FROM o_orderdate) AS INTEGER) AS y, CAST(extract(month FROM o_orderdate) AS INTEGER) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start, strftime(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH, '%Y-%m-%d') AS later, strftime(make_date(CAST(extract(year FROM o_orderdate) AS INTEGER), 1, 1), '%Y-%m-%d') AS new_year FROM orders")
def fn_date(spark, sf):
    d = F.to_date("o_orderdate")
    text = lambda c: F.date_format(c, "yyyy-MM-dd")
    return table(spark, sf, "orders").select("o_orderkey", F.datediff(d, F.lit("1995-01-01").cast("date")).alias("days"), F.year(d).alias("y"), F.month(d).alias("m"), text(F.trunc(d, "month")).alias("month_start"), text(F.add_months(d, 2)).alias("later"), text(F.make_date(F.year(d), F.lit(1), F.lit(1))).alias("new_year"))


@query("fn_string", "SELECT p_partkey, length(p_name) AS n, substr(p_name, 1, 3) AS head, split_part(p_type, ' ', 1) AS kind, lpad(CAST(p_size AS VARCHAR), 4, '0') AS pad, regexp_extract(p_name, '([0-9]+)', 1) AS digits, regexp_replace(p_brand, '[^0-9]', '', 'g') AS brand_no, lower(p_brand) AS low, concat_ws('/', p_brand, p_type) AS joined, translate(p_brand, '#', '_') AS tr, CAST(levenshtein(p_name, p_type) AS INTEGER) AS lev FROM part")
def fn_string(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.length("p_name").cast("long").alias("n"), F.substring("p_name", 1, 3).alias("head"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("kind"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("pad"), F.regexp_extract("p_name", "([0-9]+)", 1).alias("digits"), F.regexp_replace("p_brand", "[^0-9]", "").alias("brand_no"), F.lower("p_brand").alias("low"), F.concat_ws("/", "p_brand", "p_type").alias("joined"), F.translate("p_brand", "#", "_").alias("tr"), F.levenshtein("p_name", "p_type").alias("lev"))


@query("fn_array", "SELECT vec_id, CAST(len(list_filter(v, lambda x: x > 0)) AS INTEGER) AS positive, list_contains(list_transform(v, lambda x: x > 0.3), true) AS any_high, round(list_sum(v), 5) + 0 AS total, round(list_max(v), 6) AS top, CAST(list_position(v, list_max(v)) AS BIGINT) AS at, round(list_sum(v[2:4]), 6) + 0 AS part, CAST(len(list_distinct(list_transform(v, lambda x: round(x, 1)))) AS INTEGER) AS steps FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)")
def fn_array(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    total = lambda c: R(F.aggregate(c, F.lit(0.0), lambda a, x: a + x), 5)
    top = F.array_max("v")
    return e.select("vec_id", F.size(F.filter("v", lambda x: x > 0)).alias("positive"), F.exists("v", lambda x: x > 0.3).alias("any_high"), (total(F.col("v")) + 0).alias("total"), R(top, 6).alias("top"), F.array_position("v", top).alias("at"), (R(F.aggregate(F.slice("v", 2, 3), F.lit(0.0), lambda a, x: a + x), 6) + 0).alias("part"), F.size(F.array_distinct(F.transform("v", lambda x: R(x, 1) + 0))).alias("steps"))


@query("fn_array_sets", "SELECT p_partkey, array_to_string(list_sort(list_distinct(list_concat(a, b))), ',') AS u, array_to_string(list_sort(list_intersect(a, b)), ',') AS i, array_to_string(list_sort(list_filter(a, lambda x: NOT list_contains(b, x))), ',') AS e, array_to_string(list_concat(a, b), ',') AS flat FROM (SELECT p_partkey, range(p_size % 7) AS a, range(3, 3 + p_size % 4) AS b FROM part)")
def fn_array_sets(spark, sf):
    span = lambda lo, n: F.when(n > 0, F.sequence(F.lit(lo).cast("long"), lo + n - 1)).otherwise(F.array().cast("array<bigint>"))
    p = table(spark, sf, "part").select("p_partkey", span(0, (F.col("p_size") % 7).cast("long")).alias("a"), span(3, (F.col("p_size") % 4).cast("long")).alias("b"))
    text = lambda c: F.array_join(F.sort_array(c), ",")
    return p.select("p_partkey", text(F.array_union("a", "b")).alias("u"), text(F.array_intersect("a", "b")).alias("i"), text(F.array_except("a", "b")).alias("e"), F.array_join(F.flatten(F.array("a", "b")), ",").alias("flat"))


@query("fn_array_explode", "SELECT p_partkey, CAST(unnest(range(p_size % 5)) AS BIGINT) AS pos, CAST(unnest(range(p_size % 5)) * 10 AS BIGINT) AS v FROM part")
def fn_array_explode(spark, sf):
    n = (F.col("p_size") % 5).cast("long")
    a = F.when(n > 0, F.transform(F.sequence(F.lit(0).cast("long"), n - 1), lambda k: k * 10)).otherwise(F.array().cast("array<bigint>"))
    return table(spark, sf, "part").select("p_partkey", F.posexplode(a).alias("pos", "v")).select("p_partkey", F.col("pos").cast("long").alias("pos"), "v")


@query("fn_array_norms", f"SELECT vec_id, round(sqrt(list_sum(list_transform(v, lambda x: x * x))), 6) AS norm, round(list_sum(list_transform(v, lambda x: x * x * {num(0.5)})), 6) AS half FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)")
def fn_array_norms(spark, sf):
    from veilgrid.functions.columns import dot, hadamard

    e = table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    half = F.transform("v", lambda x: x * 0.5)
    return e.select("vec_id", R(F.sqrt(dot(F.col("v"), F.col("v"))), 6).alias("norm"), R(F.aggregate(hadamard(F.col("v"), half), F.lit(0.0), lambda a, x: a + x), 6).alias("half"))


@query("fn_map", "SELECT o_orderstatus, CAST(count(DISTINCT o_orderpriority) AS INTEGER) AS kinds, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent FROM orders GROUP BY o_orderstatus")
def fn_map(spark, sf):
    """A histogram as a map: built from entries, filtered and read by key."""
    counts = table(spark, sf, "orders").groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))
    m = counts.groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))
    urgent = F.map_values(F.map_filter(F.transform_values("m", lambda k, v: v + 0), lambda k, v: k.like("1%")))
    return m.select("o_orderstatus", F.size(F.map_keys("m")).alias("kinds"), F.coalesce(F.get(urgent, F.lit(0)), F.lit(0)).alias("urgent"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark, sf):
    parsed = F.from_json("props", "k bigint")
    return table(spark, sf, "events").select("event_id", F.coalesce(parsed["k"], F.get_json_object("props", "$.k").cast("long")).alias("k"))


@query("fn_struct", "SELECT p_partkey, p_size + 1 AS a, p_brand AS b FROM part")
def fn_struct(spark, sf):
    rows = table(spark, sf, "part").select("p_partkey", F.array(F.named_struct(F.lit("a"), F.col("p_size") + 1, F.lit("b"), F.col("p_brand"))).alias("rows"))
    return rows.select("p_partkey", F.inline("rows"))


@query("fn_null", "SELECT event_id, coalesce(v, 0) AS a, nullif(event_type, 'error') AS b, CASE WHEN v IS NOT NULL THEN 'set' ELSE 'none' END AS c FROM (SELECT event_id, event_type, CASE WHEN event_id % 3 > 0 THEN value END AS v FROM events)")
def fn_null(spark, sf):
    v = F.when(F.col("event_id") % 3 > 0, F.col("value"))
    return table(spark, sf, "events").select("event_id", F.coalesce(F.nanvl(v, F.lit(None).cast("double")), F.lit(0.0)).alias("a"), F.nullif(F.col("event_type"), F.lit("error")).alias("b"), F.nvl2(v, F.lit("set"), F.lit("none")).alias("c"))


@query("fn_distance", f"SELECT user_id, round(abs(x - 0.1) + abs(y), 6) AS d1, round(sqrt((x - 0.1) * (x - 0.1) + y * y), 6) AS d2, round(greatest(abs(x - 0.1), abs(y)), 6) AS d_max FROM (SELECT vec_id AS user_id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings)")
def fn_distance(spark, sf):
    from veilgrid.functions.columns import p_distance

    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("user_id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    d = lambda p: R(p_distance([F.col("x"), F.col("y")], [F.lit(0.1), F.lit(0.0)], p), 6)
    return e.select("user_id", d(1).alias("d1"), d(2).alias("d2"), d(math.inf).alias("d_max"))
