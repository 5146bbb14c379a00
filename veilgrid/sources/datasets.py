"""Point sets on the given tables: (user_id, x, y, part), their domains, and the SQL of the same rows.

The first five stand for skewed city events, large taxi pick-ups (two volumes), a road-like correlation and
natural embeddings; the last three are generated from hash uniforms of order keys by the usual transforms.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec
from veilgrid.noise import hash_uniform
from veilgrid.registry import table


@dataclass(frozen=True)
class PointSet:
    read: Callable[[SparkSession, str], DataFrame]
    sql: str
    domain: tuple[float, float, float, float]  # x0, y0, width, height

    def grid(self, d: int) -> GridSpec:
        return GridSpec(*self.domain, d)


def uniform_sql(user: str, draw: int | str, seed: int = 42) -> str:
    return f"(CAST(CAST(concat('0x', substr(md5('{seed}:' || CAST({user} AS VARCHAR) || ':' || CAST({draw} AS VARCHAR)), 1, 13)) AS BIGINT) AS DOUBLE) / CAST(4503599627370496 AS DOUBLE))"


def days_since(ts: Column, start: str) -> Column:
    """Days with fraction since a date, by fields, so that no session time zone enters."""
    seconds = F.hour(ts) * 3600 + F.minute(ts) * 60 + F.date_part(F.lit("SECOND"), ts).cast("double")
    return F.datediff(F.to_date(ts), F.lit(start).cast("date")) + seconds / 86400


def event_points(spark: SparkSession, sf: str, *extra: str) -> DataFrame:
    """(event_id, x, y, extra...): days since the start and value of every event."""
    return table(spark, sf, "events").select("event_id", days_since(F.col("ts"), "2024-01-01").alias("x"), F.col("value").alias("y"), *extra)


def _events(spark, sf):
    part = F.when((F.col("x") < 10) & (F.col("y") < 60), "A").when((F.col("x") >= 10) & (F.col("x") < 20) & (F.col("y") < 60), "B").when((F.col("x") >= 20) & (F.col("y") >= 60) & (F.col("y") < 120), "C").otherwise("rest")
    return event_points(spark, sf).withColumnRenamed("event_id", "user_id").withColumn("part", part)


_EVENTS_SQL = """SELECT user_id, x, y, CASE WHEN x < 10 AND y < 60 THEN 'A' WHEN x >= 10 AND x < 20 AND y < 60 THEN 'B' WHEN x >= 20 AND y >= 60 AND y < 120 THEN 'C' ELSE 'rest' END AS part
FROM (SELECT event_id AS user_id, CAST(epoch_us(ts) - 1704067200000000 AS DOUBLE) / 86400000000 AS x, value AS y FROM events)"""

#: Squares (in the scaled domain) of the sets that are cut into three parts: (x0, y0, width, height).
SQUARE_PARTS = {
    "crime_like": {"A": (0.0, 0.0, 10.0, 60.0), "B": (10.0, 0.0, 10.0, 60.0), "C": (20.0, 60.0, 10.0, 60.0)},
    "taxi_like": {"A": (0.0, 0.0, 250000.0, 1205.0), "B": (250000.0, 0.0, 250000.0, 1205.0), "C": (125000.0, 1205.0, 250000.0, 1205.0)},
    "taxi_big": {"A": (0.0, 0.0, 52500.0, 1255.0), "B": (52500.0, 0.0, 52500.0, 1255.0), "C": (26250.0, 1255.0, 52500.0, 1255.0)},
}


def _orders(spark, sf):
    return table(spark, sf, "orders").select(F.col("o_orderkey").alias("user_id"), F.col("o_totalprice").alias("x"), F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("double").alias("y"), F.col("o_orderstatus").alias("part"))


_ORDERS_SQL = "SELECT o_orderkey AS user_id, o_totalprice AS x, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS y, o_orderstatus AS part FROM orders"


def _lineitem(spark, sf):
    key = F.concat_ws("-", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    return table(spark, sf, "lineitem").select(key.alias("user_id"), F.col("l_extendedprice").alias("x"), F.datediff(F.to_date("l_shipdate"), F.lit("1995-01-01").cast("date")).cast("double").alias("y"), F.col("l_returnflag").alias("part"))


_LINEITEM_SQL = "SELECT concat_ws('-', l_orderkey, l_partkey, l_suppkey, l_linenumber) AS user_id, l_extendedprice AS x, CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE) AS y, l_returnflag AS part FROM lineitem"


def _documents(spark, sf):
    words = F.length("text") - F.length(F.replace(F.col("text"), F.lit(" "), F.lit(""))) + 1
    return table(spark, sf, "documents").select(F.col("doc_id").alias("user_id"), F.log(F.col("n_chars").cast("double")).alias("x"), F.log(words.cast("double")).alias("y"), F.col("lang").alias("part")).where(F.col("x").isNotNull() & F.col("y").isNotNull())


_DOCUMENTS_SQL = "SELECT doc_id AS user_id, ln(CAST(n_chars AS DOUBLE)) AS x, ln(CAST(length(text) - length(replace(text, ' ', '')) + 1 AS DOUBLE)) AS y, lang AS part FROM documents WHERE n_chars > 0 AND text IS NOT NULL"


def _embeddings(spark, sf, shift=0.0):
    e = F.col("embedding")
    move = (F.col("label") % 3) * shift
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("user_id"), (e[0].cast("double") + move).alias("x"), (e[1].cast("double") + move).alias("y"), F.col("label").cast("string").alias("part"))


def _embeddings_sql(shift):
    return f"SELECT vec_id AS user_id, CAST(embedding[1] AS DOUBLE) + (label % 3) * CAST({shift} AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) + (label % 3) * CAST({shift} AS DOUBLE) AS y, CAST(label AS VARCHAR) AS part FROM embeddings"


def _generated(spark, sf, draws):
    keys = table(spark, sf, "orders").select(F.col("o_orderkey").alias("k"), F.explode(F.array(*[F.lit(i) for i in range(draws)])).alias("draw"))
    return keys.select("k", "draw", hash_uniform(F.col("k"), F.col("draw") * 2 + 10).alias("u"), hash_uniform(F.col("k"), F.col("draw") * 2 + 11).alias("v")).withColumn("user_id", F.col("k") * draws + F.col("draw"))


def _generated_sql(draws):
    return f"SELECT k, draw, {uniform_sql('k', 'draw * 2 + 10')} AS u, {uniform_sql('k', 'draw * 2 + 11')} AS v, k * {draws} + draw AS user_id FROM (SELECT o_orderkey AS k, CAST(unnest(range({draws})) AS INTEGER) AS draw FROM orders)"


def box_muller(u: Column, v: Column) -> tuple[Column, Column]:
    r = F.sqrt(-2 * F.log(1 - u))
    return r * F.cos(2 * math.pi * v), r * F.sin(2 * math.pi * v)


def _normal(spark, sf):
    a, b = box_muller(F.col("u"), F.col("v"))
    return _generated(spark, sf, 2).select("user_id", a.alias("x"), (0.5 * a + math.sqrt(0.75) * b).alias("y"), F.lit("all").alias("part"))


_GAUSS = "sqrt(-2 * ln(1 - u)) * cos(2 * pi() * v)", "sqrt(-2 * ln(1 - u)) * sin(2 * pi() * v)"
_NORMAL_SQL = f"SELECT user_id, a AS x, 0.5 * a + sqrt(CAST(0.75 AS DOUBLE)) * b AS y, 'all' AS part FROM (SELECT user_id, {_GAUSS[0]} AS a, {_GAUSS[1]} AS b FROM ({_generated_sql(2)}))"


def _zipf(spark, sf):
    return _generated(spark, sf, 1).select("user_id", (F.pow(F.lit(2.0), "u") - 1).alias("x"), (F.pow(F.lit(2.0), "v") - 1).alias("y"), F.lit("all").alias("part"))


_ZIPF_SQL = f"SELECT user_id, pow(2.0, u) - 1 AS x, pow(2.0, v) - 1 AS y, 'all' AS part FROM ({_generated_sql(1)})"

#: Correlations of the three groups.
GROUP_RHO = (0.5, 0.0, -0.2)


def _mnormal(spark, sf, spread=1.0):
    a, b = box_muller(F.col("u"), F.col("v"))
    group = (F.col("k") % 3).cast("int")
    rho = F.when(group == 0, GROUP_RHO[0]).when(group == 1, GROUP_RHO[1]).otherwise(GROUP_RHO[2])
    return _generated(spark, sf, 2).select("user_id", (a + group * spread).alias("x"), (rho * a + F.sqrt(1 - rho * rho) * b + group * spread).alias("y"), F.lit("all").alias("part"))


_MNORMAL_SQL = f"""SELECT user_id, a + g AS x, rho * a + sqrt(1 - rho * rho) * b + g AS y, 'all' AS part FROM (SELECT user_id, k % 3 AS g, CAST(CASE k % 3 WHEN 0 THEN 0.5 WHEN 1 THEN 0 ELSE -0.2 END AS DOUBLE) AS rho, {_GAUSS[0]} AS a, {_GAUSS[1]} AS b FROM ({_generated_sql(2)}))"""

POINT_SETS = {
    "crime_like": PointSet(_events, _EVENTS_SQL, (0.0, 0.0, 30.0, 300.0)),
    "taxi_like": PointSet(_orders, _ORDERS_SQL, (0.0, 0.0, 500000.0, 2410.0)),
    "taxi_big": PointSet(_lineitem, _LINEITEM_SQL, (0.0, 0.0, 105000.0, 2510.0)),
    "road_like": PointSet(_documents, _DOCUMENTS_SQL, (0.0, 0.0, 12.0, 10.0)),
    "normal_nat": PointSet(_embeddings, _embeddings_sql(0.0), (-0.5, -0.5, 1.0, 1.0)),
    "mnormal_nat": PointSet(lambda s, d: _embeddings(s, d, 0.4), _embeddings_sql(0.4), (-0.5, -0.5, 1.8, 1.8)),
    "normal_gen": PointSet(_normal, _NORMAL_SQL, (-5.0, -5.0, 10.0, 10.0)),
    "szipf_gen": PointSet(_zipf, _ZIPF_SQL, (0.0, 0.0, 1.0, 1.0)),
    "mnormal_gen": PointSet(_mnormal, _MNORMAL_SQL, (-5.0, -5.0, 12.0, 12.0)),
}
