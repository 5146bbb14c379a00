"""Names for SQL: ldp_cell, ldp_radius as SQL functions and ldp_grid, ldp_stencil as table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from veilgrid.geometry import disk_stencil


def register(spark: SparkSession) -> None:
    """Temporary functions of the session; the scalar ones are SQL bodies, so they are inlined and stay in generated code."""

    class Grid:
        def eval(self, d: int):
            for cy in range(d):
                for cx in range(d):
                    yield cx, cy

    class Stencil:
        def eval(self, b: int):
            for c in disk_stencil(b).cells:
                yield c.dx, c.dy, c.kind, c.share

    spark.udtf.register("ldp_grid", udtf(Grid, returnType="cx int, cy int"))
    spark.udtf.register("ldp_stencil", udtf(Stencil, returnType="dx int, dy int, kind string, s double"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ldp_cell(x DOUBLE, x0 DOUBLE, side DOUBLE, d INT) RETURNS INT RETURN CAST(least(floor((x - x0) * d / side), d - 1) AS INT)")
    m1, m2 = "(exp(eps) - 1 - eps)", "(1 - exp(eps) + eps * exp(eps))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION ldp_radius(eps DOUBLE, side DOUBLE) RETURNS DOUBLE RETURN (2 * {m2} + sqrt(4 * {m2} * {m2} + pi() * exp(eps) * {m1} * {m2})) / (pi() * exp(eps) * {m1}) * side")
