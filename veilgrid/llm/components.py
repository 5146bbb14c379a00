"""Connected components of a distributed edge table by alternating star contractions.

Every round points each vertex's larger neighbours at its smallest neighbour, then its smaller ones; the
edge table turns into stars whose centre is the component's smallest vertex. All state is in DataFrames that
are checkpointed each round, minima are combined before the shuffle, and the few vertices that have a large share of
all edges are joined by broadcast, so that no task gets a hub's edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.llm.common import join_with_hubs, materialise


def connected_components(edges: DataFrame, max_rounds: int = 60, most: int | None = None) -> DataFrame:
    """edges(a, b) -> (node, root): root is the smallest node of the component; nodes without an edge are absent. ``most`` bounds the edges, if known.

    Null ends and self-loops are ignored, repeated edges count once, an empty table gives an empty result.
    """
    stars = materialise(
        edges.where(F.col("a") != F.col("b"))
        .select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        .distinct(),
        most,
    )
    state = _state(stars)
    for _ in range(max_rounds):
        if not state[0]:
            break
        stars = materialise(_small_star(_large_star(stars, state[0]), state[0]), state[0])  # a round makes no more edges than it got
        state, before = _state(stars), state
        if state == before:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = stars.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return stars.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)


def _state(stars: DataFrame) -> tuple:
    row = stars.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.count_distinct("v")).first()
    return tuple(row)


def _large_star(edges: DataFrame, rows: int) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = materialise(both.groupBy("u").agg(F.least(F.first("u"), F.min("v")).alias("m"), F.count("*").alias("n")), 2 * rows)
    larger = both.where(F.col("v") > F.col("u"))
    return join_with_hubs(larger, least, "u", "n").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame, rows: int) -> DataFrame:
    edges = materialise(edges, rows)
    least = materialise(edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")), rows)
    moved = join_with_hubs(edges, least, "u", "n").where(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct()
