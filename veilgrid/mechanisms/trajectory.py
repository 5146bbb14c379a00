"""Stand-ins for trajectory comparators: two public designs, since the compared methods' descriptions are not at hand.

'markov': first cells and transitions are reported by a categorical oracle with the budget split between them; a chain built from the
estimates is run forward and its visits are the histogram. 'pivot': a few points of each user are perturbed by the exponential mechanism
with an even share of the budget each and inverted. Either way a user spends one budget for the whole trajectory.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec, assign_cells
from veilgrid.em import clip_normalise
from veilgrid.estimate import to_histogram
from veilgrid.mechanisms.categorical import CategoricalOracle
from veilgrid.mechanisms.subset import SubsetExponentialMechanism
from veilgrid.noise import hash_uniform
from veilgrid.sources.datasets import POINT_SETS, event_points


def trajectories(spark, sf_dir: str, d: int) -> DataFrame:
    """(user_id, event_id, seq, cx, cy, cell, before): events of each user by time, with the cell before."""
    points = event_points(spark, sf_dir, "user_id", "ts")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    cell = (F.col("cy") * d + F.col("cx")).cast("int")
    cells = assign_cells(points, POINT_SETS["crime_like"].grid(d))
    return cells.select("user_id", "event_id", F.row_number().over(order).alias("seq"), "cx", "cy", cell.alias("cell"), F.lag(cell).over(order).alias("before"))


def chosen_points(paths: DataFrame, most: int, seed: int = 42) -> DataFrame:
    """Up to ``most`` points of each user, by a hash of the point."""
    order = Window.partitionBy("user_id").orderBy(hash_uniform(F.col("event_id"), 7, seed), "event_id")
    return paths.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= most)


def transitions(paths: DataFrame) -> DataFrame:
    return paths.where(F.col("before").isNotNull()).groupBy("before", "cell").agg(F.count("*").alias("n"))


def markov_estimate(paths: DataFrame, grid: GridSpec, eps: float, mode: str = "secure", seed: int | None = None, unsafe_deterministic: bool = False) -> DataFrame:
    """One first cell and one uniformly chosen transition per user, half the budget each; the chain's visits over the mean length."""
    n, d = grid.n, grid.d
    options = {"mode": mode, "seed": seed, "unsafe_deterministic": unsafe_deterministic}
    users = paths.groupBy("user_id").agg(F.count("*").alias("length"), F.min_by("cell", "seq").alias("first"), F.min_by(F.struct("before", "cell"), F.when(F.col("before").isNotNull(), F.xxhash64("event_id"))).alias("step"))
    start = CategoricalOracle("oue", eps / 2, grid)
    starts = start.support(start.report(users.select("user_id", (F.col("first") % d).alias("cx"), F.floor(F.col("first") / d).cast("int").alias("cy")), **options))
    pair_grid = GridSpec(0.0, 0.0, 1.0, 1.0, n)
    move = CategoricalOracle("olh", eps / 2, pair_grid)
    steps = users.where(F.col("step").isNotNull()).select("user_id", F.col("step.cell").alias("cx"), F.col("step.before").alias("cy"))
    moves = move.support(move.report(steps, **options))
    total, mean_length, movers = users.agg(F.count("*"), F.avg("length"), F.count("step")).first()
    p0 = np.zeros(n)
    for r in starts.collect():
        p0[r.cell] = r.n
    chain = np.zeros(n * n)
    for r in moves.collect():
        chain[r.cell] = r.n
    p0 = clip_normalise((p0 - total * start.q) / (start.p - start.q))
    chain = np.maximum((chain - movers * move.q) / (move.p - move.q), 0).reshape(n, n)
    chain = np.where(chain.sum(axis=1, keepdims=True) > 0, chain / np.maximum(chain.sum(axis=1, keepdims=True), 1e-12), p0[None])
    visits, at = np.zeros(n), p0
    for _ in range(max(1, round(mean_length))):
        visits += at
        at = at @ chain
    return to_histogram(paths.sparkSession, visits / visits.sum(), d)


def pivot_estimate(paths: DataFrame, grid: GridSpec, eps: float, points: int = 4, max_iter: int = 500, tol: float = 1e-9, mode: str = "secure", seed: int | None = None, unsafe_deterministic: bool = False) -> DataFrame:
    """``points`` points a user by the exponential mechanism, each at that share of eps per unit of distance, then EM over the cells."""
    mech = SubsetExponentialMechanism(eps / points, grid, 1)
    chosen = chosen_points(paths, points, 42 if seed is None else seed)
    counts = mech.count(mech.report(chosen, mode, "event_id", seed, unsafe_deterministic))
    return to_histogram(paths.sparkSession, mech.estimate(counts, max_iter, tol).mass, grid.d)
