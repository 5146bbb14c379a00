"""Per-axis baseline: a one-dimensional square wave on x and on y, combined afterwards."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec
from veilgrid.em import Fit, em
from veilgrid.noise import uniform_columns


def wave_radius(eps: float) -> float:
    """Radius that maximises the information bound of the one-dimensional wave over the unit interval."""
    if eps < 1e-6:
        return 0.5
    e = math.exp(eps)
    return (eps * e - e + 1) / (2 * e * (e - 1 - eps))


class SquareWave:
    """Reports cell j of d + 2b for input i with weight e^eps if |j - i| <= b and one otherwise."""

    def __init__(self, eps: float, d: int, b_hat: int | None = None):
        self.eps, self.d = eps, d
        self.b = math.floor(wave_radius(eps) * d) if b_hat is None else b_hat
        self.width = 2 * self.b + 1
        self.outputs = d + 2 * self.b
        self.q = 1 / (self.outputs + self.width * math.expm1(eps))

    def report(self, cell: Column, u: Column) -> Column:
        """Closed form: a uniform output with the background's mass, else a uniform neighbour."""
        t = u / F.lit(self.q)
        far = F.least(F.floor(t), F.lit(self.outputs - 1)) - self.b
        near = cell - self.b + F.least(F.floor((t - self.outputs) / F.lit(math.expm1(self.eps))), F.lit(self.width - 1))
        return F.when(t < self.outputs, far).otherwise(near).cast("int")

    def channel_matrix(self) -> np.ndarray:
        i, j = np.arange(self.d)[:, None], np.arange(self.outputs)[None] - self.b
        return np.where(np.abs(j - i) <= self.b, math.exp(self.eps) * self.q, self.q)


class AxisWaveMechanism:
    """budget 'split': both axes at eps/2; 'sample': one random axis at eps. merge 'outer': product of marginals; 'joint': EM on the pair channel."""

    privacy_model = "ldp"

    def __init__(self, eps: float, grid: GridSpec, budget: str = "split", merge: str = "outer", b_hat: int | None = None):
        if budget not in ("split", "sample") or merge not in ("outer", "joint") or (budget, merge) == ("sample", "joint"):
            raise ValueError("budget is split or sample, merge is outer or (with split) joint")
        self.eps, self.grid, self.budget, self.merge = eps, grid, budget, merge
        self.wave = SquareWave(eps / 2 if budget == "split" else eps, grid.d, b_hat)

    def report(self, cells: DataFrame, mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
        """(keep..., ox, oy); under 'sample' the axis that isn't reported is null."""
        df = uniform_columns(cells, ["_u", "_v"] + ["_w"] * (self.budget == "sample"), mode, user, seed, unsafe_deterministic)
        x, y = self.wave.report(F.col("cx"), F.col("_u")), self.wave.report(F.col("cy"), F.col("_v"))
        if self.budget == "sample":
            x, y = F.when(F.col("_w") < 0.5, x), F.when(F.col("_w") >= 0.5, y)
        return df.select(*keep, x.alias("ox"), y.alias("oy"))

    @staticmethod
    def count_axes(reports: DataFrame) -> DataFrame:
        """(axis, o, n) from one aggregate with grouping sets: two short lists whatever the number of reports."""
        sets = reports.groupingSets([["ox"], ["oy"]], "ox", "oy").agg(F.grouping("ox").alias("gx"), F.count("*").alias("n"))
        axis = F.when(F.col("gx") == 0, "x").otherwise("y")
        return sets.select(axis.alias("axis"), F.when(F.col("gx") == 0, F.col("ox")).otherwise(F.col("oy")).alias("o"), "n").where(F.col("o").isNotNull())

    def estimate(self, x_counts: np.ndarray, y_counts: np.ndarray, **options) -> np.ndarray:
        """Product of the two inverted marginals, as mass[cy * d + cx]."""
        channel = self.wave.channel_matrix()
        fx, fy = em(x_counts, channel, **options), em(y_counts, channel, **options)
        return np.outer(fy.mass, fx.mass).ravel()

    def estimate_joint(self, counts: np.ndarray, max_iter: int = 2000, tol: float = 1e-9) -> Fit:
        """counts[oy, ox]; the pair channel is applied as two small products."""
        from veilgrid.em import _iterate

        c, d = self.wave.channel_matrix(), self.grid.d
        shape = counts.shape
        return _iterate(counts.ravel().astype(float), d * d, lambda f: (c.T @ f.reshape(d, d) @ c).ravel(), lambda r: (c @ r.reshape(shape) @ c.T).ravel(), max_iter, tol)
