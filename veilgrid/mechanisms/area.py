"""Area mechanisms: a report's probability depends on its displacement from the true cell only.

Every member is a background weight one over the output cells plus excess weights on a stencil. A report is
therefore drawn from a mixture: uniform over the output, or a displacement by its excess. One uniform number is enough, and
neither the output domain nor the channel is listed per user.
"""

from __future__ import annotations

import math
from functools import cached_property
from itertools import groupby

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec
from veilgrid.geometry import Stencil, border_share, continuous_constants, disk_stencil, grid_radius, optimal_radius
from veilgrid.noise import uniform_columns

#: Output cells, and classes of equal weight, up to which reports are plain column expressions; beyond, a vectorised function searches arrays.
MAX_EXPRESSION_CELLS = 1_000
MAX_EXPRESSION_CLASSES = 256


class AreaMechanism:
    """weights: displacement -> weight relative to the background, each in [1, e^eps]; all others weigh one."""

    privacy_model = "ldp"

    def __init__(self, eps: float, grid: GridSpec, stencil: Stencil, weights: dict[tuple[int, int], float]):
        if eps < 0:
            raise ValueError("eps is negative")
        top = math.exp(eps)
        if any(w < 1 - 1e-12 or w > top * (1 + 1e-12) for w in weights.values()):
            raise ValueError("a weight lies outside [1, e^eps]: the mechanism would not be private")
        if {(c.dx, c.dy) for c in stencil.cells} != set(weights):
            raise ValueError("weights must be given for the stencil's displacements")
        self.eps, self.grid, self.stencil, self.weights = eps, grid, stencil, weights

    @cached_property
    def outputs(self) -> int:
        return self.stencil.output_count(self.grid.d)

    @cached_property
    def excess(self) -> list[tuple[int, int, float]]:
        """(dx, dy, weight - 1), heaviest first, then by row and column; displacements without excess are left out."""
        return sorted(((dx, dy, w - 1) for (dx, dy), w in self.weights.items() if w > 1), key=lambda x: (-x[2], x[1], x[0]))

    @cached_property
    def total_weight(self) -> float:
        return self.outputs + math.fsum(w for *_, w in self.excess)

    @property
    def q(self) -> float:
        """Probability of a background cell."""
        return 1 / self.total_weight

    @cached_property
    def output_list(self) -> list[tuple[int, int]]:
        return [(ox, oy) for oy, lo, hi in self.stencil.row_spans(self.grid.d) for ox in range(lo, hi + 1)]

    # ---- reporting ----

    def report(self, cells: DataFrame, mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
        """cells(cx, cy, ...) -> (keep..., ox, oy). In deployment this runs at the user's side and only its result leaves.

        Persist the result before using it twice: drawing again is a second report by the same user, which costs privacy again.
        """
        drawn = uniform_columns(cells, ["_u"], mode, user, seed, unsafe_deterministic)
        return self.report_with(drawn, F.col("_u")).select(*keep, "ox", "oy")

    def report_with(self, df: DataFrame, u: Column) -> DataFrame:
        """Adds ox, oy from a uniform column."""
        classes = [(w, [(dx, dy) for dx, dy, _ in same]) for w, same in groupby(self.excess, key=lambda x: x[2])]
        if self.outputs > MAX_EXPRESSION_CELLS or len(classes) > MAX_EXPRESSION_CLASSES:
            return self._report_vectorised(df, u)
        t = u * F.lit(self.total_weight)
        out_x = F.array(*[F.lit(x) for x, _ in self.output_list])
        out_y = F.array(*[F.lit(y) for _, y in self.output_list])
        at = F.least(F.floor(t), F.lit(self.outputs - 1)).cast("int")
        ox, oy = F.get(out_x, at), F.get(out_y, at)
        x, y = F.when(t < self.outputs, ox), F.when(t < self.outputs, oy)
        done = float(self.outputs)
        for k, (w, moves) in enumerate(classes):
            index = F.least(F.floor((t - F.lit(done)) / F.lit(w)), F.lit(len(moves) - 1)).cast("int")
            dx, dy = (F.get(F.array(*[F.lit(m[a]) for m in moves]), F.greatest(index, F.lit(0))) for a in (0, 1))
            done += w * len(moves)
            last = k == len(classes) - 1
            x = x.otherwise(F.col("cx") + dx) if last else x.when(t < done, F.col("cx") + dx)
            y = y.otherwise(F.col("cy") + dy) if last else y.when(t < done, F.col("cy") + dy)
        if not classes:
            x, y = ox, oy
        return df.withColumns({"ox": x.cast("int"), "oy": y.cast("int")})

    def _report_vectorised(self, df: DataFrame, u: Column) -> DataFrame:
        spans = np.array(self.stencil.row_spans(self.grid.d), dtype=np.int64)
        row_ends = np.cumsum(spans[:, 2] - spans[:, 1] + 1)
        moves = np.array([(dx, dy) for dx, dy, _ in self.excess], dtype=np.int64).reshape(-1, 2)
        ends = np.cumsum([w for *_, w in self.excess])
        total, m = self.total_weight, self.outputs

        @F.pandas_udf("struct<ox:int,oy:int>")
        def draw(cx, cy, u):
            t = u.to_numpy() * total
            far = t < m
            row = np.searchsorted(row_ends, np.minimum(np.floor(t), m - 1), side="right").clip(0, len(spans) - 1)
            ox = spans[row, 1] + np.floor(t) - (row_ends[row] - (spans[row, 2] - spans[row, 1] + 1))
            oy = spans[row, 0]
            if len(moves):
                j = np.searchsorted(ends, t - m, side="right").clip(0, len(moves) - 1)
                ox, oy = np.where(far, ox, cx + moves[j, 0]), np.where(far, oy, cy + moves[j, 1])
            return u.to_frame("ox").assign(ox=ox.astype(np.int32), oy=oy.astype(np.int32))

        return df.withColumn("_r", draw("cx", "cy", u)).withColumns({"ox": F.col("_r.ox"), "oy": F.col("_r.oy")}).drop("_r")

    # ---- channel ----

    def excess_frame(self, spark: SparkSession) -> DataFrame:
        """(dx, dy, excess) with probabilities; its size depends on the radius alone."""
        return spark.createDataFrame([(dx, dy, w * self.q) for dx, dy, w in self.excess], "dx int, dy int, excess double")

    def channel(self, spark: SparkSession) -> DataFrame:
        """(cx, cy, ox, oy, prob) for all pairs; for small grids."""
        from veilgrid.domain import input_cells, output_cells

        pairs = input_cells(spark, self.grid).crossJoin(output_cells(spark, self.grid, self.stencil))
        moved = pairs.withColumns({"dx": F.col("ox") - F.col("cx"), "dy": F.col("oy") - F.col("cy")})
        return moved.join(F.broadcast(self.excess_frame(spark)), ["dx", "dy"], "left").select("cx", "cy", "ox", "oy", (F.lit(self.q) + F.coalesce("excess", F.lit(0.0))).alias("prob"))

    def channel_matrix(self) -> np.ndarray:
        """n x m probabilities; input cell (cx, cy) is row cy * d + cx, outputs are in the order of output_list."""
        d = self.grid.d
        index = {c: k for k, c in enumerate(self.output_list)}
        out = np.full((d * d, self.outputs), self.q)
        for dx, dy, w in self.excess:
            for cy in range(d):
                for cx in range(d):
                    out[cy * d + cx, index[cx + dx, cy + dy]] += w * self.q
        return out


class DiskMechanism(AreaMechanism):
    """Weight e^eps in the disk, one outside; crossed cells get a weight between by their high share (all low without shrinkage)."""

    def __init__(self, eps: float, grid: GridSpec, b_hat: int | None = None, shrink: bool = True, factor: float = 1.0, min_radius: int = 0):
        b = grid_radius(eps, grid.d, factor, min_radius) if b_hat is None else b_hat
        stencil = disk_stencil(b, shrink)
        gain = math.expm1(eps)
        super().__init__(eps, grid, stencil, {(c.dx, c.dy): 1 + c.share * gain for c in stencil.cells})
        self.b_hat, self.shrink = b, shrink

    @staticmethod
    def report_continuous(points: DataFrame, eps: float, b: float | None = None, mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False) -> DataFrame:
        """Points in the unit square -> (rx, ry) in the rounded square around it, without rejection.

        With the background's whole mass a place is drawn uniformly from the rounded square (square, four strips, four quarter disks); otherwise from
        the disk around the point.
        """
        b = optimal_radius(eps) if b is None else b
        _, q = continuous_constants("disk", b, eps)
        area = math.pi * b * b + 4 * b + 1
        df = uniform_columns(points, ["_u", "_v", "_w"], mode, user, seed, unsafe_deterministic)
        u, v, w = F.col("_u"), F.col("_v"), F.col("_w")
        background = q * area
        t = u / F.lit(background) * F.lit(area)
        side = F.floor((t - 1) / F.lit(b)).cast("int")
        along = (t - 1) / F.lit(b) - F.floor((t - 1) / F.lit(b))
        angle, radius = 2 * math.pi * v, F.lit(b) * F.sqrt(w)
        corner_x, corner_y = radius * F.cos(angle), radius * F.sin(angle)
        far_x = F.when(t < 1, v).when(side == 0, along).when(side == 1, along).when(side == 2, -F.lit(b) * v).when(side == 3, 1 + F.lit(b) * v).otherwise(corner_x + F.when(corner_x > 0, 1.0).otherwise(0.0))
        far_y = F.when(t < 1, w).when(side == 0, -F.lit(b) * v).when(side == 1, 1 + F.lit(b) * v).when(side == 2, along).when(side == 3, along).otherwise(corner_y + F.when(corner_y > 0, 1.0).otherwise(0.0))
        near_x, near_y = F.col("x") + radius * F.cos(angle), F.col("y") + radius * F.sin(angle)
        return df.withColumns({"rx": F.when(u < background, far_x).otherwise(near_x), "ry": F.when(u < background, far_y).otherwise(near_y)}).drop("_u", "_v", "_w")


class DecayMechanism(AreaMechanism):
    """Weight decays with the distance, from e^eps at the centre to one at the radius.

    profile 'rings': one weight per ring of width one, e^(eps (1 - (j-1)/b)) in ring j, crossed cells mix two rings' weights
    by their high share; 'center': the decay at the cell's centre.
    """

    def __init__(self, eps: float, grid: GridSpec, b_hat: int | None = None, profile: str = "rings", factor: float = 1.0, min_radius: int = 0):
        b = grid_radius(eps, grid.d, factor, min_radius) if b_hat is None else b_hat
        stencil = disk_stencil(b)
        if b == 0:
            weights = {(0, 0): math.exp(eps)}
        elif profile == "rings":
            weights = {(c.dx, c.dy): _ring_weight(c.dx, c.dy, b, eps) for c in stencil.cells}
        elif profile == "center":
            weights = {(c.dx, c.dy): max(1.0, math.exp(eps * (1 - math.hypot(c.dx, c.dy) / b))) for c in stencil.cells}
        else:
            raise ValueError("profile is rings or center")
        super().__init__(eps, grid, stencil, weights)
        self.b_hat, self.profile = b, profile

    @staticmethod
    def report_continuous(points: DataFrame, eps: float, b: float | None = None, mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False, steps: int = 4096) -> DataFrame:
        """As the disk's, with the excess radius drawn from a table of its cumulative distribution (``steps`` rows)."""
        b = optimal_radius(eps) if b is None else b
        _, q = continuous_constants("decay", b, eps)
        area = math.pi * b * b + 4 * b + 1
        background = q * area
        r = np.linspace(0, b, steps + 1)
        mass = np.concatenate([[0], np.cumsum(((np.exp(eps * (1 - r / b)) - 1) * r)[:-1] + ((np.exp(eps * (1 - r / b)) - 1) * r)[1:])])
        mass = mass / mass[-1] if mass[-1] else np.linspace(0, 1, steps + 1)
        df = uniform_columns(points, ["_u", "_v", "_w"], mode, user, seed, unsafe_deterministic)

        @F.pandas_udf("struct<rx:double,ry:double>")
        def draw(x, y, u, v, w):
            near_r = np.interp(w, mass, r)
            angle = 2 * np.pi * v.to_numpy()
            fx, fy = _rounded_square((u / background).to_numpy() * area, v.to_numpy(), w.to_numpy(), b)
            far = (u < background).to_numpy()
            rx = np.where(far, fx, x.to_numpy() + near_r * np.cos(angle))
            return x.to_frame("rx").assign(rx=rx, ry=np.where(far, fy, y.to_numpy() + near_r * np.sin(angle)))

        return df.withColumn("_r", draw("x", "y", "_u", "_v", "_w")).withColumns({"rx": F.col("_r.rx"), "ry": F.col("_r.ry")}).drop("_r", "_u", "_v", "_w")


def _rounded_square(t: np.ndarray, v: np.ndarray, w: np.ndarray, b: float) -> tuple[np.ndarray, np.ndarray]:
    side = np.floor((t - 1) / b)
    along = (t - 1) / b - side
    rx, ry = b * np.sqrt(w) * np.cos(2 * np.pi * v), b * np.sqrt(w) * np.sin(2 * np.pi * v)
    x = np.select([t < 1, side <= 1, side == 2, side == 3], [v, along, -b * v, 1 + b * v], rx + (rx > 0))
    y = np.select([t < 1, side == 0, side == 1, side <= 3], [w, -b * v, 1 + b * v, along], ry + (ry > 0))
    return x, y


def _ring_weight(dx: int, dy: int, b: int, eps: float) -> float:
    """Ring j holds centres with j - 1 < r <= j. A cell that the inner circle of its ring crosses mixes in the ring inside by the share."""
    r2 = dx * dx + dy * dy
    j = math.isqrt(r2 - 1) + 1 if r2 else 1
    weight = lambda k: max(1.0, math.exp(eps * (1 - (k - 1) / b)))
    inner = j - 1
    x, y = max(0, 2 * abs(dx) - 1), max(0, 2 * abs(dy) - 1)
    if inner and r2 and x * x + y * y < 4 * inner * inner:
        s = border_share(dx, dy, inner)
        return s * weight(inner) + (1 - s) * weight(j)
    return weight(j)
