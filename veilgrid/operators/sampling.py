"""Draws: from arbitrary weights, and by areas as the response procedure describes them."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilgrid.mechanisms.area import DiskMechanism


def alias_table(weights: list[float]) -> tuple[list[float], list[int]]:
    """(keep, other) per place: a place is kept with probability keep, else its other is taken. Any draw then costs one look."""
    n = len(weights)
    scaled = [w * n / math.fsum(weights) for w in weights]
    keep, other = [1.0] * n, list(range(n))
    small, large = [k for k, w in enumerate(scaled) if w < 1], [k for k, w in enumerate(scaled) if w >= 1]
    while small and large:
        s, big = small.pop(), large[-1]
        keep[s], other[s] = scaled[s], big
        scaled[big] -= 1 - scaled[s]
        if scaled[big] < 1:
            small.append(large.pop())
    return keep, other


def draw_from(weights: list[float], u: Column) -> Column:
    """A place drawn in proportion to the weights from one uniform, by array lookups in generated code."""
    if not weights or min(weights) < 0 or sum(weights) <= 0:
        raise ValueError("weights must be non-negative with a positive sum")
    keep, other = alias_table(weights)
    t = u * F.lit(float(len(weights)))
    at = F.least(F.floor(t), F.lit(len(weights) - 1)).cast("int")
    kept = F.get(F.array(*[F.lit(float(k)) for k in keep]), at)
    return F.when(t - at < kept, at).otherwise(F.get(F.array(*[F.lit(o) for o in other]), at)).cast("int")


def draw_large(weights: np.ndarray, u: Column) -> Column:
    """The same for tables too long for literals: cumulative weights go with a vectorised function that searches them."""
    ends = np.cumsum(weights)

    @F.pandas_udf("int")
    def draw(u):
        return u.__class__(np.minimum(np.searchsorted(ends, u.to_numpy() * ends[-1], side="right"), len(ends) - 1).astype(np.int32))

    return draw(u)


def report_by_areas(cells: DataFrame, mech: DiskMechanism, u: Column, v: Column) -> DataFrame:
    """Adds ox, oy by choosing an area first (low, border, high, by area times weight) and then a cell in it.

    The law is the mechanism's; the low area's cell is found by rank among the output cells outside the stencil, which takes one look at
    each stencil cell, so the mixture form (AreaMechanism.report_with) is preferred.
    """
    gain, d = math.exp(mech.eps), mech.grid.d
    pure = [c for c in mech.stencil.cells if c.kind == "pure"]
    border = [c for c in mech.stencil.cells if c.kind == "border"]
    low = mech.outputs - len(pure) - len(border)
    border_weights = [(1 - c.share) + c.share * gain for c in border]
    total = low + math.fsum(border_weights) + len(pure) * gain
    t = u * F.lit(total)
    spans = mech.stencil.row_spans(d)
    reach, starts, count = -spans[0][0], [], 0
    for _, lo, hi in spans:
        starts.append(count - lo)  # place of (ox, oy) in row order is starts[row] + ox
        count += hi - lo + 1
    row_start = F.array(*[F.lit(s) for s in starts])
    ordered = sorted(mech.stencil.cells, key=lambda c: (c.dy, c.dx))
    own = F.array(*[F.struct(F.lit(c.dx).alias("dx"), F.lit(c.dy).alias("dy")) for c in ordered])
    rank = F.least(F.floor(v * F.lit(float(low))), F.lit(max(low - 1, 0))).cast("int")
    place = F.aggregate(own, rank, lambda at, c: F.when(F.get(row_start, F.col("cy") + c["dy"] + reach) + F.col("cx") + c["dx"] <= at, at + 1).otherwise(at))
    out = F.array(*[F.struct(F.lit(x).alias("x"), F.lit(y).alias("y")) for x, y in mech.output_list])

    def cell(group, at):
        moves = F.array(*[F.struct(F.lit(c.dx).alias("x"), F.lit(c.dy).alias("y")) for c in group])
        return F.struct((F.col("cx") + F.get(moves, at)["x"]).alias("x"), (F.col("cy") + F.get(moves, at)["y"]).alias("y"))

    low_cell = F.get(out, place)
    high_cell = cell(pure, F.least(F.floor(v * F.lit(float(len(pure)))), F.lit(len(pure) - 1)).cast("int"))
    pick = F.when(t < low, low_cell)
    if border:
        pick = pick.when(t < total - len(pure) * gain, cell(border, draw_from(border_weights, v)))
    return cells.withColumn("_o", pick.otherwise(high_cell)).withColumns({"ox": F.col("_o.x"), "oy": F.col("_o.y")}).drop("_o")
