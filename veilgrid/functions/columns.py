"""Column expressions that users of the methods need."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def morton(x: str, y: str, bits: int) -> Column:
    """Interleaved bits of two cell numbers, x in the even places: rows sorted by it keep near cells near."""
    out = F.lit(0)
    for k in range(bits):
        for place, c in ((2 * k, x), (2 * k + 1, y)):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(F.col(c), k).bitwiseAND(F.lit(1)), place))
    return out


def p_distance(xs: list[Column], ys: list[Column], p: float) -> Column:
    """Minkowski distance of two points given by columns; p may be infinite."""
    gaps = [F.abs(x - y) for x, y in zip(xs, ys, strict=True)]
    if p == float("inf"):
        return F.greatest(*gaps) if len(gaps) > 1 else gaps[0]
    total = sum((F.pow(g, p) for g in gaps[1:]), F.pow(gaps[0], p))
    return F.pow(total, 1.0 / p)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def to_polar(x: str, y: str) -> tuple[Column, Column]:
    return F.hypot(x, y), F.atan2(y, x)


def from_polar(r: str, theta: str) -> tuple[Column, Column]:
    return F.col(r) * F.cos(theta), F.col(r) * F.sin(theta)
