"""Geometry of the disk on a grid: stencils, octants, areas, radius rules. Plain Python on the driver, O(b^2) or less."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column
from pyspark.sql import functions as F


# ---- continuous radius and information bound ---------------------------------------------------------------

def _m1_m2(eps: float) -> tuple[float, float]:
    """e^eps - 1 - eps and 1 - e^eps + eps e^eps; by series where the differences cancel."""
    if eps < 1e-2:
        m1 = sum(eps**k / math.factorial(k) for k in range(2, 9))
        m2 = sum(eps**k * (k - 1) / math.factorial(k) for k in range(2, 9))
        return m1, m2
    return math.expm1(eps) - eps, eps * math.exp(eps) - math.expm1(eps)


def optimal_radius(eps: float, side: float = 1.0) -> float:
    """The radius that maximises the information bound; its limits are (2 + sqrt(4 + pi)) / pi and 0 times the side."""
    if eps < 0:
        raise ValueError("eps is negative")
    if eps < 1e-12:
        return (2 + math.sqrt(4 + math.pi)) / math.pi * side
    m1, m2 = _m1_m2(eps)
    e = math.exp(eps)
    return (2 * m2 + math.sqrt(4 * m2 * m2 + math.pi * e * m1 * m2)) / (math.pi * e * m1) * side


def optimal_radius_col(eps: Column, side: Column | float = 1.0) -> Column:
    """The same rule as a column expression, for eps of at least 0.01."""
    e = F.exp(eps)
    m1, m2 = e - 1 - eps, 1 - e + eps * e
    return (2 * m2 + F.sqrt(4 * m2 * m2 + F.lit(math.pi) * e * m1 * m2)) / (F.lit(math.pi) * e * m1) * side


def info_bound_col(b: Column, eps: Column, side: Column) -> Column:
    """Upper bound of the mutual information of a point and its report, in bits."""
    disk, ring = F.lit(math.pi) * b * b, 4 * side * b + side * side
    high = disk * F.exp(eps)
    return F.log2((disk + ring) / (high + ring)) + high * eps * F.lit(math.log2(math.e)) / (high + ring)


def info_gradient_col(b: Column, eps: Column, side: Column) -> Column:
    """Derivative of the bound by b."""
    e = F.exp(eps)
    m1, m2 = e - 1 - eps, 1 - e + eps * e
    disk, ring = F.lit(math.pi) * b * b, 4 * side * b + side * side
    top = 2 * math.pi * side * b * (2 * b + side) * (-math.pi * e * m1 * b * b + 4 * side * m2 * b + side * side * m2)
    return top / ((disk + ring) * (disk * e + ring) * (disk * e + ring) * F.lit(math.log(2)))


def grid_radius(eps: float, d: int, factor: float = 1.0, min_radius: int = 0) -> int:
    """Radius in cells: the optimal radius times ``factor``, floored. ``min_radius`` 1 avoids the degenerate radius 0."""
    return max(min_radius, math.floor(optimal_radius(eps) * factor * d))


# ---- stencils -----------------------------------------------------------------------------------------------

@dataclass(frozen=True)
class StencilCell:
    dx: int
    dy: int
    kind: str  # pure or border
    share: float  # area share that counts as high


@dataclass(frozen=True)
class Stencil:
    """Displacements whose report probability may exceed the background, with relative weights of at least one."""

    b: int
    cells: tuple[StencilCell, ...]

    @cached_property
    def high_area(self) -> float:
        return math.fsum(c.share for c in self.cells)

    @cached_property
    def half_widths(self) -> tuple[int, ...]:
        """For each |dy| the largest dx of the stencil."""
        out = [0] * (max(abs(c.dy) for c in self.cells) + 1)
        for c in self.cells:
            out[abs(c.dy)] = max(out[abs(c.dy)], c.dx)
        return tuple(out)

    def row_spans(self, d: int) -> list[tuple[int, int, int]]:
        """Rows (oy, first ox, last ox) of the output domain over a d x d input."""
        reach = len(self.half_widths) - 1
        out = []
        for oy in range(-reach, d + reach):
            beyond = max(0, -oy, oy - (d - 1))
            w = self.half_widths[beyond]
            out.append((oy, -w, d - 1 + w))
        return out

    def output_count(self, d: int) -> int:
        return sum(hi - lo + 1 for _, lo, hi in self.row_spans(d))


def border_share(dx: int, dy: int, b: int) -> float:
    """Area share of a crossed cell whose centre is outside: a rectangle around the arc point toward the centre, kept within the cell."""
    x, y = max(abs(dx), abs(dy)), min(abs(dx), abs(dy))  # one order, so that mirrored cells get equal numbers
    r = math.sqrt(x * x + y * y)
    return min(1.0, max(0.0, 4 * (x * b / r - x + 0.5) * (y * b / r - y + 0.5))) if r else 1.0


def _crossed(dx: int, dy: int, b: int) -> bool:
    """Whether the cell's nearest corner or edge lies strictly inside the circle."""
    x, y = max(0, 2 * abs(dx) - 1), max(0, 2 * abs(dy) - 1)
    return x * x + y * y < 4 * b * b


def disk_stencil(b: int, shrink: bool = True) -> Stencil:
    """All cells that the disk of radius b around a cell's centre covers or crosses. Radius 0 is the cell alone."""
    if b < 0:
        raise ValueError("the radius is negative")
    if b == 0:
        return Stencil(0, (StencilCell(0, 0, "pure", 1.0),))
    cells = []
    for dy in range(-b - 1, b + 2):
        for dx in range(-b - 1, b + 2):
            if dx * dx + dy * dy <= b * b:
                cells.append(StencilCell(dx, dy, "pure", 1.0))
            elif _crossed(dx, dy, b):
                cells.append(StencilCell(dx, dy, "border", border_share(dx, dy, b) if shrink else 0.0))
    return Stencil(b, tuple(cells))


# ---- octant formulas, as cross-checks of the stencil --------------------------------------------------------

def octant_border(b: int) -> list[tuple[int, int]]:
    """Border cells strictly between the axis and the diagonal: rows from 1, one candidate each, kept if crossed and centred outside."""
    out = []
    for i in range(1, b + 1):
        rest = b * b - (i - 0.5) ** 2
        if rest <= 0:
            break
        x = math.ceil(math.sqrt(rest) - 0.5)
        if x > i and x * x + i * i > b * b:
            out.append((x, i))
    return out


def octant_pure_count(b: int) -> int:
    """Cells strictly between the axis and the diagonal whose centres are in the disk, by rows."""
    return sum(max(0, math.isqrt(b * b - i * i) - i) for i in range(1, b + 1))


def diagonal_cells(b: int) -> tuple[int, float]:
    """Whole pure cells on one diagonal ray besides the centre, and the high share of the next one."""
    whole = math.isqrt(b * b // 2)
    k = whole + 1
    return whole, border_share(k, k, b) if _crossed(k, k, b) else 0.0


def octant_high_area(b: int) -> float:
    """High area by symmetry: the centre, four axes, four diagonals and eight open octants."""
    if b == 0:
        return 1.0
    whole, next_share = diagonal_cells(b)
    return 1 + 4 * (b + whole + next_share) + 8 * (octant_pure_count(b) + math.fsum(border_share(x, y, b) for x, y in octant_border(b)))


def pure_low_area(d: int, b: int) -> int:
    """Output cells that one input cell's stencil doesn't touch."""
    return d * d + 4 * b * d - 4 * b - 1


@dataclass(frozen=True)
class GridConstants:
    outputs: int
    high: float
    low: float
    p: float
    q: float


def grid_constants(d: int, b: int, eps: float, shrink: bool = True) -> GridConstants:
    stencil = disk_stencil(b, shrink)
    m = stencil.output_count(d)
    high = stencil.high_area
    low = m - high
    q = 1 / (high * math.exp(eps) + low)
    return GridConstants(m, high, low, math.exp(eps) * q, q)


def continuous_constants(kind: str, b: float, eps: float, side: float = 1.0) -> tuple[float, float]:
    """(largest, smallest) density of the continuous disk or decay mechanism over a square of the given side."""
    ring = 4 * side * b + side * side
    e = math.exp(eps)
    if kind == "disk":
        q = 1 / (math.pi * b * b * e + ring)
    elif kind == "decay":
        q = eps * eps / (2 * math.pi * _m1_m2(eps)[0] * b * b + ring * eps * eps) if eps > 1e-9 else 1 / (math.pi * b * b + ring)
    else:
        raise ValueError("kind is disk or decay")
    return e * q, q
