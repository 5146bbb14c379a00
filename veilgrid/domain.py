"""The square domain, its cells, and histograms over them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.geometry import Stencil


@dataclass(frozen=True)
class GridSpec:
    """A rectangle that is scaled to the unit square and cut into d x d cells; cell (0, 0) is the lower left one."""

    x0: float
    y0: float
    width: float
    height: float
    d: int

    def __post_init__(self):
        if self.d < 1 or self.width <= 0 or self.height <= 0:
            raise ValueError("a grid needs a positive size and at least one cell a side")

    @classmethod
    def square(cls, x0: float, y0: float, side: float, d: int | None = None, g: float | None = None) -> GridSpec:
        """From the number of cells a side, or from the cell side g (the last cell is cut where g doesn't divide the side)."""
        if (d is None) == (g is None):
            raise ValueError("give either d or g")
        return cls(x0, y0, side, side, d if d is not None else -int(-side // g))

    @classmethod
    def from_data(cls, df: DataFrame, d: int, x: str = "x", y: str = "y", pad: float = 0.0) -> GridSpec:
        """Bounds of the finite points, each side widened by ``pad`` of its length; one aggregate, one row."""
        finite = [F.when(~F.isnan(c) & (F.abs(F.col(c)) < float("inf")), F.col(c)) for c in (x, y)]
        lo_x, hi_x, lo_y, hi_y = df.agg(F.min(finite[0]), F.max(finite[0]), F.min(finite[1]), F.max(finite[1])).first()
        if lo_x is None or lo_y is None:
            raise ValueError("no finite points")
        w, h = (hi_x - lo_x) or 1.0, (hi_y - lo_y) or 1.0
        return cls(lo_x - pad * w, lo_y - pad * h, w * (1 + 2 * pad), h * (1 + 2 * pad), d)

    @property
    def n(self) -> int:
        return self.d * self.d

    @property
    def g(self) -> float:
        """Cell side in units of the scaled square."""
        return 1.0 / self.d


def cell_of(value: Column, origin: float, length: float, d: int) -> Column:
    """Cell number along one axis; the far edge belongs to the last cell."""
    return F.least(F.floor((value - F.lit(origin)) * F.lit(float(d)) / F.lit(length)), F.lit(d - 1)).cast("int")


def in_domain(grid: GridSpec, x: str = "x", y: str = "y") -> Column:
    """A range predicate on plain columns, so it reaches the scan. Null and NaN are outside."""
    return F.col(x).between(grid.x0, grid.x0 + grid.width) & F.col(y).between(grid.y0, grid.y0 + grid.height)


def assign_cells(df: DataFrame, grid: GridSpec, x: str = "x", y: str = "y", out_of_domain: str = "drop") -> DataFrame:
    """Adds cx, cy. Points outside are dropped, moved to the nearest cell ('clamp') or refused when they are computed ('error').

    Null and NaN coordinates have no nearest cell: they are dropped under 'clamp' too.
    """
    if out_of_domain == "drop":
        df = df.where(in_domain(grid, x, y))
    elif out_of_domain == "clamp":
        df = df.where(F.col(x).isNotNull() & F.col(y).isNotNull() & ~F.isnan(F.col(x).cast("double")) & ~F.isnan(F.col(y).cast("double")))
    elif out_of_domain != "error":
        raise ValueError("out_of_domain is drop, clamp or error")
    cells = {"cx": cell_of(F.col(x), grid.x0, grid.width, grid.d), "cy": cell_of(F.col(y), grid.y0, grid.height, grid.d)}
    if out_of_domain == "clamp":
        cells = {k: F.greatest(c, F.lit(0)) for k, c in cells.items()}
    if out_of_domain == "error":
        inside = F.coalesce(in_domain(grid, x, y), F.lit(False))
        cells = {k: F.when(inside, c).otherwise(F.raise_error(F.lit("point outside the domain")).cast("int")) for k, c in cells.items()}
    return df.withColumns(cells)


def input_cells(spark: SparkSession, grid: GridSpec) -> DataFrame:
    """(cx, cy) of all d x d cells, by a range."""
    return spark.range(grid.n).select((F.col("id") % grid.d).cast("int").alias("cx"), F.floor(F.col("id") / grid.d).cast("int").alias("cy"))


def output_cells(spark: SparkSession, grid: GridSpec, stencil: Stencil) -> DataFrame:
    """(ox, oy) of all cells that some input cell's stencil covers, in closed form by rows: nothing is multiplied out and deduplicated."""
    spans = stencil.row_spans(grid.d)
    rows = spark.createDataFrame([(oy, lo, hi) for oy, lo, hi in spans], "oy int, lo int, hi int")
    return rows.select(F.explode(F.sequence("lo", "hi")).alias("ox"), "oy")


def true_histogram(points: DataFrame, grid: GridSpec, x: str = "x", y: str = "y", normalise: bool = True) -> DataFrame:
    """(cx, cy, mass) over all cells, empty ones included. Only counts are shuffled."""
    counts = assign_cells(points, grid, x, y).groupBy("cx", "cy").count()
    return fill_histogram(counts.withColumnRenamed("count", "n"), grid, normalise)


def fill_histogram(counts: DataFrame, grid: GridSpec, normalise: bool = True) -> DataFrame:
    """counts(cx, cy, n) with all cells; masses sum to one if asked for (all zero for an empty input)."""
    cells = input_cells(counts.sparkSession, grid)
    full = cells.join(counts.select("cx", "cy", "n"), ["cx", "cy"], "left").select("cx", "cy", F.coalesce("n", F.lit(0)).cast("double").alias("mass"))
    if not normalise:
        return full
    total = full.agg(F.sum("mass").alias("total"))
    return full.crossJoin(F.broadcast(total)).select("cx", "cy", F.when(F.col("total") > 0, F.col("mass") / F.col("total")).otherwise(0.0).alias("mass"))


def distance_set(cells: DataFrame, centres: DataFrame, b: float) -> DataFrame:
    """(cx, cy, ox, oy): cells (ox, oy) within b of centres (cx, cy), by a join on coarse blocks and an exact test.

    A block is at least b wide, so a centre meets only its own block and the eight around it.
    """
    width = max(1, -(-int(b * 1000000) // 1000000))
    block = lambda c: F.floor(F.col(c) / F.lit(width)).cast("int")
    near = centres.select("cx", "cy", F.explode(F.sequence(block("cx") - 1, block("cx") + 1)).alias("bx"), block("cy").alias("mid"))
    near = near.select("cx", "cy", "bx", F.explode(F.sequence(F.col("mid") - 1, F.col("mid") + 1)).alias("by"))
    keyed = cells.select("ox", "oy", block("ox").alias("bx"), block("oy").alias("by"))
    dx, dy = F.col("ox") - F.col("cx"), F.col("oy") - F.col("cy")
    return near.join(keyed, ["bx", "by"]).where(dx * dx + dy * dy <= F.lit(float(b) * float(b))).select("cx", "cy", "ox", "oy")
