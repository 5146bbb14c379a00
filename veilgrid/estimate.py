"""The whole estimate: cells, reports, one count, inversion."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec, assign_cells
from veilgrid.em import Fit, em, em_fft, em_stencil
from veilgrid.mechanisms.area import AreaMechanism
from veilgrid.mechanisms.axis import AxisWaveMechanism

#: Dense inversion up to this many channel entries; stencil or transform beyond.
DENSE_ENTRIES = 4_000_000
#: Stencil cells above which both sums of a step are computed by transforms.
WIDE_STENCIL = 400


def count_reports(reports: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., ox, oy, n): partial counts before one shuffle of at most outputs rows a task."""
    return reports.groupBy(*by, "ox", "oy").agg(F.count("*").alias("n"))


def invert_counts(mech: AreaMechanism, counts: dict[tuple[int, int], int], max_iter: int = 2000, tol: float = 1e-9, smooth: bool = False, method: str = "auto", start: np.ndarray | None = None) -> Fit:
    """counts by output cell, bounded by the domain and not by the users."""
    d = mech.grid.d
    if method == "auto":
        method = "dense" if d * d * mech.outputs <= DENSE_ENTRIES else "fft" if len(mech.excess) > WIDE_STENCIL else "stencil"
    if method == "dense":
        return em(np.array([counts.get(c, 0) for c in mech.output_list], dtype=float), mech.channel_matrix(), max_iter, tol, smooth, start=start)
    reach = len(mech.stencil.half_widths) - 1
    frame, mask = np.zeros((2, d + 2 * reach, d + 2 * reach))
    for oy, lo, hi in mech.stencil.row_spans(d):
        mask[oy + reach, lo + reach : hi + reach + 1] = 1
    for (ox, oy), n in counts.items():
        frame[oy + reach, ox + reach] = n
    excess = [(dx, dy, w * mech.q) for dx, dy, w in mech.excess]
    return (em_fft if method == "fft" else em_stencil)(frame, excess, mech.q, d, reach, mask, max_iter, tol, smooth, start)


def to_histogram(spark: SparkSession, mass: np.ndarray, d: int) -> DataFrame:
    cells = np.arange(d * d)
    return spark.createDataFrame(pd.DataFrame({"cx": (cells % d).astype(np.int32), "cy": (cells // d).astype(np.int32), "mass": mass}), "cx int, cy int, mass double")


def estimate_from_reports(reports: DataFrame, mech: AreaMechanism, **options) -> DataFrame:
    """What the analyst runs: sees reports only."""
    counts = {(r.ox, r.oy): r.n for r in count_reports(reports).collect()}  # at most mech.outputs rows
    return to_histogram(reports.sparkSession, invert_counts(mech, counts, **options).mass, mech.grid.d)


def estimate_distribution(points: DataFrame, grid: GridSpec, mech: AreaMechanism, mode: str = "secure", seed: int | None = None, unsafe_deterministic: bool = False, **options) -> DataFrame:
    """points(user_id, x, y) -> (cx, cy, mass)."""
    reports = mech.report(assign_cells(points, grid), mode, seed=seed, unsafe_deterministic=unsafe_deterministic)
    return estimate_from_reports(reports, mech, **options)


def estimate_by(points: DataFrame, grid: GridSpec, mech: AreaMechanism, by: tuple[str, ...], mode: str = "secure", seed: int | None = None, unsafe_deterministic: bool = False, max_iter: int = 2000, tol: float = 1e-9) -> DataFrame:
    """(by..., cx, cy, mass) for every group: one count for all, then one inversion a group in parallel."""
    reports = mech.report(assign_cells(points, grid), mode, seed=seed, unsafe_deterministic=unsafe_deterministic, keep=by)
    d = grid.d

    def invert(key, pdf):
        mass = invert_counts(mech, dict(zip(zip(pdf.ox, pdf.oy, strict=True), pdf.n, strict=True)), max_iter, tol).mass
        cells = np.arange(d * d)
        return pd.DataFrame({**dict(zip(by, key, strict=True)), "cx": cells % d, "cy": cells // d, "mass": mass})

    counts = count_reports(reports, by)
    fields = ", ".join(f"{c} {t}" for c, t in counts.select(*by).dtypes)
    return counts.groupBy(*by).applyInPandas(invert, f"{fields}, cx int, cy int, mass double")


def estimate_axes(points: DataFrame, grid: GridSpec, mech: AxisWaveMechanism, mode: str = "secure", seed: int | None = None, unsafe_deterministic: bool = False, **options) -> DataFrame:
    """Per-axis baseline end to end, by either merge."""
    reports = mech.report(assign_cells(points, grid), mode, seed=seed, unsafe_deterministic=unsafe_deterministic)
    b, m = mech.wave.b, mech.wave.outputs
    if mech.merge == "joint":
        frame = np.zeros((m, m))
        for r in count_reports(reports).collect():
            frame[r.oy + b, r.ox + b] = r.n
        mass = mech.estimate_joint(frame, **options).mass
    else:
        axes = {"x": np.zeros(m), "y": np.zeros(m)}
        for r in mech.count_axes(reports).collect():
            axes[r.axis][r.o + b] = r.n
        mass = mech.estimate(axes["x"], axes["y"], **options)
    return to_histogram(points.sparkSession, mass, grid.d)
