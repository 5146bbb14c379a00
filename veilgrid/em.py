"""Inversion of noisy counts: expectation-maximisation and linear estimates.

After counting, nothing depends on the number of users: dense and stencil forms work on arrays of the
cells, the relational forms keep everything in DataFrames for domains that don't fit one process.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.lineage import materialise


@dataclass(frozen=True)
class Fit:
    mass: np.ndarray
    iterations: int
    log_likelihood: float


def smooth_mass(f: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Binomial smoothing (1, 2, 1) / 4 along each axis; weights that fall outside are given back to the border cell."""
    out = f.reshape(shape)
    for axis, n in enumerate(shape):
        padded = np.concatenate([out.take([0], axis), out, out.take([-1], axis)], axis)
        out = 0.25 * padded.take(range(n), axis) + 0.5 * out + 0.25 * padded.take(range(2, n + 2), axis)
    return out.ravel() / out.sum()


def em(counts: np.ndarray, channel: np.ndarray, max_iter: int = 2000, tol: float = 1e-9, smooth: bool = False, shape: tuple[int, ...] | None = None, start: np.ndarray | None = None) -> Fit:
    """counts over m outputs, channel n x m. Uniform start unless another is given; stops on a small relative change of the log-likelihood.

    With ``smooth`` every step is followed by binomial smoothing over ``shape`` (a square unless given), which keeps fine grids from being over-fitted.
    """
    return _iterate(counts, channel.shape[0], lambda f: f @ channel, lambda r: channel @ r, max_iter, tol, smooth, shape, start)


def _iterate(counts, n, forward, backward, max_iter, tol, smooth=False, shape=None, start=None) -> Fit:
    seen = counts > 0

    def step(f):
        predicted = forward(f)
        likelihood = float(counts[seen] @ np.log(predicted[seen]))
        return likelihood, lambda: backward(np.divide(counts, predicted, out=np.zeros_like(predicted), where=predicted > 0))

    return iterate_steps(step, n, counts.sum(), max_iter, tol, smooth, shape, start)


def iterate_steps(step, n, total, max_iter, tol, smooth=False, shape=None, start=None) -> Fit:
    """``step`` gives the log-likelihood of a mass and a function for what each cell's mass is multiplied by (times the total).

    A start is mixed with a little of the uniform one: a cell at zero would stay there.
    """
    shape = shape or (math.isqrt(n), math.isqrt(n))
    f = np.full(n, 1 / n) if start is None else 0.99 * start / start.sum() + 0.01 / n
    if total == 0:
        return Fit(f, 0, 0.0)
    before = -math.inf
    for k in range(1, max_iter + 1):
        likelihood, gain = step(f)
        if abs(likelihood - before) < tol * abs(likelihood):
            return Fit(f, k - 1, likelihood)
        before = likelihood
        f = f * gain() / total
        f = smooth_mass(f, shape) if smooth else f / f.sum()
    return Fit(f, max_iter, before)


def em_stencil(counts: np.ndarray, excess: list[tuple[int, int, float]], q: float, d: int, reach: int, output_mask: np.ndarray, max_iter: int = 2000, tol: float = 1e-9, smooth: bool = False, start: np.ndarray | None = None) -> Fit:
    """counts on the (d + 2 reach)^2 frame of the output domain; cost per step is cells times stencil, no channel is held."""
    def forward(f):
        out = q * f.sum() * output_mask
        g = f.reshape(d, d)
        for dx, dy, w in excess:
            out[reach + dy : reach + dy + d, reach + dx : reach + dx + d] += w * g
        return out.ravel()

    def backward(r):
        r = r.reshape(output_mask.shape)
        out = np.full((d, d), q * (r * output_mask).sum())
        for dx, dy, w in excess:
            out += w * r[reach + dy : reach + dy + d, reach + dx : reach + dx + d]
        return out.ravel()

    return _iterate(counts.ravel().astype(float), d * d, forward, backward, max_iter, tol, smooth, start=start)


def em_fft(counts: np.ndarray, excess: list[tuple[int, int, float]], q: float, d: int, reach: int, output_mask: np.ndarray, max_iter: int = 2000, tol: float = 1e-9, smooth: bool = False, start: np.ndarray | None = None) -> Fit:
    """The same as em_stencil with both sums as convolutions; for wide stencils and large d."""
    size = d + 2 * reach
    kernel = np.zeros((size, size))
    for dx, dy, w in excess:
        kernel[dy % size, dx % size] += w
    spectrum = np.fft.rfft2(kernel)
    mask = output_mask.astype(float)

    def forward(f):
        frame = np.zeros((size, size))
        frame[reach : reach + d, reach : reach + d] = f.reshape(d, d)
        return (np.maximum(np.fft.irfft2(np.fft.rfft2(frame) * spectrum, s=frame.shape), 0) + q * f.sum() * mask).ravel()

    def backward(r):
        r = r.reshape(size, size)
        back = np.fft.irfft2(np.fft.rfft2(r) * spectrum.conj(), s=r.shape)[reach : reach + d, reach : reach + d]
        return (np.maximum(back, 0) + q * (r * mask).sum()).ravel()

    return _iterate(counts.ravel().astype(float), d * d, forward, backward, max_iter, tol, smooth, start=start)


def em_frame(counts: DataFrame, channel: DataFrame, n: int, iterations: int) -> DataFrame:
    """Relational EM with a fixed number of steps: counts(ox, oy, n), channel(cx, cy, ox, oy, prob) -> (cx, cy, mass).

    Two equi-joins and two sums a step; each sum combines before its shuffle.
    """
    total = F.lit(float(counts.agg(F.sum("n")).first()[0] or 0))
    f = channel.select("cx", "cy").distinct().withColumn("mass", F.lit(1.0 / n))
    joint = channel.join(counts, ["ox", "oy"])
    for _ in range(iterations):
        weighed = joint.join(f, ["cx", "cy"]).withColumn("part", F.col("mass") * F.col("prob"))
        predicted = weighed.groupBy("ox", "oy").agg(F.sum("part").alias("predicted"))
        f = weighed.join(predicted, ["ox", "oy"]).groupBy("cx", "cy").agg((F.sum(F.col("part") * F.col("n") / F.col("predicted")) / total).alias("mass"))
    return f


def em_stencil_frame(counts: DataFrame, cells: DataFrame, excess: DataFrame, q: float, iterations: int, checkpoint_every: int = 0) -> DataFrame:
    """Relational EM without a channel: the background is a scalar and the excess a broadcast stencil, so a step costs cells times stencil.

    counts(ox, oy, n), cells(cx, cy), excess(dx, dy, excess); the stencil's size is set by the radius, not the data.
    """
    total = float(counts.agg(F.sum("n")).first()[0] or 0)
    n = cells.count()
    f = cells.withColumn("mass", F.lit(1.0 / n))
    stencil = F.broadcast(excess)
    for k in range(iterations):
        spread = f.crossJoin(stencil).select((F.col("cx") + F.col("dx")).alias("ox"), (F.col("cy") + F.col("dy")).alias("oy"), (F.col("mass") * F.col("excess")).alias("part"))
        near = spread.groupBy("ox", "oy").agg(F.sum("part").alias("near"))
        ratio = counts.join(near, ["ox", "oy"], "left").select("ox", "oy", (F.col("n") / (F.lit(q) + F.coalesce("near", F.lit(0.0)))).alias("ratio"))
        back = ratio.crossJoin(stencil).select((F.col("ox") - F.col("dx")).alias("cx"), (F.col("oy") - F.col("dy")).alias("cy"), (F.col("ratio") * F.col("excess")).alias("part"))
        gained = back.groupBy("cx", "cy").agg(F.sum("part").alias("gain"))
        base = ratio.agg(F.sum("ratio").alias("all"))
        f = f.join(gained, ["cx", "cy"], "left").crossJoin(F.broadcast(base)).select("cx", "cy", (F.col("mass") * (F.lit(q) * F.col("all") + F.coalesce("gain", F.lit(0.0))) / F.lit(total)).alias("mass"))
        if checkpoint_every and k % checkpoint_every == checkpoint_every - 1:
            f = materialise(f)
    return f


def invert_linear(counts: np.ndarray, channel: np.ndarray) -> np.ndarray:
    """Least-squares inverse of the channel; unbiased, may be negative."""
    return np.linalg.lstsq(channel.T, counts / max(1, counts.sum()), rcond=None)[0]


def project_simplex(v: np.ndarray) -> np.ndarray:
    """Nearest distribution by Euclidean distance."""
    u = np.sort(v)[::-1]
    gap = np.cumsum(u) - 1
    k = np.flatnonzero(u - gap / np.arange(1, len(v) + 1) > 0)[-1]
    return np.maximum(v - gap[k] / (k + 1), 0)


def clip_normalise(v: np.ndarray) -> np.ndarray:
    v = np.maximum(v, 0)
    return v / v.sum() if v.sum() > 0 else np.full(len(v), 1 / len(v))
