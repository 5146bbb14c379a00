"""Subset exponential mechanism under distance-scaled privacy.

A report is a set S of k cells, with probability proportional to exp(-eps' / 2 * distance of the nearest member). The
nearest member's rank among the cells sorted by distance fixes how many sets share that weight, so a report is drawn by
rank and then uniformly among the farther cells: no set is ever listed.
"""

from __future__ import annotations

import math
from functools import cached_property
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec
from veilgrid.em import Fit, em, iterate_steps, smooth_mass
from veilgrid.lineage import materialise
from veilgrid.noise import uniform_columns

#: Distinct sets that are inverted in one process (the channel has as many columns).
MAX_SETS = 100_000
#: Sets of a smaller space are counted in one array with a place for each; of a larger one, those that are met are kept.
DENSE_SETS = 1 << 24
#: Draws, or sets, that are handled at once.
CHUNK = 1 << 17


def default_size(eps: float, n: int) -> int:
    """k = n / e^eps to the nearest whole, at least one."""
    return min(n, max(1, math.floor(n / math.exp(eps) + 0.5)))


class SubsetExponentialMechanism:
    privacy_model = "distance"

    def __init__(self, eps_prime: float, grid: GridSpec, k: int = 1, score: str = "nearest"):
        if not 1 <= k <= grid.n:
            raise ValueError("k lies between one and the number of cells")
        if score not in ("nearest", "sum"):
            raise ValueError("score is nearest or sum")
        self.eps_prime, self.grid, self.k, self.score = eps_prime, grid, k, score

    @cached_property
    def distances(self) -> np.ndarray:
        c = np.arange(self.grid.n)
        x, y = c % self.grid.d, c // self.grid.d
        return np.hypot(x[:, None] - x[None], y[:, None] - y[None])

    @cached_property
    def order(self) -> np.ndarray:
        """order[i]: cells by distance from i, then by number."""
        return np.argsort(self.distances, axis=1, kind="stable")

    @cached_property
    def rank_law(self) -> np.ndarray:
        """rank_law[i, r]: probability that the r-th nearest cell of i is the nearest member."""
        n, k = self.grid.n, self.k
        sets = np.array([_log_choose(n - 1 - r, k - 1) for r in range(n)])
        log_weight = sets[None] - 0.5 * self.eps_prime * np.take_along_axis(self.distances, self.order, axis=1)
        weight = np.exp(log_weight - log_weight.max(axis=1, keepdims=True))
        return weight / weight.sum(axis=1, keepdims=True)

    @cached_property
    def log_normaliser(self) -> np.ndarray:
        n, k = self.grid.n, self.k
        sets = np.array([_log_choose(n - 1 - r, k - 1) for r in range(n)])
        return np.logaddexp.reduce(sets[None] - 0.5 * self.eps_prime * np.take_along_axis(self.distances, self.order, axis=1), axis=1)

    @cached_property
    def sum_law(self) -> np.ndarray:
        """For score 'sum': the law of the member drawn first; the others are uniform. A set's weight is the sum of its members'."""
        n, k = self.grid.n, self.k
        w = np.exp(-0.5 * self.eps_prime * self.distances)
        return w / w.sum(axis=1, keepdims=True)

    def sample(self, cells: np.ndarray, rng: np.random.Generator) -> np.ndarray:
        """Sorted members, one row per given input cell number."""
        return self.sample_from(cells, rng.random((len(cells), self.k)))

    def sample_from(self, cells: np.ndarray, u: np.ndarray) -> np.ndarray:
        """The same from uniforms u[row, k]: the first picks the nearest member (or, for score 'sum', the member drawn by weight), each other one
        picks evenly among the cells that may follow and aren't picked yet."""
        n, k = self.grid.n, self.k
        law = self.rank_law if self.score == "nearest" else self.sum_law
        first = np.minimum((np.cumsum(law, axis=1)[cells] < u[:, :1]).sum(axis=1), n - k if self.score == "nearest" else n - 1)
        left = n - 1 - first if self.score == "nearest" else np.full(len(cells), n - 1)
        picked = np.empty((len(cells), 0), dtype=np.int64)
        for j in range(1, k):
            at = np.minimum(np.floor(u[:, j] * (left - j + 1)).astype(np.int64), left - j)
            for c in range(j - 1):  # places already taken are passed over, in rising order
                at = at + (at >= picked[:, c])
            picked = np.sort(np.column_stack([picked, at]), axis=1)
        if self.score == "nearest":
            ranks = np.column_stack([first, picked + first[:, None] + 1])
            out = np.take_along_axis(self.order[cells], ranks, axis=1)
        else:
            out = np.column_stack([first, picked + (picked >= first[:, None])])
        return np.sort(out, axis=1).astype(np.int32)

    def report(self, cells: DataFrame, mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
        """(keep..., members ARRAY<INT>) from k uniforms a user, by Arrow batches; the rank table (n x n) goes with the function."""
        sample, d, names = self.sample_from, self.grid.d, [f"_u{j}" for j in range(self.k)]
        drawn = uniform_columns(cells, names, mode, user, seed, unsafe_deterministic)

        @F.pandas_udf("array<int>")
        def draw(cx, cy, u):
            return cx.__class__(list(sample((cy * d + cx).to_numpy(), np.stack(u.to_numpy())))) if len(cx) else cx.astype(object)

        return drawn.select(*keep, draw("cx", "cy", F.array(*names)).alias("members"))

    @staticmethod
    def count(reports: DataFrame) -> DataFrame:
        """(members, n): up to as many rows as reports for small eps and k above one."""
        return reports.groupBy("members").count().withColumnRenamed("count", "n")

    def set_probabilities(self, sets: np.ndarray) -> np.ndarray:
        """P(S | i) for each row of members: n x number of sets."""
        if self.score == "sum":
            n, k = self.grid.n, self.k
            w = np.exp(-0.5 * self.eps_prime * self.distances)
            return w[:, sets].sum(axis=2) / (w.sum(axis=1, keepdims=True) * math.exp(_log_choose(n - 1, k - 1)))
        near = self.distances[:, sets].min(axis=2)
        return np.exp(-0.5 * self.eps_prime * near - self.log_normaliser[:, None])

    @cached_property
    def binomials(self) -> np.ndarray:
        """binomials[j, c] = C(c, j); what exceeds the largest set number is cut there, where no search reaches."""
        if math.comb(self.grid.n, self.k) >= 1 << 62:
            raise ValueError("too many sets to be numbered")
        return np.array([[min(math.comb(c, j), 1 << 62) for c in range(self.grid.n + 1)] for j in range(self.k + 1)])

    def members_of(self, numbers: np.ndarray, k: int | None = None) -> np.ndarray:
        """Rising members of the sets of k with these numbers; sets are numbered by their largest member first, then the next."""
        k, rest = self.k if k is None else k, numbers
        out = np.empty((len(numbers), k), dtype=np.int64)
        for j in range(k, 0, -1):
            out[:, j - 1] = np.searchsorted(self.binomials[j], rest, side="right") - 1
            rest = rest - self.binomials[j][out[:, j - 1]]
        return out

    def numbers_of(self, sets: np.ndarray) -> np.ndarray:
        return sum(self.binomials[j + 1][sets[:, j]] for j in range(self.k))

    def tally(self, counts: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        """(numbers of the sets met, how often) when counts[i] users of each cell report; memory depends on the sets, not on the users.

        The nearest members' ranks are a multinomial per cell; then each user's other members are one even number among the sets of farther cells.
        """
        if self.score != "nearest":
            raise ValueError("sets are tallied for score nearest")
        n, k, dense = self.grid.n, self.k, math.comb(self.grid.n, self.k) <= DENSE_SETS
        met = np.zeros(math.comb(n, k), dtype=np.int64) if dense else (np.empty(0, dtype=np.int64),) * 2
        for i in np.flatnonzero(counts):
            for r, users in enumerate(rng.multinomial(counts[i], self.rank_law[i])):
                for at in range(0, users, CHUNK):
                    drawn, times = np.unique(rng.integers(math.comb(n - 1 - r, k - 1), size=min(CHUNK, users - at)), return_counts=True)
                    ranks = np.column_stack([np.full(len(drawn), r), self.members_of(drawn, k - 1) + r + 1])
                    numbers = self.numbers_of(np.sort(self.order[i][ranks], axis=1))
                    if dense:
                        met[numbers] += times  # one cell and rank: no number comes twice
                    else:
                        met = _add_up(np.concatenate([met[0], numbers]), np.concatenate([met[1], times]))
        return (np.flatnonzero(met), met[met > 0]) if dense else met

    def invert_tally(self, numbers: np.ndarray, times: np.ndarray, max_iter: int = 500, tol: float = 1e-9, smooth: bool = False) -> Fit:
        """EM over tallied sets. A set's column of the channel isn't held: it is told by the distance of its nearest member from each cell, and the
        few distances of some cells make one short code, so that a step looks up and adds up whole groups of cells."""
        n, (levels, level_of) = self.grid.n, np.unique(self.distances, return_inverse=True)
        level_of = level_of.reshape(n, n).astype(np.int32)
        base = level_of[np.arange(n), self.order[:, n - self.k]] + 1  # k members can't all be farther than that
        groups, width = [[]], 1
        for i in range(n):
            if groups[-1] and width * int(base[i]) > 1 << 16:
                groups, width = [*groups, []], 1
            groups[-1].append(i)
            width *= int(base[i])
        codes = np.empty((len(groups), len(numbers)), dtype=np.uint16 if base.max() <= 1 << 16 else np.int64)
        parts = [slice(a, a + CHUNK) for a in range(0, len(numbers), CHUNK)]
        for part in parts:
            members = self.members_of(numbers[part])
            for g, cells in enumerate(groups):
                code = 0
                for i in cells:
                    near = level_of[i][members[:, 0]]
                    for j in range(1, self.k):
                        np.minimum(near, level_of[i][members[:, j]], out=near)
                    code = code * base[i] + near
                codes[g, part] = code
        prob = np.exp(-0.5 * self.eps_prime * levels[None] - self.log_normaliser[:, None])

        def step(f):
            tables, likelihood = [np.zeros(1)] * len(groups), 0.0
            for g, cells in enumerate(groups):
                for i in cells:
                    tables[g] = np.add.outer(tables[g], f[i] * prob[i, : base[i]]).ravel()
            sums = [np.zeros(len(t)) for t in tables]
            for part in parts:
                at, seen = codes[:, part].astype(np.intp), times[part]
                predicted = tables[0][at[0]]
                for g in range(1, len(groups)):
                    predicted += tables[g][at[g]]
                likelihood += float(seen @ np.log(predicted))
                ratio = seen / predicted
                for g, total in enumerate(sums):
                    total += np.bincount(at[g], ratio, len(total))
            gain = np.empty(n)
            for g, cells in enumerate(groups):
                cube = sums[g].reshape(base[cells])
                for axis, i in enumerate(cells):
                    gain[i] = prob[i, : base[i]] @ cube.sum(axis=tuple(a for a in range(len(cells)) if a != axis))
            return likelihood, lambda: gain

        return iterate_steps(step, n, times.sum(), max_iter, tol, smooth, (self.grid.d, self.grid.d))

    def estimate(self, counts: DataFrame, max_iter: int = 500, tol: float = 1e-9, smooth: bool = False, most: int = MAX_SETS) -> Fit:
        """EM over counts (members, n). Up to ``most`` distinct sets are inverted in one process; more of them stay where they are, and
        every step sums one vector of cells per task."""
        n = self.grid.n
        counts = materialise(counts)
        if counts.count() <= most:
            rows = counts.collect()
            sets = np.array([r.members for r in rows], dtype=np.int64).reshape(-1, self.k)
            return em(np.array([r.n for r in rows], dtype=float), self.set_probabilities(sets), max_iter, tol, smooth)
        probabilities, f, before = self.set_probabilities, np.full(n, 1 / n), -math.inf
        total = float(counts.agg(F.sum("n")).first()[0])
        for step in range(1, max_iter + 1):
            def gained(batches, f=f):
                out, likelihood = np.zeros(n), 0.0
                for pdf in batches:
                    prob, seen = probabilities(np.stack(pdf.members.to_numpy()).astype(np.int64)), pdf.n.to_numpy(dtype=float)
                    predicted = f @ prob
                    out, likelihood = out + f * (prob @ (seen / predicted)), likelihood + float(seen @ np.log(predicted))
                yield pd.DataFrame({"gain": [out.tolist()], "likelihood": [likelihood]})

            parts = counts.mapInPandas(gained, "gain array<double>, likelihood double").toPandas()
            likelihood = float(parts.likelihood.sum())
            if abs(likelihood - before) < tol * abs(likelihood):
                return Fit(f, step - 1, likelihood)
            before, f = likelihood, np.sum(parts.gain.tolist(), axis=0) / total
            f = smooth_mass(f, (self.grid.d, self.grid.d)) if smooth else f / f.sum()
        return Fit(f, max_iter, before)

    def all_sets(self) -> np.ndarray:
        return np.array(list(combinations(range(self.grid.n), self.k)), dtype=np.int32)

    def output_space(self) -> float:
        return math.exp(_log_choose(self.grid.n, self.k))

    def rank_table(self, spark: SparkSession) -> DataFrame:
        """(cell, rank, other, dist, prob) by a window over distances; for score 'nearest'."""
        rows = [(i, r, int(self.order[i, r]), float(self.distances[i, self.order[i, r]]), float(self.rank_law[i, r])) for i in range(self.grid.n) for r in range(self.grid.n)]
        return spark.createDataFrame(rows, "cell int, rank int, other int, dist double, prob double")


def _add_up(keys: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sums of times by key, keys rising."""
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[first], np.add.reduceat(times[order], first)


def _log_choose(n: int, k: int) -> float:
    return -math.inf if k < 0 or k > n else math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
