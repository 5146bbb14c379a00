"""Ordinary frequency oracles on cells, which ignore distance: k-ary response, unary encoding, local hashing, subset selection."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec, fill_histogram, input_cells
from veilgrid.noise import hash_below, hash_limit, uniform_columns

KINDS = ("grr", "sue", "oue", "olh", "subset")


class CategoricalOracle:
    """Each kind reports a value or a set of cells and has a closed unbiased estimate (support - N q) / (N (p - q))."""

    privacy_model = "ldp"

    def __init__(self, kind: str, eps: float, grid: GridSpec):
        if kind not in KINDS:
            raise ValueError(f"kind is one of {KINDS}")
        self.kind, self.eps, self.grid = kind, eps, grid
        n, e = grid.n, math.exp(eps)
        self.hashes = max(2, round(e) + 1)
        self.size = max(1, round(n / (e + 1)))
        if kind == "grr":
            self.p, self.q = e / (e + n - 1), 1 / (e + n - 1)
        elif kind == "sue":
            self.p, self.q = math.exp(eps / 2) / (math.exp(eps / 2) + 1), 1 / (math.exp(eps / 2) + 1)
        elif kind == "oue":
            self.p, self.q = 0.5, 1 / (e + 1)
        elif kind == "olh":
            self.p, self.q = e / (e + self.hashes - 1), 1 / self.hashes
        else:
            k = self.size
            self.p = k * e / (k * e + n - k)
            self.q = self.p * (k - 1) / (n - 1) + (1 - self.p) * k / (n - 1) if n > 1 else self.p

    def cell(self) -> Column:
        return F.col("cy") * self.grid.d + F.col("cx")

    def report(self, cells: DataFrame, mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False) -> DataFrame:
        """grr: value; sue, oue: members (array of set positions; hash mode: a row per set position); olh: seed and value; subset: members."""
        n = self.grid.n
        if self.kind in ("grr", "olh"):
            df = uniform_columns(cells, ["_u", "_v"], mode, user, seed, unsafe_deterministic)
            domain = n if self.kind == "grr" else self.hashes
            own = self.cell() if self.kind == "grr" else olh_hash(F.col(user), self.cell(), self.hashes)
            stay = self.p if self.kind == "grr" or domain > 1 else 1.0
            other = F.floor(F.col("_v") * (domain - 1)).cast("int")
            value = F.when((F.col("_u") < stay) | F.lit(domain == 1), own).otherwise(other + (other >= own).cast("int"))
            return df.select(user, value.cast("int").alias("value")) if self.kind == "olh" else df.select(value.cast("int").alias("value"))
        if self.kind == "subset":
            return self._report_subset(cells, mode, user, seed, unsafe_deterministic)
        if mode == "hash":
            uniform_columns(cells.limit(0), ["_x"], mode, user, seed, unsafe_deterministic)  # refuses without consent
            one = cells.select(F.col(user).alias("_user"), self.cell().alias("_own"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("_j"))
            set_ = hash_below(F.col("_user"), F.col("_j"), F.when(F.col("_j") == F.col("_own"), hash_limit(self.p)).otherwise(hash_limit(self.q)), 42 if seed is None else seed)
            return one.where(set_).select("_user", F.col("_j").alias("cell"))  # the set bits as rows: all of it is generated code
        return self._report_bits(cells)

    def _report_bits(self, cells: DataFrame) -> DataFrame:
        p, q, n = self.p, self.q, self.grid.n

        @F.pandas_udf("array<int>")
        def draw(own):
            rng = np.random.default_rng()  # seeded by the operating system
            limit = np.full((len(own), n), q)
            limit[np.arange(len(own)), own.to_numpy()] = p
            hits = rng.random(limit.shape) < limit
            return own.__class__([np.flatnonzero(h).astype(np.int32) for h in hits])

        return cells.select(draw.asNondeterministic()(self.cell()).alias("members"))

    def _report_subset(self, cells, mode, user, seed, unsafe_deterministic) -> DataFrame:
        """k cells: the true one with probability p, the rest uniform among the others, as the first k of a random order."""
        df = uniform_columns(cells, ["_u", "_v"], mode, user, seed, unsafe_deterministic)
        n, k = self.grid.n, self.size
        start = [F.lit(str(42 if seed is None else seed)), F.col(user).cast("string")] if mode == "hash" else [F.col("_v").cast("string")]
        order = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.struct(F.md5(F.concat_ws(":", *start, (j + 2).cast("string")).cast("binary")).alias("h"), j.alias("j"))))
        others = F.filter(F.transform(order, lambda x: x["j"]), lambda j: j != self.cell())
        members = F.when(F.col("_u") < self.p, F.concat(F.array(self.cell()), F.slice(others, 1, k - 1) if k > 1 else F.array().cast("array<int>"))).otherwise(F.slice(others, 1, k))
        return df.select(F.array_sort(members).alias("members"))

    def support(self, reports: DataFrame, user: str = "user_id") -> DataFrame:
        """(cell, n): reports that speak for each cell, one shuffle of at most n rows a task."""
        if self.kind == "grr":
            return reports.groupBy(F.col("value").alias("cell")).count().withColumnRenamed("count", "n")
        if self.kind == "olh":
            hit = F.filter(F.sequence(F.lit(0), F.lit(self.grid.n - 1)), lambda j: olh_hash(F.col(user), j, self.hashes) == F.col("value"))
            reports = reports.select(hit.alias("members"))
        if "cell" in reports.columns:
            return reports.groupBy("cell").count().withColumnRenamed("count", "n")
        return reports.select(F.explode("members").alias("cell")).groupBy("cell").count().withColumnRenamed("count", "n")

    def estimate(self, support: DataFrame, users: int) -> DataFrame:
        """(cx, cy, mass): unbiased, may be negative."""
        d = self.grid.d
        counted = support.select((F.col("cell") % d).cast("int").alias("cx"), F.floor(F.col("cell") / d).cast("int").alias("cy"), "n")
        full = fill_histogram(counted, self.grid, normalise=False)
        return full.select("cx", "cy", ((F.col("mass") - users * self.q) / (users * (self.p - self.q))).alias("mass"))


def olh_hash(user: Column, cell: Column, hashes: int) -> Column:
    """Hash of a cell under the user's own function: digits of md5('user:cell') modulo the range."""
    digest = F.md5(F.concat_ws(":", user.cast("string"), cell.cast("string")).cast("binary"))
    return F.pmod(F.conv(F.substring(digest, 1, 13), 16, 10).cast("long"), F.lit(hashes)).cast("int")
