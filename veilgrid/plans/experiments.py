"""The experiment workloads: distances as one parameter varies, for every method, point set and part.

One scan per point set gives the true cell counts of every side length; from there a study needs no user. The noisy
counts of a run are drawn per true cell as multinomials, which has the law of counting every user's report, and each (part, setting,
run) is one group of at most d^2 rows that is simulated, inverted and measured in its own task.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilgrid.domain import GridSpec, assign_cells, cell_of, in_domain
from veilgrid.em import em
from veilgrid.estimate import count_reports, invert_counts
from veilgrid.geometry import grid_radius
from veilgrid.mechanisms import AxisWaveMechanism, DecayMechanism, DiskMechanism, SubsetExponentialMechanism
from veilgrid.mechanisms.subset import default_size
from veilgrid.metrics.transport import pointwise_errors, sliced_wasserstein, wasserstein_exact, wasserstein_sinkhorn
from veilgrid.privacy import local_privacy, match_privacy
from veilgrid.registry import query, table
from veilgrid.sources.datasets import POINT_SETS, SQUARE_PARTS

#: The settings of the experiments.
SIDES_SMALL, SIDES_LARGE = (1, 2, 3, 4, 5), (1, 5, 10, 15, 20)
EPS_SMALL, EPS_LARGE = (0.7, 1.4, 2.1, 2.8, 3.5), (5.0, 6.0, 7.0, 8.0, 9.0)
FACTORS = (0.33, 0.67, 1.0, 1.33, 1.67)
RUNS = 10
#: Plain and smoothed inversion.
BOTH = (False, True)
ALL_METHODS = ("disk", "disk_noshrink", "decay", "axis", "subset")
RESULT = "dataset string, part string, setting int, method string, eps double, d int, factor double, b_hat int, k int, eps_prime double, smooth boolean, measure string, run int, w2 double, sw1 double, mae double, kl double, iterations int"


def truth_counts(points: DataFrame, name: str, sides: tuple[int, ...], by_part: bool = True) -> DataFrame:
    """(dataset, part, d, cx, cy, n): one scan, one shuffle of cell counts for all sides.

    Parts are squares, half open so that they don't overlap, each with a grid of its own; without parts the whole domain is one.
    """
    parts = SQUARE_PARTS[name] if by_part else {"all": POINT_SETS[name].domain}
    x, y, places = F.col("x"), F.col("y"), []
    for d in sorted(set(sides)):
        for part, domain in parts.items():
            grid = GridSpec(*domain, d)
            inside = (x >= grid.x0) & (x < grid.x0 + grid.width) & (y >= grid.y0) & (y < grid.y0 + grid.height) if by_part else in_domain(grid)
            cx, cy = cell_of(x, grid.x0, grid.width, d), cell_of(y, grid.y0, grid.height, d)
            places.append(F.struct(F.lit(d).alias("d"), F.lit(part).alias("part"), cx.alias("cx"), cy.alias("cy"), inside.alias("inside")))
    spread = points.select(F.explode(F.array(*places)).alias("s")).where("s.inside")
    return spread.groupBy(F.lit(name).alias("dataset"), *[F.col(f"s.{c}").alias(c) for c in ("part", "d", "cx", "cy")]).agg(F.count("*").alias("n"))


@lru_cache(maxsize=256)
def matched_budget(eps: float, d: int, k_rule: str = "one", min_radius: int = 0) -> tuple[int, float]:
    """(k, eps') of the subset mechanism with the disk's local privacy. k_rule 'growth' starts from n / e^eps and lowers k while it can't match."""
    grid = GridSpec(0.0, 0.0, 1.0, 1.0, d)
    if d == 1:
        return 1, eps
    distances = SubsetExponentialMechanism(1.0, grid).distances
    target = local_privacy(DiskMechanism(eps, grid, min_radius=min_radius).channel_matrix(), distances)
    k = 1 if k_rule == "one" else default_size(eps, grid.n)
    while True:
        try:
            return k, match_privacy(target, grid, k, samples=4000, rounds=30)
        except ValueError:
            if k == 1:
                raise
            k = max(1, k // 2)


def settings_for(methods, sides=(5,), budgets=(3.5,), factors=(1.0,), k_rule: str = "growth", min_radius: int = 0, smooth: tuple[bool, ...] = (False,), measure: str = "exact") -> list[dict]:
    """Every combination, numbered; ``smooth`` says whether the inversion smooths (both are tried where both are given), ``measure`` how
    the distance is found on all of them: exact or sinkhorn."""
    out = []
    for d in sides:
        for eps in budgets:
            for factor in factors:
                for method, ems in ((m, x) for m in methods for x in smooth):
                    k, e = matched_budget(eps, d, k_rule, min_radius) if method == "subset" else (0, 0.0)
                    out.append({"setting": len(out), "method": method, "eps": float(eps), "d": int(d), "factor": float(factor), "b_hat": grid_radius(eps, d, factor, min_radius), "k": k, "eps_prime": float(e), "smooth": ems, "measure": measure})
    return out


def simulate(method: str, counts: np.ndarray, d: int, eps: float, b_hat: int, k: int, eps_prime: float, rng: np.random.Generator, smooth: bool = False, max_iter: int = 1000, tol: float = 1e-8) -> tuple[np.ndarray, int]:
    """(estimated mass, EM steps) of one run from true counts (counts[cy * d + cx])."""
    grid = GridSpec(0.0, 0.0, 1.0, 1.0, d)
    if method == "exact":
        return counts / counts.sum(), 0
    if method == "uniform":
        return np.full(d * d, 1 / (d * d)), 0
    if method == "axis":
        wave = AxisWaveMechanism(eps, grid)
        channel = wave.wave.channel_matrix()
        sides = counts.reshape(d, d)
        noisy = [sum(rng.multinomial(n, row / row.sum()) for n, row in zip(sides.sum(axis=a), channel, strict=True)) for a in (0, 1)]
        fits = [em(x.astype(float), channel, max_iter, tol, smooth, (d,)) for x in noisy]
        return np.outer(fits[1].mass, fits[0].mass).ravel(), sum(f.iterations for f in fits)
    if method == "subset" and k > 1:
        mech = SubsetExponentialMechanism(eps_prime, grid, k)
        if math.comb(grid.n, k) < 1 << 62:
            fit = mech.invert_tally(*mech.tally(counts, rng), max_iter, tol, smooth)
        else:  # sets that no whole number tells apart are kept as rows
            sets = np.concatenate([mech.sample(part, rng) for part in np.array_split(np.repeat(np.arange(d * d), counts), max(1, counts.sum() // 20_000))])
            distinct, n = np.unique(sets, axis=0, return_counts=True)
            fit = em(n.astype(float), mech.set_probabilities(distinct), max_iter, tol, smooth)
        return fit.mass, fit.iterations
    if method == "subset":
        mech = SubsetExponentialMechanism(eps_prime, grid, 1)
        channel = mech.set_probabilities(np.arange(d * d)[:, None])
    elif method == "decay":
        channel = DecayMechanism(eps, grid, b_hat).channel_matrix()
    else:
        channel = DiskMechanism(eps, grid, b_hat, shrink=method == "disk").channel_matrix()
    noisy = np.zeros(channel.shape[1])
    for n, row in zip(counts, channel, strict=True):
        if n:
            noisy += rng.multinomial(n, row / row.sum())
    fit = em(noisy, channel, max_iter, tol, smooth)
    return fit.mass, fit.iterations


def evaluate(pdf: pd.DataFrame, seed: int = 1) -> pd.DataFrame:
    """One group: the true cells of a part with one setting and run."""
    s = pdf.iloc[0]
    d = int(s.d)
    counts = np.zeros(d * d, dtype=np.int64)
    counts[(pdf.cy * d + pdf.cx).to_numpy()] = pdf.n
    rng = np.random.default_rng([seed, int(s.setting), int(s.run), sum(map(ord, f"{s.dataset}/{s.part}"))])
    mass, steps = simulate(s.method, counts, d, s.eps, int(s.b_hat), int(s.k), s.eps_prime, rng, bool(s.smooth))
    truth = counts / counts.sum()
    w2 = wasserstein_exact(truth, mass, d) if s.measure == "exact" else wasserstein_sinkhorn(truth, mass, d, max_iter=10_000, tol=1e-5)
    errors = pointwise_errors(truth, mass)
    row = {c: s[c] for c in ("dataset", "part", "setting", "method", "eps", "d", "factor", "b_hat", "k", "eps_prime", "smooth", "measure", "run")}
    return pd.DataFrame([row | {"w2": w2, "sw1": sliced_wasserstein(truth, mass, d, angles=16), "mae": errors["mae"], "kl": errors["kl"], "iterations": steps}])


def sweep(truth: DataFrame, settings: list[dict], runs: int = RUNS) -> DataFrame:
    """One row of measures per part, setting and run."""
    spark = truth.sparkSession
    params = spark.createDataFrame(pd.DataFrame(settings), "setting int, method string, eps double, d int, factor double, b_hat int, k int, eps_prime double, smooth boolean, measure string")
    numbered = params.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    work = truth.join(F.broadcast(numbered), "d")  # settings x runs rows, whatever the data
    # as many tasks as settings and runs: groups differ by far in cost, and those that share a task wait for each other
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism * 4, len(settings) * runs)
    return work.repartition(tasks, "dataset", "part", "setting", "run").groupBy("dataset", "part", "setting", "run").applyInPandas(lambda pdf: evaluate(pdf), RESULT)


def aggregate_runs(results: DataFrame) -> DataFrame:
    """Mean of a part's runs first, then of the parts; the standard error is over all of them."""
    keys = ["dataset", "method", "eps", "d", "factor", "b_hat", "k", "eps_prime", "smooth", "measure"]
    by_part = results.groupBy(*keys, "part").agg(F.avg("w2").alias("w2"), F.avg("sw1").alias("sw1"), F.avg("mae").alias("mae"), F.avg("kl").alias("kl"), F.avg("iterations").alias("iterations"), F.stddev_samp("w2").alias("spread"), F.count("*").alias("runs"))
    return by_part.groupBy(*keys).agg(*[F.avg(c).alias(c) for c in ("w2", "sw1", "mae", "kl", "iterations")], (F.sqrt(F.sum(F.coalesce(F.col("spread") * F.col("spread") / F.col("runs"), F.lit(0.0)))) / F.count("*")).alias("w2_se"), F.sum("runs").alias("runs"), F.count("*").alias("parts"))


def study(spark, sf_dir: str, name: str, settings: list[dict], runs: int = RUNS, by_part: bool = True) -> DataFrame:
    points = POINT_SETS[name].read(spark, sf_dir)
    truth = truth_counts(points, name, tuple(s["d"] for s in settings), by_part)
    return aggregate_runs(sweep(truth, settings, runs))


#: Point set -> whether it is cut into parts.
STUDIED = {"crime_like": True, "taxi_like": True, "normal_gen": False, "szipf_gen": False, "mnormal_gen": False}


#: Panels: the radius, small and large sides, small and large budgets, and small budgets with growing subsets. Matching waits until one is asked for.
PANELS = {
    "sweep_b": lambda: settings_for(("disk",), (15,), (3.5,), FACTORS, smooth=BOTH, measure="sinkhorn"),
    "sweep_d": lambda: settings_for(ALL_METHODS, SIDES_SMALL, smooth=BOTH),
    "sweep_d_large": lambda: settings_for(("disk", "subset"), SIDES_LARGE, (5.0,), smooth=BOTH, measure="sinkhorn"),
    "sweep_eps": lambda: settings_for(ALL_METHODS, (5,), EPS_SMALL, k_rule="one", smooth=BOTH),
    "sweep_eps_growth": lambda: settings_for(("disk", "subset"), (5,), EPS_SMALL, smooth=BOTH),
    "sweep_eps_large": lambda: settings_for(("disk", "subset"), (15,), EPS_LARGE, smooth=BOTH, measure="sinkhorn"),
}


def run_panel(spark, sf_dir: str, panel: str, name: str, runs: int = RUNS) -> DataFrame:
    return study(spark, sf_dir, name, PANELS[panel](), runs, STUDIED[name])


for _name in STUDIED:
    for _panel in PANELS:
        query(f"{_panel}_{_name}")(lambda spark, sf, p=_panel, n=_name: run_panel(spark, sf, p, n))


def _parts_sql(name: str, d: int) -> str:
    """Cell counts of each square, by range joins with its cells."""
    squares = ", ".join(f"('{part}', {x0!r}, {y0!r}, {w!r}, {h!r})" for part, (x0, y0, w, h) in SQUARE_PARTS[name].items())
    return f"SELECT '{name}' AS dataset, q.part, CAST({d} AS INTEGER) AS d, CAST(floor((x - x0) * {d} / w) AS INTEGER) AS cx, CAST(floor((y - y0) * {d} / h) AS INTEGER) AS cy, count(*) AS n FROM ({POINT_SETS[name].sql}) p JOIN (SELECT part, CAST(x0 AS DOUBLE) AS x0, CAST(y0 AS DOUBLE) AS y0, CAST(w AS DOUBLE) AS w, CAST(h AS DOUBLE) AS h FROM (VALUES {squares}) v(part, x0, y0, w, h)) q ON x >= x0 AND x < x0 + w AND y >= y0 AND y < y0 + h GROUP BY ALL"


@query("study_truth", " UNION ALL ".join(_parts_sql(n, d) for n in SQUARE_PARTS for d in (3, 5)))
def study_truth(spark, sf):
    """What every study starts from: the true counts of the square parts."""
    out = None
    for name in SQUARE_PARTS:
        counts = truth_counts(POINT_SETS[name].read(spark, sf), name, (3, 5))
        out = counts if out is None else out.unionByName(counts)
    return out


@query("study_by_reports")
def study_by_reports(spark, sf):
    """A panel run user by user: every run draws, counts and inverts real reports, beside the multinomial draws of the other studies."""
    grid, runs, budgets = POINT_SETS["taxi_like"].grid(5), 3, (1.4, 3.5)
    cells = assign_cells(POINT_SETS["taxi_like"].read(spark, sf), grid).select("user_id", "cx", "cy")
    counted = None
    for eps in budgets:
        for run in range(runs):
            counts = count_reports(DiskMechanism(eps, grid).report(cells, "hash", seed=1000 + run, unsafe_deterministic=True))
            counts = counts.select(F.lit(eps).alias("eps"), F.lit(run).alias("run"), "ox", "oy", "n")
            counted = counts if counted is None else counted.unionByName(counts)
    truth = np.zeros(25)
    for r in cells.groupBy("cx", "cy").count().collect():
        truth[r.cy * 5 + r.cx] = r["count"]

    def measure(key, pdf):
        mech = DiskMechanism(key[0], GridSpec(0.0, 0.0, 1.0, 1.0, 5))
        mass = invert_counts(mech, dict(zip(zip(pdf.ox, pdf.oy, strict=True), pdf.n, strict=True)), 1000, 1e-8).mass
        drawn, _ = simulate("disk", truth.astype(np.int64), 5, key[0], mech.b_hat, 0, 0.0, np.random.default_rng([7, int(key[1])]))
        w2 = [wasserstein_exact(truth, x, 5) for x in (mass, drawn)]
        return pd.DataFrame([{"eps": key[0], "run": key[1], "reports": int(pdf.n.sum()), "w2_reports": w2[0], "w2_multinomial": w2[1]}])

    return counted.groupBy("eps", "run").applyInPandas(measure, "eps double, run int, reports long, w2_reports double, w2_multinomial double")


@query("full_domain")
def full_domain(spark, sf):
    """No parts: the whole rectangles of the two table-born sets, with both anchors."""
    settings = settings_for((*ALL_METHODS, "exact", "uniform"), smooth=BOTH)
    return study(spark, sf, "crime_like", settings, RUNS, False).unionByName(study(spark, sf, "taxi_like", settings, RUNS, False))


@query("min_radius_ablation")
def min_radius_ablation(spark, sf):
    """A least radius of one against the plain floor, where the floor gives zero."""
    plain = study(spark, sf, "normal_gen", settings_for(("disk", "decay"), (4, 5), (5.0, 7.0)), RUNS, False)
    return plain.unionByName(study(spark, sf, "normal_gen", settings_for(("disk", "decay"), (4, 5), (5.0, 7.0), min_radius=1), RUNS, False))


@query("road_like_comparison")
def road_like_comparison(spark, sf):
    """Strongly correlated axes: area mechanisms against the per-axis one."""
    return study(spark, sf, "road_like", settings_for(ALL_METHODS, (5,), (3.5, 5.0), smooth=BOTH), RUNS, False)


@query("volume_comparison")
def volume_comparison(spark, sf):
    return study(spark, sf, "taxi_big", settings_for(ALL_METHODS, smooth=BOTH), RUNS, True)


@query("trajectory_comparison")
def trajectory_comparison(spark, sf):
    """Distances of the disk and both trajectory stand-ins from the truth. Each user spends one budget: on one point for the disk."""
    from veilgrid.domain import true_histogram
    from veilgrid.estimate import estimate_from_reports
    from veilgrid.mechanisms.trajectory import chosen_points, markov_estimate, pivot_estimate, trajectories
    from veilgrid.metrics.frames import grid_distances

    grid = POINT_SETS["crime_like"].grid(5)
    truth, paths = true_histogram(POINT_SETS["crime_like"].read(spark, sf), grid), trajectories(spark, sf, 5)
    tests = {"mode": "hash", "unsafe_deterministic": True}
    disk = DiskMechanism(3.5, grid)
    found = {"disk": estimate_from_reports(disk.report(chosen_points(paths, 1), user="event_id", **tests), disk), "markov": markov_estimate(paths, grid, 3.5, **tests), "pivot": pivot_estimate(paths, grid, 3.5, **tests)}
    out = None
    for method, estimate in found.items():
        row = grid_distances(truth, estimate, 5).withColumn("method", F.lit(method))
        out = row if out is None else out.unionByName(row)
    return out


#: Results of made-up runs, one row a method, part and run, from the orders: what averaging is checked on.
_RUNS_SQL = "SELECT 'm' || CAST(o_custkey % 3 AS VARCHAR) AS method, o_orderstatus AS part, CAST(o_orderkey % 10 AS INTEGER) AS run, avg(o_totalprice) / 100000 AS w2, avg(o_custkey) / 1000 AS sw1 FROM orders GROUP BY ALL"


@query("run_means", f"""SELECT method, round(avg(w2), 6) AS w2, round(avg(sw1), 6) AS sw1, round(sqrt(sum(spread * spread / runs)) / count(*), 6) AS w2_se, CAST(sum(runs) AS BIGINT) AS runs, count(*) AS parts
FROM (SELECT method, part, avg(w2) AS w2, avg(sw1) AS sw1, stddev_samp(w2) AS spread, count(*) AS runs FROM ({_RUNS_SQL}) GROUP BY method, part) GROUP BY method""")
def run_means(spark, sf):
    """Means of runs, then of parts, by the function that every study ends with."""
    keys = [F.concat(F.lit("m"), F.col("o_custkey") % 3).alias("method"), F.col("o_orderstatus").alias("part"), (F.col("o_orderkey") % 10).cast("int").alias("run")]
    rows = table(spark, sf, "orders").groupBy(*keys).agg((F.avg("o_totalprice") / 100000).alias("w2"), (F.avg("o_custkey") / 1000).alias("sw1"))
    fixed = {"dataset": F.lit("made"), "eps": F.lit(1.0), "d": F.lit(5), "factor": F.lit(1.0), "b_hat": F.lit(1), "k": F.lit(0), "eps_prime": F.lit(0.0), "smooth": F.lit(False), "measure": F.lit("exact"), "mae": F.lit(0.0), "kl": F.lit(0.0), "iterations": F.lit(1)}
    return aggregate_runs(rows.withColumns(fixed)).select("method", F.round("w2", 6).alias("w2"), F.round("sw1", 6).alias("sw1"), F.round("w2_se", 6).alias("w2_se"), "runs", "parts")


for _g in ("normal_gen", "szipf_gen", "mnormal_gen"):
    query(f"generate_{_g}", f"SELECT user_id, round(x, 6) + 0 AS x, round(y, 6) + 0 AS y FROM ({POINT_SETS[_g].sql})")(lambda spark, sf, g=_g: POINT_SETS[g].read(spark, sf).select("user_id", (F.round("x", 6) + 0).alias("x"), (F.round("y", 6) + 0).alias("y")))
