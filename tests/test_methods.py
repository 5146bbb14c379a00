"""Reporting, inversion, distances and privacy measures."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F
from veilgrid.domain import GridSpec, assign_cells, distance_set, input_cells, true_histogram
from veilgrid.em import clip_normalise, em, em_fft, em_stencil, invert_linear, project_simplex
from veilgrid.estimate import count_reports, estimate_axes, estimate_by, estimate_distribution, invert_counts
from veilgrid.mechanisms import AxisWaveMechanism, CategoricalOracle, DecayMechanism, DiskMechanism, SquareWave, SubsetExponentialMechanism
from veilgrid.mechanisms import area
from veilgrid.metrics import transport as T
from veilgrid.plans.experiments import simulate
from veilgrid.privacy import distance_loss, local_privacy, local_privacy_subset, match_privacy, privacy_loss

HASH = {"mode": "hash", "unsafe_deterministic": True}


def unit(d):
    return GridSpec(0.0, 0.0, 1.0, 1.0, d)


def uniform_points(spark, n):
    return spark.range(n).select(F.col("id").alias("user_id"), F.rand(1).alias("x"), F.rand(2).alias("y")).cache()


# ---- cells ----

def test_cells_edges_and_outside(spark):
    rows = [(0, 0.0, 0.0), (1, 1.0, 1.0), (2, 0.2, 0.2), (3, -0.1, 0.5), (4, 1.5, 0.5), (5, float("nan"), 0.5), (6, None, 0.5), (7, 0.19999, 0.99999)]
    p = spark.createDataFrame(rows, "user_id int, x double, y double")
    kept = {r.user_id: (r.cx, r.cy) for r in assign_cells(p, unit(5)).collect()}
    assert kept == {0: (0, 0), 1: (4, 4), 2: (1, 1), 7: (0, 4)}
    clamped = {r.user_id: (r.cx, r.cy) for r in assign_cells(p, unit(5), out_of_domain="clamp").collect()}
    assert clamped[3] == (0, 2) and clamped[4] == (4, 2) and 5 not in clamped and 6 not in clamped
    with pytest.raises(Exception, match="outside the domain"):
        assign_cells(p, unit(5), out_of_domain="error").collect()
    with pytest.raises(ValueError):
        assign_cells(p, unit(5), out_of_domain="guess")


def test_histogram_has_all_cells_and_sums_to_one(spark):
    h = true_histogram(uniform_points(spark, 500), unit(7)).collect()
    assert len(h) == 49 and sum(r.mass for r in h) == pytest.approx(1)
    empty = true_histogram(uniform_points(spark, 500).limit(0), unit(3)).collect()
    assert len(empty) == 9 and all(r.mass == 0 for r in empty)


def test_grid_from_data(spark):
    g = GridSpec.from_data(spark.createDataFrame([(1.0, 2.0), (3.0, 8.0), (float("nan"), 1.0)], "x double, y double"), 4)
    assert (g.x0, g.y0, g.width, g.height, g.n) == (1.0, 1.0, 2.0, 7.0, 16)


@pytest.mark.parametrize("b", [1.0, 1.5, 2.5, 3.0])
def test_distance_set(spark, b):
    cells = input_cells(spark, unit(9))
    found = {tuple(r) for r in distance_set(cells.select(F.col("cx").alias("ox"), F.col("cy").alias("oy")), cells, b).collect()}
    side = range(9)
    assert found == {(x, y, u, v) for x in side for y in side for u in side for v in side if (x - u) ** 2 + (y - v) ** 2 <= b * b}


# ---- reports ----

@pytest.mark.parametrize("mech", [DiskMechanism(3.5, unit(6), 1), DiskMechanism(1.0, unit(5), 3), DiskMechanism(2.0, unit(5), 2, shrink=False), DecayMechanism(2.0, unit(5), 3), DecayMechanism(3.0, unit(4), 2, profile="center"), DiskMechanism(7.0, unit(4), 0), DiskMechanism(0.0, unit(3), 1)])
@pytest.mark.parametrize("vectorised", [False, True])
def test_sampler_law_is_the_channel(spark, mech, vectorised, monkeypatch):
    """Evenly spaced draws reproduce a channel row exactly up to the spacing."""
    n = 40_000
    draws = spark.range(n).select(((F.col("id") + 0.5) / n).alias("u"), F.lit(1).alias("cx"), F.lit(2).alias("cy"))
    if vectorised:
        monkeypatch.setattr(area, "MAX_EXPRESSION_CELLS", 0)
    got = {(r.ox, r.oy): r.n / n for r in count_reports(mech.report_with(draws, F.col("u"))).collect()}
    row = mech.channel_matrix()[2 * mech.grid.d + 1]
    assert set(got) <= set(mech.output_list)
    assert max(abs(got.get(c, 0) - p) for c, p in zip(mech.output_list, row, strict=True)) < 3 / n * 3


def test_modes(spark):
    cells = assign_cells(uniform_points(spark, 3000), unit(5))
    mech = DiskMechanism(3.5, unit(5))
    with pytest.raises(ValueError, match="replayed"):
        mech.report(cells, "hash")
    a, b = (sorted(map(tuple, mech.report(x, keep=("user_id",), **HASH).collect())) for x in (cells, cells.repartition(7)))
    assert a == b
    for mode in ("secure", "rand"):
        rows = mech.report(cells, mode, keep=("user_id",)).collect()
        assert len(rows) == 3000 and {(r.ox, r.oy) for r in rows} <= set(mech.output_list)
    with pytest.raises(ValueError):
        mech.report(cells, "other")


def test_continuous_reports(spark):
    p = spark.range(60_000).select(F.col("id").alias("user_id"), F.lit(0.3).alias("x"), F.lit(0.6).alias("y"))
    b = 0.25
    for kind in (DiskMechanism, DecayMechanism):
        out = kind.report_continuous(p, 2.0, b, **HASH).select("rx", "ry").toPandas().to_numpy()
        outside = np.hypot(out[:, 0] - out[:, 0].clip(0, 1), out[:, 1] - out[:, 1].clip(0, 1))
        assert outside.max() <= b + 1e-9
        near = (np.hypot(out[:, 0] - 0.3, out[:, 1] - 0.6) <= b).mean()
        q = __import__("veilgrid.geometry", fromlist=["x"]).continuous_constants("disk" if kind is DiskMechanism else "decay", b, 2.0)[1]
        assert near == pytest.approx(1 - (4 * b + 1) * q, abs=0.01)
        far = out[np.hypot(out[:, 0] - 0.3, out[:, 1] - 0.6) > b]
        inner = ((far >= 0) & (far <= 1)).all(axis=1).mean()
        assert inner == pytest.approx((1 - math.pi * b * b) / (1 + 4 * b), abs=0.02)


def test_plan_has_one_exchange_and_pushed_filter(spark, sf):
    from veilgrid.sources.datasets import POINT_SETS

    points = POINT_SETS["taxi_like"].read(spark, sf)
    plan = count_reports(DiskMechanism(3.5, unit(5)).report(assign_cells(points, POINT_SETS["taxi_like"].grid(5)), **HASH))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Python" not in plan and "PushedFilters: [IsNotNull(o_totalprice)" in plan
    assert "o_orderpriority" not in plan


# ---- inversion ----

def test_em_steps():
    c = np.array([[0.7, 0.3], [0.3, 0.7]])
    assert em(np.array([60.0, 40.0]), c, 1, -1).mass == pytest.approx([0.54, 0.46])
    assert em(np.array([60.0, 40.0]), c, 20, -1).mass == pytest.approx([0.73815584, 0.26184416], abs=1e-8)
    assert em(np.zeros(2), c).mass == pytest.approx([0.5, 0.5])


def test_em_likelihood_rises_and_noiseless_counts_are_recovered():
    mech = DiskMechanism(3.5, unit(4), 1)
    f = np.random.default_rng(1).dirichlet(np.ones(16))
    counts = 1e6 * f @ mech.channel_matrix()
    fits = [em(counts, mech.channel_matrix(), k, -1) for k in (1, 5, 50)]
    assert fits[0].log_likelihood < fits[1].log_likelihood < fits[2].log_likelihood
    assert np.abs(em(counts, mech.channel_matrix(), 20_000, 1e-15).mass - f).max() < 1e-3
    assert np.abs(invert_linear(counts, mech.channel_matrix()) - f).max() < 1e-9


@pytest.mark.parametrize("smooth", [False, True])
def test_three_inversions_agree(smooth):
    mech = DecayMechanism(2.0, unit(9), 3)
    rng = np.random.default_rng(0)
    counts = dict(zip(mech.output_list, rng.integers(0, 50, mech.outputs).tolist(), strict=True))
    dense, stencil, fft = (invert_counts(mech, counts, 40, -1, smooth, m).mass for m in ("dense", "stencil", "fft"))
    assert np.allclose(dense, stencil, atol=1e-12) and np.allclose(dense, fft, atol=1e-9) and dense.sum() == pytest.approx(1)


def test_simplex_projection():
    v = np.array([0.6, 0.7, -0.4])
    p = project_simplex(v)
    assert p.sum() == pytest.approx(1) and (p >= 0).all() and p == pytest.approx([0.45, 0.55, 0])
    assert clip_normalise(np.array([-1.0, 0.5, 0.5])) == pytest.approx([0, 0.5, 0.5]) and clip_normalise(np.array([-1.0, -2.0])) == pytest.approx([0.5, 0.5])


def test_estimates_end_to_end(spark):
    p = spark.range(20_000).select(F.col("id").alias("user_id"), (0.1 + 0.2 * F.rand(3)).alias("x"), (0.7 + 0.2 * F.rand(4)).alias("y"), (F.col("id") % 2).cast("string").alias("part"))
    grid = unit(5)
    truth = {(r.cx, r.cy): r.mass for r in true_histogram(p, grid).collect()}
    for mech in (DiskMechanism(5.0, grid), DecayMechanism(5.0, grid), DiskMechanism(3.5, grid, shrink=False)):
        got = {(r.cx, r.cy): r.mass for r in estimate_distribution(p, grid, mech, **HASH).collect()}
        assert sum(got.values()) == pytest.approx(1) and sum(abs(got[c] - truth[c]) for c in truth) < 0.25
    by = estimate_by(p, grid, DiskMechanism(5.0, grid), ("part",), **HASH).groupBy("part").agg(F.sum("mass").alias("m"), F.count("*").alias("n")).collect()
    assert len(by) == 2 and all(r.m == pytest.approx(1) and r.n == 25 for r in by)
    for mech in (AxisWaveMechanism(5.0, grid), AxisWaveMechanism(5.0, grid, merge="joint"), AxisWaveMechanism(5.0, grid, budget="sample")):
        got = {(r.cx, r.cy): r.mass for r in estimate_axes(p, grid, mech, **HASH).collect()}
        assert sum(got.values()) == pytest.approx(1) and sum(abs(got[c] - truth[c]) for c in truth) < 0.4
    with pytest.raises(ValueError):
        AxisWaveMechanism(1.0, grid, "sample", "joint")


def test_square_wave():
    for eps in (0.5, 1.75, 4.0):
        w = SquareWave(eps, 8)
        c = w.channel_matrix()
        assert np.allclose(c.sum(axis=1), 1) and c.max() / c.min() <= math.exp(eps) * (1 + 1e-9)


@pytest.mark.parametrize("kind", ["grr", "sue", "oue", "olh", "subset"])
def test_oracles_are_unbiased_enough(spark, kind):
    p = spark.range(12_000).select(F.col("id").alias("user_id"), F.when(F.col("id") % 3 > 0, 0.1).otherwise(0.9).alias("x"), F.lit(0.5).alias("y"))
    o = CategoricalOracle(kind, 2.0, unit(3))
    rows = {(r.cx, r.cy): r.mass for r in o.estimate(o.support(o.report(assign_cells(p, unit(3)), **HASH)), 12_000).collect()}
    assert abs(rows[0, 1] - 2 / 3) < 0.06 and abs(rows[2, 1] - 1 / 3) < 0.06 and abs(rows[1, 1]) < 0.06


def test_oracle_random_bits(spark):
    p = uniform_points(spark, 500)
    for kind in ("oue", "sue"):
        assert CategoricalOracle(kind, 1.0, unit(3)).report(assign_cells(p, unit(3))).count() == 500


# ---- subset mechanism ----

@pytest.mark.parametrize("k", [1, 2, 3])
@pytest.mark.parametrize("score", ["nearest", "sum"])
def test_subset_law_by_enumeration(k, score):
    mech = SubsetExponentialMechanism(1.3, unit(3), k, score)
    sets = mech.all_sets()
    prob = mech.set_probabilities(sets)
    assert np.allclose(prob.sum(axis=1), 1)
    assert distance_loss(prob, mech.distances) <= 1.3 + 1e-9
    rng = np.random.default_rng(0)
    got = mech.sample(np.full(60_000, 4), rng)
    index = {tuple(s): j for j, s in enumerate(sets)}
    freq = np.bincount([index[tuple(s)] for s in got], minlength=len(sets)) / len(got)
    assert np.abs(freq - prob[4]).max() < 0.01
    if score == "nearest":
        assert np.allclose(mech.rank_law.sum(axis=1), 1)


def test_subset_reports(spark):
    mech = SubsetExponentialMechanism(2.0, unit(4), 2)
    rows = mech.count(mech.report(assign_cells(uniform_points(spark, 800), unit(4)), seed=1)).collect()
    assert sum(r.n for r in rows) == 800 and all(len(r.members) == 2 and r.members[0] < r.members[1] for r in rows)


# ---- distances ----

def test_transport_basics():
    rng = np.random.default_rng(0)
    a, b, c = rng.dirichlet(np.ones(25), 3)
    w = lambda x, y: T.wasserstein_exact(x, y, 5)
    assert w(a, a) == pytest.approx(0, abs=1e-6) and w(a, b) == pytest.approx(w(b, a)) and w(a, c) <= w(a, b) + w(b, c) + 1e-9
    point = lambda k: np.eye(25)[k]
    assert w(point(0), point(3)) == pytest.approx(3) and w(point(0), point(24)) == pytest.approx(math.hypot(4, 4))
    assert T.wasserstein_exact(point(0), point(3), 5, unit="domain") == pytest.approx(0.6)
    assert w(a, b) == pytest.approx(T.wasserstein_sinkhorn(a, b, 5, tol=1e-9), abs=1e-3)
    assert T.wasserstein_sinkhorn(point(0), point(3), 5) == pytest.approx(3, abs=1e-6)


def test_exact_transport_against_enumeration():
    """Equal masses on n cells: the best of all permutations."""
    from itertools import permutations

    rng = np.random.default_rng(2)
    for _ in range(5):
        x, y = rng.choice(25, 5, replace=False), rng.choice(25, 5, replace=False)
        cost = T.grid_cost(5)
        best = min(sum(cost[i, j] for i, j in zip(x, p, strict=True)) for p in permutations(y)) / 5
        a, b = np.zeros(25), np.zeros(25)
        a[x], b[y] = 0.2, 0.2
        assert T.transport_cost(a, b, cost) == pytest.approx(best)


def test_line_distances_match_transport():
    rng = np.random.default_rng(4)
    a, b = rng.dirichlet(np.ones(6), 2)
    t = np.arange(6.0)
    for p in (1, 2):
        assert T.wasserstein_line(t, a, b, p) == pytest.approx(T.transport_cost(a, b, np.abs(t[:, None] - t[None]) ** p))


def test_frames_match_arrays(spark):
    from veilgrid.metrics import frames

    rng = np.random.default_rng(5)
    a, b = rng.dirichlet(np.ones(16), 2)
    to = lambda m: spark.createDataFrame([(k % 4, k // 4, float(m[k])) for k in range(16)], "cx int, cy int, mass double")
    assert frames.sliced_wasserstein(to(a), to(b), 32).first()[0] == pytest.approx(T.sliced_wasserstein(a, b, 4, angles=32))
    row = frames.grid_distances(to(a), to(b), 4).first()
    assert row.w2 == pytest.approx(T.wasserstein_exact(a, b, 4)) and row.mae == pytest.approx(np.abs(a - b).mean())


@pytest.mark.parametrize(("v", "theta"), [((0, 0, 3, 1), 0.3), ((0, 0, 2, 5), 2.0), ((5, 0, 0, 0), 4.0)])
def test_report_separation_slope(v, theta):
    """Along any direction two report laws differ by the shift times one minus the background's mass, for every area mechanism."""
    slopes = []
    for mech in (DiskMechanism(2.0, unit(6), 2), DecayMechanism(2.0, unit(6), 2)):
        c, out = mech.channel_matrix(), np.array(mech.output_list)
        t = np.round(out[:, 0] * math.cos(theta) + out[:, 1] * math.sin(theta), 12)
        o = np.argsort(t)
        got = T.wasserstein_line(t[o], c[v[1] * 6 + v[0]][o], c[v[3] * 6 + v[2]][o])
        shift = abs((v[2] - v[0]) * math.cos(theta) + (v[3] - v[1]) * math.sin(theta))
        assert got == pytest.approx(shift * (1 - mech.outputs * mech.q), abs=1e-9)
        slopes.append(got)
    assert slopes[0] >= slopes[1]


# ---- privacy ----

@pytest.mark.parametrize(("eps", "lp"), [(0.7, 2.516), (1.4, 2.405), (2.1, 2.192), (2.8, 1.903), (3.5, 1.582), (5.0, 0.685)])
def test_local_privacy_of_the_disk(eps, lp):
    c = DiskMechanism(eps, unit(5)).channel_matrix()
    distances = SubsetExponentialMechanism(1.0, unit(5)).distances
    assert local_privacy(c, distances) == pytest.approx(lp, abs=6e-4) and privacy_loss(c) <= eps + 1e-9
    matched = match_privacy(local_privacy(c, distances), unit(5))
    assert local_privacy_subset(SubsetExponentialMechanism(matched, unit(5)))[0] == pytest.approx(local_privacy(c, distances), abs=1e-6)


def test_matching_limits_and_monotony():
    values = [local_privacy_subset(SubsetExponentialMechanism(e, unit(5), 2))[0] for e in (0.0, 1.0, 3.0, 9.0, 60.0)]
    assert values == sorted(values, reverse=True) and values[0] == pytest.approx(2.548, abs=1e-3) and values[-1] == pytest.approx(1.328, abs=2e-3)
    with pytest.raises(ValueError, match="smaller k"):
        match_privacy(1.0, unit(5), 2)
    with pytest.raises(ValueError, match="above"):
        match_privacy(3.0, unit(5))
    sampled = local_privacy_subset(SubsetExponentialMechanism(2.0, unit(5), 12), samples=6000)
    assert sampled[1] > 0 and 0 < sampled[0] < 3


def test_tallied_sets_follow_the_law_and_invert_as_the_dense_channel_does():
    for d, k in ((3, 3), (4, 2), (3, 9)):
        mech = SubsetExponentialMechanism(1.3, unit(d), k)
        sets = mech.all_sets().astype(np.int64)
        assert sorted(mech.numbers_of(sets)) == list(range(len(sets)))
        assert np.array_equal(mech.members_of(mech.numbers_of(sets)), sets)
        counts = np.zeros(d * d, dtype=np.int64)
        counts[[0, d + 1]] = 200_000, 100_000
        numbers, times = mech.tally(counts, np.random.default_rng(3))
        assert times.sum() == 300_000 and len(set(numbers)) == len(numbers)
        law = (counts @ mech.set_probabilities(mech.members_of(numbers))) / counts.sum()
        assert np.abs(times / times.sum() - law).max() < 5 * np.sqrt(law.max() / 300_000)
        for smooth in (False, True):
            want = em(times.astype(float), mech.set_probabilities(mech.members_of(numbers)), 40, -1.0, smooth)
            got = mech.invert_tally(numbers, times, 40, -1.0, smooth)
            assert np.allclose(got.mass, want.mass, atol=1e-10) and got.log_likelihood == pytest.approx(want.log_likelihood)
    wide = SubsetExponentialMechanism(1.3, unit(7), 8)  # too many sets for a place each
    numbers, times = wide.tally(np.full(49, 100), np.random.default_rng(3))
    assert times.sum() == 4900 and (np.diff(numbers) > 0).all() and len(set(map(tuple, wide.members_of(numbers)))) == len(numbers)


def test_memory_of_a_run_with_large_subsets_does_not_follow_the_users():
    import tracemalloc

    counts = np.full(25, 16_000)
    tracemalloc.start()
    mass, _ = simulate("subset", counts, 5, 0.7, 1, 12, 1.6, np.random.default_rng(1), max_iter=3)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert mass.sum() == pytest.approx(1) and peak < 200e6


# ---- studies ----

def test_multinomial_counts_have_the_reports_law():
    counts = np.array([4000, 0, 1000, 5000])
    mass, _ = simulate("disk", counts, 2, 6.0, 0, 0, 0.0, np.random.default_rng(1))
    assert np.abs(mass - counts / counts.sum()).max() < 0.05
    for method in ("exact", "uniform", "axis", "decay", "disk_noshrink"):
        assert simulate(method, counts, 2, 3.0, 1, 0, 0.0, np.random.default_rng(1))[0].sum() == pytest.approx(1)
    for k in (1, 2):
        assert simulate("subset", counts, 2, 3.0, 1, k, 2.0, np.random.default_rng(1))[0].sum() == pytest.approx(1)


def test_disk_beats_per_axis_on_correlated_points_and_distance_falls_with_budget(spark):
    from veilgrid.plans.experiments import settings_for, study

    rows = study(spark, "/root/testdata/sf0.01", "normal_gen", settings_for(("disk", "axis"), (5,), (2.1, 5.0)), 5, False).collect()
    w = {(r.method, r.eps): r.w2 for r in rows}
    assert w["disk", 2.1] < w["axis", 2.1] and w["disk", 5.0] < w["axis", 5.0] and w["disk", 5.0] < w["disk", 2.1]


# ---- draws ----

@pytest.mark.parametrize("mech", [DiskMechanism(3.5, unit(5), 1), DiskMechanism(1.0, unit(4), 3), DiskMechanism(2.0, unit(5), 2, shrink=False), DiskMechanism(7.0, unit(3), 0)])
def test_area_sampler_has_the_same_law(spark, mech):
    from veilgrid.operators.sampling import report_by_areas

    side = 300
    draws = spark.range(side * side).select(((F.floor(F.col("id") / side) + 0.5) / side).alias("u"), ((F.col("id") % side + 0.5) / side).alias("v"), F.lit(2).alias("cx"), F.lit(0).alias("cy"))
    got = {(r.ox, r.oy): r.n / side**2 for r in count_reports(report_by_areas(draws, mech, F.col("u"), F.col("v"))).collect()}
    row = mech.channel_matrix()[2]
    assert set(got) <= set(mech.output_list)
    assert max(abs(got.get(c, 0) - p) for c, p in zip(mech.output_list, row, strict=True)) < 4 / side


def test_weighted_draws(spark):
    from veilgrid.operators.sampling import alias_table, draw_from, draw_large

    weights = [1.0, 0.0, 2.0, 5.0, 0.5]
    keep, other = alias_table(weights)
    law = np.zeros(5)
    for k in range(5):
        law[k] += keep[k] / 5
        law[other[k]] += (1 - keep[k]) / 5
    assert law == pytest.approx(np.array(weights) / 8.5)
    n = 20_000
    df = spark.range(n).select(((F.col("id") + 0.5) / n).alias("u"))
    for column in (draw_from(weights, F.col("u")), draw_large(np.array(weights), F.col("u"))):
        counts = {r[0]: r[1] / n for r in df.groupBy(column).count().collect()}
        assert all(abs(counts.get(k, 0) - w / 8.5) < 1e-3 for k, w in enumerate(weights))
    with pytest.raises(ValueError):
        draw_from([0.0, -1.0], F.col("u"))


def test_smoothing_keeps_mass_and_gives_the_distance_a_minimum_near_the_best_radius(spark):
    from veilgrid.em import smooth_mass
    from veilgrid.plans.experiments import FACTORS, settings_for, study

    f = np.random.default_rng(1).dirichlet(np.ones(12))
    assert smooth_mass(f, (3, 4)).sum() == pytest.approx(1) and smooth_mass(np.full(9, 1 / 9), (3, 3)) == pytest.approx(np.full(9, 1 / 9))
    assert smooth_mass(np.array([1.0, 0, 0, 0]), (4,)) == pytest.approx([0.75, 0.25, 0, 0])
    rows = study(spark, "/root/testdata/sf0.01", "normal_gen", settings_for(("disk",), (15,), (3.5,), FACTORS, smooth=(True,)), 5, False).collect()
    w = {r.b_hat: r.w2 for r in rows}
    assert min(w, key=w.get) in (2, 3, 4) and w[1] > min(w.values()) and w[5] > min(w.values())


def test_relational_forms_agree_with_arrays(spark):
    from veilgrid.em import em_frame, em_stencil_frame

    mech = DiskMechanism(3.0, unit(4), 1)
    rng = np.random.default_rng(0)
    n = rng.integers(0, 40, mech.outputs)
    counts = spark.createDataFrame([(x, y, int(k)) for (x, y), k in zip(mech.output_list, n, strict=True) if k], "ox int, oy int, n long")
    want = em(n.astype(float), mech.channel_matrix(), 3, -1).mass
    frame = em_frame(counts, mech.channel(spark), 16, 3)
    stencil = em_stencil_frame(counts, input_cells(spark, unit(4)), mech.excess_frame(spark), mech.q, 3, checkpoint_every=2)
    for got in (frame, stencil):
        rows = {(r.cx, r.cy): r.mass for r in got.collect()}
        assert [rows[k % 4, k // 4] for k in range(16)] == pytest.approx(want, abs=1e-9)


def test_range_extraction_takes_the_whole_table(spark, tmp_path):
    from veilgrid.plans.catalog import QUERIES

    spark.range(20_000).select(F.col("id").alias("event_id"), F.lit("2024-01-11 12:00:00").cast("timestamp").alias("ts"), (F.col("id") % 80 + 0.25).alias("value")).write.parquet(f"{tmp_path}/events.parquet")
    rows = QUERIES["range_extraction"](spark, str(tmp_path)).collect()
    assert sum(r.n for r in rows) == 10_000 and {r.part for r in rows} == {"B"}


def test_null_safe_join_takes_all_orders(spark, tmp_path):
    from veilgrid.plans.catalog import QUERIES

    spark.range(900).select(F.col("id").alias("o_orderkey"), F.element_at(F.array(F.lit("F"), F.lit("O"), F.lit("P")), (F.col("id") % 3 + 1).cast("int")).alias("o_orderstatus"), F.lit(1.0).alias("o_totalprice")).write.parquet(f"{tmp_path}/orders.parquet")
    assert {r.part: r.pairs for r in QUERIES["op_join_null_safe"](spark, str(tmp_path)).collect()} == {"F": 300, "O": 300, None: 300}
