"""Stencils, areas and radius rules against brute force and fixed values."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from veilgrid import geometry as geo
from veilgrid.domain import GridSpec
from veilgrid.mechanisms import DecayMechanism, DiskMechanism


def brute_cells(b):
    """Cells whose square meets the open disk, by their nearest point."""
    out = {}
    for dx in range(-b - 2, b + 3):
        for dy in range(-b - 2, b + 3):
            near = math.hypot(max(0, abs(dx) - 0.5), max(0, abs(dy) - 0.5))
            if dx * dx + dy * dy <= b * b:
                out[dx, dy] = "pure"
            elif near < b - 1e-12:
                out[dx, dy] = "border"
    return out


@pytest.mark.parametrize("b", [*range(1, 41), 65, 100])
def test_stencil_is_the_brute_force_set(b):
    assert {(c.dx, c.dy): c.kind for c in geo.disk_stencil(b).cells} == brute_cells(b)


@pytest.mark.parametrize("b", range(1, 201))
def test_octant_formulas(b):
    pure = [(x, y) for y in range(1, b + 1) for x in range(y + 1, b + 1) if x * x + y * y <= b * b]
    assert geo.octant_pure_count(b) == len(pure)
    border = sorted((x, y) for y in range(1, b + 1) for x in range(y + 1, b + 2) if x * x + y * y > b * b and (x - 0.5) ** 2 + (y - 0.5) ** 2 < b * b)
    assert sorted(geo.octant_border(b)) == border


@pytest.mark.parametrize("b", range(0, 61))
def test_symmetry_sum_equals_stencil_sum(b):
    assert geo.octant_high_area(b) == pytest.approx(geo.disk_stencil(b).high_area, abs=1e-9)


@pytest.mark.parametrize(("b", "high"), [(1, 5.686292), (2, 16.645825), (3, 33.968538), (4, 57.169627)])
def test_high_areas(b, high):
    assert geo.disk_stencil(b).high_area == pytest.approx(high, abs=1e-6)


def test_seven_cells_radius_has_thirteen_pure_and_four_border_cells_in_an_octant():
    assert geo.octant_pure_count(7) == 13 and len(geo.octant_border(7)) == 4


def test_pythagorean_cell_on_the_circle_is_pure():
    assert {(c.dx, c.dy): c.kind for c in geo.disk_stencil(5).cells}[4, 3] == "pure" and (4, 3) not in geo.octant_border(5)


@pytest.mark.parametrize(("b", "cell"), [(3, (3, 2)), (7, (7, 3)), (8, (8, 3))])
def test_shares_never_leave_the_unit_interval(b, cell):
    assert geo.border_share(*cell, b) == 0.0
    assert all(0 <= c.share <= 1 for c in geo.disk_stencil(b).cells)


@pytest.mark.parametrize("b", range(1, 41))
@pytest.mark.parametrize("d", [1, 5, 12])
def test_output_domain(b, d):
    stencil = geo.disk_stencil(b)
    union = {(x + c.dx, y + c.dy) for x in range(d) for y in range(d) for c in stencil.cells} if b < 12 else None
    rows = {(ox, oy) for oy, lo, hi in stencil.row_spans(d) for ox in range(lo, hi + 1)}
    assert union is None or rows == union
    assert stencil.output_count(d) - len(stencil.cells) == geo.pure_low_area(d, b)


@pytest.mark.parametrize(("d", "b", "eps", "q"), [(5, 1, 3.5, 0.00431746), (15, 3, 3.5, 0.00065449), (15, 1, 5.0, 0.00088713), (20, 2, 5.0, 0.00033049)])
def test_grid_constants(d, b, eps, q):
    c = geo.grid_constants(d, b, eps)
    assert c.q == pytest.approx(q, abs=6e-9) and c.p / c.q == pytest.approx(math.exp(eps))
    assert [geo.grid_constants(5, k, eps, shrink=False).high for k in (1, 3, 4)] == [5, 29, 49]


def test_radius_limits_and_values():
    assert geo.optimal_radius(1e-9) == pytest.approx((2 + math.sqrt(4 + math.pi)) / math.pi, rel=1e-6)
    assert geo.optimal_radius(60) < 1e-6 and geo.optimal_radius(3.5, 15) == pytest.approx(15 * geo.optimal_radius(3.5))
    found = [round(geo.optimal_radius(e), 4) for e in (0.7, 1.4, 2.1, 2.8, 3.5, 5, 6, 7, 8, 9)]
    assert found == [0.9977, 0.6802, 0.4705, 0.3295, 0.2332, 0.1142, 0.0719, 0.0455, 0.0289, 0.0184]
    assert geo.optimal_radius(0.009999) == pytest.approx(geo.optimal_radius(0.010001), rel=1e-5)
    assert [geo.grid_radius(3.5, 15, f) for f in (0.33, 0.67, 1, 1.33, 1.67)] == [1, 2, 3, 4, 5]
    assert geo.grid_radius(3.5, 4) == 0 and geo.grid_radius(3.5, 4, min_radius=1) == 1
    with pytest.raises(ValueError):
        geo.optimal_radius(-1)


def bound(b, eps, side):
    ring, disk = 4 * side * b + side * side, math.pi * b * b
    high = disk * math.exp(eps)
    return math.log2((disk + ring) / (high + ring)) + high * eps * math.log2(math.e) / (high + ring)


@settings(max_examples=40, deadline=None)
@given(st.floats(0.05, 9), st.floats(0.5, 20))
def test_radius_maximises_the_bound(eps, side):
    best = geo.optimal_radius(eps, side)
    assert all(bound(best, eps, side) >= bound(best * f, eps, side) - 1e-12 for f in (0.5, 0.9, 0.99, 1.01, 1.1, 2))


def test_gradient_is_the_derivative(spark):
    from pyspark.sql import functions as F

    for eps, side, b in ((1.0, 1.0, 0.4), (3.5, 2.0, 0.3), (5.0, 15.0, 2.0)):
        got = spark.range(1).select(geo.info_gradient_col(F.lit(b), F.lit(eps), F.lit(side))).first()[0]
        h = 1e-6 * b
        assert got == pytest.approx((bound(b + h, eps, side) - bound(b - h, eps, side)) / (2 * h), rel=1e-4)


@pytest.mark.parametrize("eps", [0.7, 2.0, 3.5, 6.0])
def test_continuous_densities_integrate_to_one(eps):
    b = geo.optimal_radius(eps)
    p, q = geo.continuous_constants("disk", b, eps)
    assert math.pi * b * b * p + (4 * b + 1) * q == pytest.approx(1)
    _, q = geo.continuous_constants("decay", b, eps)
    r = np.linspace(0, b, 200_001)
    mass = np.trapezoid(q * np.exp(eps * (1 - r / b)) * 2 * np.pi * r, r)
    assert mass + (4 * b + 1) * q == pytest.approx(1, abs=1e-6)
    assert geo.continuous_constants("disk", 2 * b, eps, 2.0)[1] == pytest.approx(geo.continuous_constants("disk", b, eps)[1] / 4)


@pytest.mark.parametrize(("d", "b", "eps"), [(5, 1, 3.5), (15, 3, 3.5), (15, 1, 5.0), (5, 4, 0.7), (6, 2, 2.0), (4, 0, 7.0)])
def test_channels_are_private_and_sum_to_one(d, b, eps):
    grid = GridSpec.square(0, 0, 1, d=d)
    for mech in (DiskMechanism(eps, grid, b), DiskMechanism(eps, grid, b, shrink=False), DecayMechanism(eps, grid, b), DecayMechanism(eps, grid, b, profile="center")):
        c = mech.channel_matrix()
        assert np.allclose(c.sum(axis=1), 1, atol=1e-12)
        ratio = (c.max(axis=0) / c.min(axis=0)).max()
        assert ratio <= math.exp(eps) * (1 + 1e-9) and ratio == pytest.approx(math.exp(eps))


def test_grid_from_cell_side_rounds_up():
    assert GridSpec.square(0, 0, 10, g=3).d == 4 and GridSpec.square(0, 0, 10, g=2.5).d == 4
    with pytest.raises(ValueError):
        GridSpec.square(0, 0, 10)


def test_weights_outside_the_budget_are_refused():
    from veilgrid.mechanisms import AreaMechanism

    grid, stencil = GridSpec.square(0, 0, 1, d=4), geo.disk_stencil(1)
    ok = {(c.dx, c.dy): 1.5 for c in stencil.cells}
    assert AreaMechanism(1.0, grid, stencil, ok).q > 0
    for bad in (0.5, 3.0):
        with pytest.raises(ValueError):
            AreaMechanism(1.0, grid, stencil, ok | {(0, 0): bad})
