"""DuckDB SQL of the methods, written from their definitions: channels are listed cell by cell and draws are found by ranges."""

from __future__ import annotations

import math

from veilgrid.sources.datasets import POINT_SETS, uniform_sql


def num(x: float) -> str:
    return f"CAST({x!r} AS DOUBLE)"


def in_grid(name: str) -> str:
    x0, y0, w, h = POINT_SETS[name].domain
    return f"x >= {num(x0)} AND x <= {num(x0 + w)} AND y >= {num(y0)} AND y <= {num(y0 + h)}"


def cells(name: str, d: int, extra: str = "") -> str:
    """(user_id, part, cx, cy) of the points inside the domain."""
    x0, y0, w, h = POINT_SETS[name].domain
    axis = lambda c, o, s: f"CAST(least(floor(({c} - {num(o)}) * {num(float(d))} / {num(s)}), {d - 1}) AS INTEGER)"
    return f"SELECT user_id, part, {axis('x', x0, w)} AS cx, {axis('y', y0, h)} AS cy{extra} FROM ({POINT_SETS[name].sql}) WHERE {in_grid(name)}"


def grid_cells(d: int) -> str:
    return f"SELECT CAST(a.range AS INTEGER) AS cx, CAST(b.range AS INTEGER) AS cy FROM range({d}) a, range({d}) b"


def share(x: str, y: str, b: str) -> str:
    big, small = f"greatest(abs({x}), abs({y}))", f"least(abs({x}), abs({y}))"
    r = f"sqrt(CAST({x} * {x} + {y} * {y} AS DOUBLE))"
    return f"least(1, greatest(0, 4 * ({big} * {b} / {r} - {big} + 0.5) * ({small} * {b} / {r} - {small} + 0.5)))"


def crossed(x: str, y: str, b: str) -> str:
    return f"(greatest(0, 2 * abs({x}) - 1) * greatest(0, 2 * abs({x}) - 1) + greatest(0, 2 * abs({y}) - 1) * greatest(0, 2 * abs({y}) - 1) < 4 * {b} * {b})"


def stencil(b: int, shrink: bool = True) -> str:
    """(dx, dy, kind, s)."""
    if b == 0:
        return "SELECT 0 AS dx, 0 AS dy, 'pure' AS kind, CAST(1 AS DOUBLE) AS s"
    border = f"CAST({share('dx', 'dy', str(b))} AS DOUBLE)" if shrink else "CAST(0 AS DOUBLE)"
    return f"""SELECT dx, dy, CASE WHEN dx * dx + dy * dy <= {b * b} THEN 'pure' ELSE 'border' END AS kind, CASE WHEN dx * dx + dy * dy <= {b * b} THEN CAST(1 AS DOUBLE) ELSE {border} END AS s
FROM (SELECT CAST(a.range AS INTEGER) AS dx, CAST(c.range AS INTEGER) AS dy FROM range({-b - 1}, {b + 2}) a, range({-b - 1}, {b + 2}) c) WHERE {crossed('dx', 'dy', str(b))}"""


def disk_weights(b: int, eps: float, shrink: bool = True) -> str:
    return f"SELECT dx, dy, 1 + s * (exp({num(eps)}) - 1) AS w FROM ({stencil(b, shrink)})"


def ring_weights(b: int, eps: float) -> str:
    """Ring number is the ceiling of the distance (one at the centre); a cell crossed by its ring's inner circle mixes."""
    ring = f"exp({num(eps)} * (1 - (j - 1) / CAST({b} AS DOUBLE)))"
    inner = f"exp({num(eps)} * (1 - (j - 2) / CAST({b} AS DOUBLE)))"
    return f"""SELECT dx, dy, CASE WHEN j > 1 AND {crossed('dx', 'dy', '(j - 1)')} THEN {share('dx', 'dy', '(j - 1)')} * greatest(1, {inner}) + (1 - {share('dx', 'dy', '(j - 1)')}) * greatest(1, {ring}) ELSE greatest(1, {ring}) END AS w
FROM (SELECT dx, dy, CAST(greatest(1, ceil(round(sqrt(CAST(dx * dx + dy * dy AS DOUBLE)), 9))) AS INTEGER) AS j FROM ({stencil(b)}))"""


def center_weights(b: int, eps: float) -> str:
    return f"SELECT dx, dy, greatest(1, exp({num(eps)} * (1 - sqrt(CAST(dx * dx + dy * dy AS DOUBLE)) / {b}))) AS w FROM ({stencil(b)})"


def outputs(d: int, b: int) -> str:
    return f"SELECT DISTINCT cx + dx AS ox, cy + dy AS oy FROM ({grid_cells(d)}), ({stencil(b)})"


def channel(d: int, b: int, weights: str) -> str:
    """(cx, cy, ox, oy, prob): each input cell's weights over all output cells, normalised."""
    return f"""SELECT cx, cy, ox, oy, w / sum(w) OVER (PARTITION BY cx, cy) AS prob FROM (SELECT c.cx, c.cy, o.ox, o.oy, coalesce(s.w, 1) AS w FROM ({grid_cells(d)}) c CROSS JOIN ({outputs(d, b)}) o LEFT JOIN ({weights}) s ON s.dx = o.ox - c.cx AND s.dy = o.oy - c.cy)"""


def reports(name: str, d: int, b: int, weights: str, user_cells: str | None = None) -> str:
    """(user_id, part, ox, oy) from hash uniforms: places in row order first, then displacements by falling weight."""
    return f"""SELECT p.user_id, p.part, CASE WHEN t < m THEN o.ox ELSE p.cx + s.dx END AS ox, CASE WHEN t < m THEN o.oy ELSE p.cy + s.dy END AS oy
FROM (SELECT c.*, {uniform_sql('user_id', 0)} * (k.m + k.total) AS t, k.m FROM ({user_cells or cells(name, d)}) c, (SELECT (SELECT count(*) FROM ({outputs(d, b)})) AS m, (SELECT coalesce(sum(w - 1), 0) FROM ({weights})) AS total) k) p
LEFT JOIN (SELECT ox, oy, row_number() OVER (ORDER BY oy, ox) - 1 AS at FROM ({outputs(d, b)})) o ON p.t < p.m AND o.at = floor(p.t)
LEFT JOIN (SELECT dx, dy, sum(w - 1) OVER (ORDER BY round(w, 10) DESC, dy, dx) - (w - 1) AS lo, sum(w - 1) OVER (ORDER BY round(w, 10) DESC, dy, dx) AS hi FROM ({weights}) WHERE w > 1) s ON p.t >= p.m AND p.t - p.m >= s.lo AND p.t - p.m < s.hi"""


def em_steps(channel_sql: str, counts_sql: str, n: int, steps: int, cell: str = "cx, cy", out: str = "ox, oy") -> str:
    """A recursive statement: each step weighs the joint rows, sums per output by a window, and sums per input. Gives (cell, mass)."""
    cj = " AND ".join(f"m.{c.strip()} = f.{c.strip()}" for c in cell.split(","))
    oj = " AND ".join(f"m.{c.strip()} = k.{c.strip()}" for c in out.split(","))
    mc = ", ".join(f"m.{c.strip()}" for c in cell.split(","))
    mo = ", ".join(f"m.{c.strip()}" for c in out.split(","))
    return f"""WITH RECURSIVE m AS MATERIALIZED (SELECT * FROM ({channel_sql})), k AS MATERIALIZED (SELECT * FROM ({counts_sql})), total AS (SELECT CAST(sum(n) AS DOUBLE) AS total FROM k),
f AS (SELECT 0 AS step, {cell}, CAST(1 AS DOUBLE) / {n} AS mass FROM (SELECT DISTINCT {cell} FROM m)
UNION ALL SELECT step + 1, {cell}, CAST(sum(part * n / predicted) / any_value(total) AS DOUBLE) FROM (SELECT step, {mc}, f.mass * m.prob AS part, k.n, sum(f.mass * m.prob) OVER (PARTITION BY {mo}) AS predicted, total.total FROM f JOIN m ON {cj} JOIN k ON {oj}, total WHERE step < {steps}) GROUP BY step, {cell})
SELECT {cell}, mass FROM f WHERE step = {steps}"""


def radius(eps: str, side: str = "1") -> str:
    m1, m2 = f"(exp({eps}) - 1 - {eps})", f"(1 - exp({eps}) + {eps} * exp({eps}))"
    return f"((2 * {m2} + sqrt(4 * {m2} * {m2} + pi() * exp({eps}) * {m1} * {m2})) / (pi() * exp({eps}) * {m1}) * {side})"


def wave_axis(cell: str, u: str, d: int, b: int, eps: float) -> str:
    total = d + 2 * b + (2 * b + 1) * math.expm1(eps)
    t = f"({u} * {num(total)})"
    return f"CAST(CASE WHEN {t} < {d + 2 * b} THEN floor({t}) - {b} ELSE {cell} - {b} + least(floor(({t} - {d + 2 * b}) / {num(math.expm1(eps))}), {2 * b}) END AS INTEGER)"
