"""Wasserstein distances of histograms: exact transport for small grids, Sinkhorn scaling for larger ones."""

from __future__ import annotations

import numpy as np

#: Largest side whose plan (d^4 entries) is held whole.
DENSE_SIDE = 32
#: Logarithm of a factor at which it is taken into the potentials.
ABSORB = 30.0


def grid_cost(d: int, p: float = 2.0) -> np.ndarray:
    c = np.arange(d * d)
    return np.hypot((c % d)[:, None] - (c % d)[None], (c // d)[:, None] - (c // d)[None]) ** p


def transport_cost(a: np.ndarray, b: np.ndarray, cost: np.ndarray, tol: float = 1e-13) -> float:
    """Least cost of moving a to b: shortest augmenting paths with potentials over the bipartite residual graph."""
    a, b = np.asarray(a, float) / np.sum(a), np.asarray(b, float) / np.sum(b)
    rows, cols = np.flatnonzero(a > 0), np.flatnonzero(b > 0)
    cost, supply, demand = cost[np.ix_(rows, cols)].astype(float), a[rows].copy(), b[cols].copy()
    n, m = cost.shape
    flow = np.zeros((n, m))
    u, v = np.zeros(n), cost.min(axis=0)
    while supply.max() > tol and demand.max() > tol:
        reduced = np.maximum(cost - u[:, None] - v[None], 0)
        dr, dc = np.where(supply > tol, 0.0, np.inf), np.full(m, np.inf)
        from_row, from_col = np.full(m, -1), np.full(n, -1)
        done_r, done_c = np.zeros(n, bool), np.zeros(m, bool)
        target = -1
        while True:
            open_r, open_c = np.where(done_r, np.inf, dr), np.where(done_c, np.inf, dc)
            i, j = int(open_r.argmin()), int(open_c.argmin())
            if open_r[i] <= open_c[j]:
                if not np.isfinite(open_r[i]):
                    break
                done_r[i] = True
                reach = dr[i] + reduced[i]
                better = (reach < dc) & ~done_c
                dc[better], from_row[better] = reach[better], i
            else:
                done_c[j] = True
                if demand[j] > tol:
                    target = j
                    break
                back = flow[:, j] > tol
                better = back & ~done_r & (dc[j] < dr)
                dr[better], from_col[better] = dc[j], j
        if target < 0:
            break
        path, j, amount = [], target, demand[target]
        while True:
            i = int(from_row[j])
            path.append((i, j, 1))
            if from_col[i] < 0:
                amount = min(amount, supply[i])
                break
            j = int(from_col[i])
            amount = min(amount, flow[i, j])
            path.append((i, j, -1))
        for x, y, sign in path:
            flow[x, y] += sign * amount
        supply[path[-1][0]] -= amount
        demand[target] -= amount
        reach = dc[target]
        u += np.where(done_r, reach - np.minimum(dr, reach), 0)
        v -= np.where(done_c, reach - np.minimum(dc, reach), 0)
    return float((flow * cost).sum())


def wasserstein_exact(a: np.ndarray, b: np.ndarray, d: int, p: float = 2.0, unit: str = "cell") -> float:
    """W_p of two mass vectors over d x d cells (mass[cy * d + cx]); unit 'cell' or 'domain' (the side is one)."""
    w = max(0.0, transport_cost(a, b, grid_cost(d, p))) ** (1 / p)
    return w if unit == "cell" else w / d


def _soft_min(f: np.ndarray, k: np.ndarray) -> np.ndarray:
    """log sum exp of f + separable kernel over both axes."""
    for _ in range(2):
        t = k[:, :, None] + f[None]
        top = t.max(axis=1)
        safe = np.where(np.isfinite(top), top, 0)
        with np.errstate(divide="ignore"):
            f = (safe + np.log(np.exp(t - safe[:, None]).sum(axis=1))).T
    return f


def sinkhorn_cost(a: np.ndarray, b: np.ndarray, d: int, reg: float = 0.1, max_iter: int = 3000, tol: float = 1e-6, anneal: bool = False) -> float:
    """Cost of the entropic plan between two mass vectors, squared distances in cells.

    Up to DENSE_SIDE the plan is held and scaled by matrix products; larger grids use that a squared distance splits by axis. With ``anneal``
    the scaling starts from wider kernels, which takes far fewer rounds.
    """
    if d <= DENSE_SIDE:
        with np.errstate(all="ignore"):
            found = _scaled_cost(np.asarray(a, float) / np.sum(a), np.asarray(b, float) / np.sum(b), grid_cost(d), reg, max_iter, tol, anneal)
        if np.isfinite(found):
            return found  # else a factor ran over between two absorptions
    return _separable_cost(a, b, d, reg, max_iter, tol)


def _scaled_cost(a, b, cost, reg, max_iter, tol, anneal) -> float:
    """Scaling with absorption: potentials are kept in logarithms, a few rounds at a time run on plain factors beside the plan."""
    rows, cols = np.flatnonzero(a > 0), np.flatnonzero(b > 0)
    a, b, cost = a[rows], b[cols], cost[np.ix_(rows, cols)]
    g, plan = np.zeros(len(b)), None
    for width in ([reg * 64, reg * 16, reg * 4] if anneal else []) + [reg]:
        final = width == reg
        f, g, plan = _scale(a, b, cost, width, g, max_iter if final else 60, tol if final else 1e-3)
    return float((plan * cost).sum())


def _scale(a, b, cost, reg, g, max_iter, tol):
    """(f, g, plan) from potentials g, all in units of cost. A round fits the rows, then the columns."""
    k = -cost / reg
    f = np.log(a) - _log_sums(k + g[None] / reg, 1)
    g = np.log(b) - _log_sums(k + f[:, None], 0)
    plan = np.exp(k + f[:, None] + g[None])
    u, v = np.ones(len(a)), np.ones(len(b))
    for step in range(1, max_iter):
        u = a / (plan @ v)
        reached = u @ plan
        if step % 10 == 9 and np.abs(v * reached - b).sum() < tol:
            break
        v = b / reached
        if step % 20 == 19 and max(np.abs(np.log(u)).max(), np.abs(np.log(v)).max()) > ABSORB:
            f, g = f + np.log(u), g + np.log(v)
            plan = np.exp(k + f[:, None] + g[None])
            u, v = np.ones(len(a)), np.ones(len(b))
    return f * reg, (g + np.log(v)) * reg, u[:, None] * plan * v[None]


def _log_sums(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis=axis, keepdims=True))).squeeze(axis)


def _separable_cost(a, b, d, reg, max_iter, tol) -> float:
    with np.errstate(divide="ignore"):
        la, lb = np.log(np.asarray(a, float) / np.sum(a)).reshape(d, d), np.log(np.asarray(b, float) / np.sum(b)).reshape(d, d)
    i = np.arange(d)
    k = -((i[:, None] - i[None]) ** 2) / reg
    f = g = np.zeros((d, d))
    for step in range(max_iter):
        f = np.where(np.isfinite(la), la - _soft_min(g, k), -np.inf)
        column = _soft_min(f, k)
        g_new = np.where(np.isfinite(lb), lb - column, -np.inf)
        if step % 10 == 9:
            off = np.abs(np.exp(np.where(np.isfinite(g), g + column, -np.inf)) - np.exp(lb)).sum()
            if off < tol:
                break
        g = g_new
    plan_total = 0.0
    for shape in ("x", "y"):
        c = (i[:, None] - i[None]) ** 2
        with np.errstate(divide="ignore"):
            kc = k + np.log(c)
        plan_total += float(np.exp(f + _axis_pair(g, k, kc, shape)).sum())
    return plan_total


def _axis_pair(g: np.ndarray, k: np.ndarray, kc: np.ndarray, weighed: str) -> np.ndarray:
    """log sum exp over one axis with the kernel and over the other with kernel times cost."""
    first, second = (kc, k) if weighed == "y" else (k, kc)
    for kernel in (first, second):
        t = kernel[:, :, None] + g[None]
        top = t.max(axis=1)
        safe = np.where(np.isfinite(top), top, 0)
        with np.errstate(divide="ignore"):
            g = (safe + np.log(np.exp(t - safe[:, None]).sum(axis=1))).T
    return g


def wasserstein_sinkhorn(a: np.ndarray, b: np.ndarray, d: int, reg: float = 0.1, max_iter: int = 3000, tol: float = 1e-6, unit: str = "cell", debias: bool = False, anneal: bool = True) -> float:
    cost = sinkhorn_cost(a, b, d, reg, max_iter, tol, anneal)
    if debias:
        cost -= 0.5 * (sinkhorn_cost(a, a, d, reg, max_iter, tol, anneal) + sinkhorn_cost(b, b, d, reg, max_iter, tol, anneal))
    w = max(0.0, cost) ** 0.5
    return w if unit == "cell" else w / d


def wasserstein_line(t: np.ndarray, a: np.ndarray, b: np.ndarray, p: int = 1) -> float:
    """W_p^p on the line for masses a, b at sorted positions t; p = 1 by distribution functions, else by quantiles."""
    fa, fb = np.cumsum(a), np.cumsum(b)
    if p == 1:
        return float((np.abs(fa - fb)[:-1] * np.diff(t)).sum())
    cuts = np.unique(np.concatenate([[0.0], fa, fb]).clip(0, 1))
    mid = (cuts[1:] + cuts[:-1]) / 2
    x, y = (t[np.minimum(np.searchsorted(f, mid), len(t) - 1)] for f in (fa, fb))
    return float((np.abs(x - y) ** p * np.diff(cuts)).sum())


def sliced_wasserstein(a: np.ndarray, b: np.ndarray, d: int, p: int = 1, angles: int = 64, normalise: bool = False) -> float:
    """Integral over all directions of W_p^p of the projections; the mean over directions if normalised."""
    c = np.arange(d * d)
    total = 0.0
    for theta in 2 * np.pi * np.arange(angles) / angles:
        t = np.round((c % d) * np.cos(theta) + (c // d) * np.sin(theta), 12)
        order = np.argsort(t)
        total += wasserstein_line(t[order], a[order], b[order], p)
    mean = total / angles
    return mean if normalise else 2 * np.pi * mean


def pointwise_errors(a: np.ndarray, b: np.ndarray, smoothing: float = 1e-9) -> dict[str, float]:
    """Order-blind measures: L1, mean absolute error, mean squared error, variance of the error, KL of smoothed masses, Jensen-Shannon, total variation."""
    diff = a - b
    pa, pb = (a + smoothing) / (a + smoothing).sum(), (b + smoothing) / (b + smoothing).sum()
    mid = (pa + pb) / 2
    kl = lambda x, y: float((x * np.log(x / y)).sum())
    return {"l1": float(np.abs(diff).sum()), "mae": float(np.abs(diff).mean()), "mse": float((diff**2).mean()), "var": float(diff.var()), "kl": kl(pa, pb), "js": 0.5 * kl(pa, mid) + 0.5 * kl(pb, mid), "tv": 0.5 * float(np.abs(diff).sum())}
