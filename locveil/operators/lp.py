"""The two linear-programming baselines, solved by a primal-dual interior-point method.

All ratio constraints of a geo-indistinguishable kernel tie entries of one reported
column; columns meet only in the row sums (and, for the joint programme, in one
bound on the adversary's error).  The Newton system is therefore one small block per
column plus a Schur complement of n (+1) rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


def greedy_spanner(d: np.ndarray, stretch: float) -> list[tuple[int, int]]:
    """Edges, shortest first, kept where the graph so far is longer than stretch times the edge."""
    n = len(d)
    if stretch <= 1:
        return [(i, j) for i in range(n) for j in range(i + 1, n)]
    path = np.where(np.eye(n, dtype=bool), 0.0, np.inf)
    kept = []
    i, j = np.triu_indices(n, 1)
    for e in np.argsort(d[i, j], kind="stable"):
        a, b = int(i[e]), int(j[e])
        if path[a, b] > stretch * d[a, b] + 1e-12:
            kept.append((a, b))
            via = np.minimum(path[:, [a]] + d[a, b] + path[[b], :], path[:, [b]] + d[a, b] + path[[a], :])
            path = np.minimum(path, via)
    return kept


#: Added to the unit diagonal of a column's Newton block.
REGULAR = 1e-13
#: Least product of a slack and its dual, as a share of their mean.
CENTRAL = 1e-4
#: Solves of each Newton system; all but the first refine it.
REFINED = 3
#: Share of the uniform kernel mixed into the solution.
LIFT = 1e-9


@dataclass
class Solution:
    kernel: np.ndarray
    loss: float
    gap: float
    residual: float
    steps: int
    #: solved; infeasible (no kernel has that error); unsolved (the steps ended before the tolerances held)
    status: str = "solved"


def _rows(d: np.ndarray, eps_g: float, edges: list[tuple[int, int]]) -> np.ndarray:
    """One row for each direction of an edge: k_i exp(-a) - k_i' <= 0 with a = eps_g d."""
    n = len(d)
    g = np.zeros((2 * len(edges), n))
    for r, (a, b) in enumerate(edges):
        c = np.exp(-eps_g * d[a, b])
        g[2 * r, a], g[2 * r, b] = c, -1.0
        g[2 * r + 1, b], g[2 * r + 1, a] = c, -1.0
    return g


def solve(p: np.ndarray, d: np.ndarray, eps_g: float, delta: float = 0.05, d_min: float | None = None, tol: float = 1e-9, max_steps: int = 80) -> Solution:
    """Least expected loss under geo-indistinguishability; with d_min also a least expected inference error.

    delta > 0 replaces all pairs by a (1 + delta)-spanner with the budget divided by
    1 + delta, which implies the constraint for every pair.  The kernel is only one to
    use where the status is "solved"; no kernel has a larger error than the best guess
    without any report, so that a larger d_min is infeasible.
    """
    n = len(p)
    if d_min is not None and d_min > (d @ p).min() + 1e-12:
        return Solution(np.full((n, n), np.nan), np.nan, np.nan, np.nan, 0, "infeasible")
    edges = greedy_spanner(d, 1 + delta)
    g = _rows(d, eps_g / (1 + delta), edges)
    joint = d_min is not None
    width = n + joint
    if joint:  # t_j <= sum_i p_i k_ij d(guess, i) for every guess
        g = np.hstack([g, np.zeros((len(g), 1))])
        g = np.vstack([g, np.hstack([-d * p[None, :], np.ones((n, 1))])])
    cost = np.zeros((n, width))
    cost[:, :n] = (p[:, None] * d).T
    tie = np.eye(width)[:n] if not joint else np.eye(width)
    goal = np.ones(width)
    if joint:
        goal[n] = d_min
    v = np.full((n, width), 1.0 / n)
    if joint:
        v[:, n] = 0.5 * (d @ p).min() / n
    s = np.maximum(-(v @ g.T), 1e-3 / n)
    start = cost[:, :n].mean() / n
    z = start / s  # on the central path as far as products go
    y = np.zeros(width)
    over = 1.0  # slack of the error bound, and its dual
    dual_over = start / over
    m = s.size + joint
    steps = 0
    gap = residual = np.inf
    first = None
    for steps in range(1, max_steps + 1):
        r_dual = cost + z @ g + y @ tie
        r_rows = v @ g.T + s
        r_tie = v.sum(0) @ tie.T - goal
        if joint:
            r_tie[n] -= over
            r_over = -y[n] - dual_over  # stationarity of the slack
        gap = (float((s * z).sum()) + joint * over * dual_over) / m
        residual = max(np.abs(r_dual).max(), np.abs(r_rows).max(), np.abs(r_tie).max(), abs(r_over) if joint else 0.0)
        if gap < tol and residual < 1e-6:
            break
        w = z / s
        h = np.einsum("jm,ma,mb->jab", w, g, g, optimize=True) if len(g) < 64 else np.stack([g.T @ (w[j][:, None] * g) for j in range(n)])
        # Entries of a column span many magnitudes: invert with a unit diagonal.
        unit = 1 / np.sqrt(np.einsum("jaa->ja", h))
        inv = np.linalg.inv(h * unit[:, :, None] * unit[:, None, :] + REGULAR * np.eye(width)) * unit[:, :, None] * unit[:, None, :]
        schur = inv.sum(0)
        if joint:
            schur[n, n] += over / dual_over

        def step(target: float, corr: np.ndarray | float = 0.0, corr_over: float = 0.0):
            rc = (target - corr) / s - z  # dz = rc - w ds, ds = -r_rows - G dv
            rhs = -(r_dual + (rc + w * r_rows) @ g)
            right = -r_tie
            if joint:
                rc_over = (target - corr_over) / over - dual_over
                # dz_over = rc_over - (z/over) d_over and -dy - dz_over = -r_over
                right[n] += (over / dual_over) * (rc_over - r_over)
            dv, dy = np.zeros_like(v), np.zeros(width)
            for _ in range(REFINED):  # h dv + dy = rhs, sum dv - (over / dual) dy_n = right
                off, off_tie = rhs - np.einsum("jab,jb->ja", h, dv) - dy, right - dv.sum(0)
                if joint:
                    off_tie[n] += (over / dual_over) * dy[n]
                base = np.einsum("jab,jb->ja", inv, off)
                more = np.linalg.solve(schur, base.sum(0) - off_tie)
                dv, dy = dv + base - np.einsum("jab,b->ja", inv, more), dy + more
            ds = -r_rows - dv @ g.T
            dz = rc - w * ds
            if not joint:
                return dv, ds, dz, dy, 0.0, 0.0
            dz_over = r_over - dy[n]
            d_over = (rc_over - dz_over) * over / dual_over
            return dv, ds, dz, dy, d_over, dz_over

        def longest(x, dx) -> float:
            neg = dx < 0
            return min(1.0, float((-x[neg] / dx[neg]).min())) if neg.any() else 1.0

        def scalar(x: float, dx: float) -> float:
            return min(1.0, -x / dx) if dx < 0 else 1.0

        dv, ds, dz, dy, do, dzo = step(0.0)
        ap = min(longest(s, ds), scalar(over, do))
        ad = min(longest(z, dz), scalar(dual_over, dzo))
        ahead = (float(((s + ap * ds) * (z + ad * dz)).sum()) + joint * (over + ap * do) * (dual_over + ad * dzo)) / m
        sigma = min(1.0, max(ahead / gap, 1e-6)) ** 3
        first = first or (gap, residual)
        if residual / first[1] > 10 * gap / first[0]:  # complementarity must not run ahead of feasibility
            sigma = max(sigma, 0.5)
        dv, ds, dz, dy, do, dzo = step(sigma * gap, ds * dz, do * dzo)
        ap = 0.995 * min(longest(s, ds), scalar(over, do))
        ad = 0.995 * min(longest(z, dz), scalar(dual_over, dzo))
        for _ in range(30):  # stay near the central path
            ahead = (s + ap * ds) * (z + ad * dz)
            if ahead.min() >= CENTRAL * (float(ahead.sum()) + joint * (over + ap * do) * (dual_over + ad * dzo)) / m:
                break
            ap, ad = 0.8 * ap, 0.8 * ad
        v, s, z, y = v + ap * dv, s + ap * ds, z + ad * dz, y + ad * dy
        if joint:
            over, dual_over = over + ap * do, dual_over + ad * dzo
    k = np.maximum(v[:, :n].T, 0)
    k /= k.sum(1, keepdims=True)
    k = (1 - LIFT) * k + LIFT / n  # equal rows satisfy every ratio, so round-off near zero no longer shows
    done = gap < tol and residual < 1e-6
    return Solution(k, float((p[:, None] * k * d).sum()), gap * m, residual, steps, "solved" if done else "unsolved")


def exp_err(k: np.ndarray, p: np.ndarray, d: np.ndarray) -> float:
    return float((d @ (p[:, None] * k)).min(0).sum())


def least_eps_g(p: np.ndarray, d: np.ndarray, target: float, delta: float = 0.05, tol: float = 0.005, max_steps: int = 40) -> float | None:
    """The least eps_g whose geo-indistinguishable optimum errs by no more than the target (within tol); None where none does.

    The error falls with eps_g.  A programme that also asks for the target error has
    the same optimum up to this eps_g, as its bound is slack there, and meets the
    target at every larger one: so it is the least for both.
    """
    aim = target + 0.75 * tol  # accepted from half the tolerance on

    def off(x: float) -> float:
        return exp_err(solve(p, d, float(np.exp(x)), delta).kernel, p, d) - aim

    if target > (d @ p).min() + tol:
        return None
    lo, hi = np.log(0.02), np.log(2.0)
    f_lo, f_hi = off(lo), off(hi)
    while f_lo < 0 and lo > np.log(1e-5):
        lo, hi, f_hi = lo - np.log(8), lo, f_lo
        f_lo = off(lo)
    while f_hi > 0 and hi < np.log(1e3):
        lo, f_lo, hi = hi, f_hi, hi + np.log(4)
        f_hi = off(hi)
    if f_lo < 0:  # the target is the largest error there is, within the tolerance
        return float(np.exp(lo))
    if f_hi > 0:
        return None
    kept = 0
    x = hi
    for _ in range(max_steps):  # false position; an end that stays twice counts half
        x = (lo * f_hi - hi * f_lo) / (f_hi - f_lo)
        f = off(x)
        if abs(f) <= 0.25 * tol:
            break
        if f > 0:
            lo, f_lo = x, f
            f_hi, kept = (f_hi / 2 if kept == 1 else f_hi), 1
        else:
            hi, f_hi = x, f
            f_lo, kept = (f_lo / 2 if kept == -1 else f_lo), -1
    return float(np.exp(x))


def tuned(p: np.ndarray, d: np.ndarray, target: float, delta: float = 0.05, d_min: float | None = None, tol: float = 0.005, eps_g: float | None = None) -> tuple[Solution, float]:
    """The programme at the least eps_g that meets the target error (a smaller eps_g protects more).

    Where none meets it the status says so: infeasible.
    """
    eps_g = eps_g or least_eps_g(p, d, target, delta, tol)
    if eps_g is None:
        n = len(p)
        return Solution(np.full((n, n), np.nan), np.nan, np.nan, np.nan, 0, "infeasible"), np.nan
    return solve(p, d, eps_g, delta, d_min), eps_g
