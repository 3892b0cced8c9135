"""Array mathematics of one domain, for use inside grouped functions.

A domain has n cells (n is bounded by tiling): x, y, prior mass p and budgets eps.
Everything here is a pure function of arrays sorted by cell_id.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Guards comparisons of sums that differ only by rounding.
TINY = 1e-12


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    dx, dy = x[:, None] - x[None, :], y[:, None] - y[None, :]
    return np.sqrt(dx * dx + dy * dy)


def anchor_outer(members: np.ndarray, p: np.ndarray, d: np.ndarray) -> float:
    """Least prior-weighted mean distance from the members to one guess anywhere."""
    return float((d[:, members] @ p[members]).min() / p[members].sum())


def anchor_inner(members: np.ndarray, p: np.ndarray, d: np.ndarray) -> float:
    """The same with the guess among the members."""
    return float((d[np.ix_(members, members)] @ p[members]).min() / p[members].sum())


def reach(members: np.ndarray, d: np.ndarray) -> float:
    return float(d[np.ix_(members, members)].max())


@dataclass
class Segments:
    """Every run a..b of a curve: anchor errors, mass, reach and least budget, as matrices [a, b]."""

    mass: np.ndarray
    outer: np.ndarray
    inner: np.ndarray
    reach: np.ndarray
    eps: np.ndarray


def segment_table(order: np.ndarray, p: np.ndarray, d: np.ndarray, eps: np.ndarray) -> Segments:
    n = len(order)
    d, p, eps = d[np.ix_(order, order)], p[order], eps[order]
    mass, outer, inner, wide, least = (np.full((n, n), np.nan) for _ in range(5))
    for a in range(n):
        cost = np.cumsum(d[:, a:] * p[a:], axis=1)  # guess by end
        total = np.cumsum(p[a:])
        mass[a, a:] = total
        outer[a, a:] = cost.min(0) / total
        low = np.where(np.arange(n)[:, None] <= np.arange(a, n)[None, :], cost, np.inf)
        inner[a, a:] = low[a:].min(0) / total
        least[a, a:] = np.minimum.accumulate(eps[a:])
        grown = np.array([d[b, a : b + 1].max() for b in range(a, n)])
        wide[a, a:] = np.maximum.accumulate(grown)
    return Segments(mass, outer, inner, wide, least)


def curve_walk(seg: Segments, d: np.ndarray, e_min: float, kind: str = "outer") -> list[tuple[int, int]] | None:
    """Cut a curve into runs that meet the floor, working inward from both ends; None if even the whole cannot.

    ``d`` is in curve order.  The two open runs are [la, lb] and [ra, rb]; of two
    finished runs the wider goes out first, so that far-off cells get their zone early.
    """
    n = len(d)
    err = seg.outer if kind == "outer" else seg.inner

    def good(a: int, b: int) -> bool:
        return b > a and err[a, b] >= np.exp(seg.eps[a, b]) * e_min - TINY

    if n < 2 or not good(0, n - 1):
        return None
    if n < 4:
        return [(0, n - 1)]
    la, lb, ra, rb = 0, 1, n - 2, n - 1
    left: list[tuple[int, int]] = []
    right: list[tuple[int, int]] = []
    last: list[str] = []
    while True:
        while not good(la, lb) and lb + 1 < ra:
            lb += 1
        while not good(ra, rb) and ra - 1 > lb:
            ra -= 1
        gap = ra - lb - 1
        if gap < 2:
            break
        if seg.reach[la, lb] >= seg.reach[ra, rb]:
            left.append((la, lb))
            last.append("left")
            la, lb = lb + 1, lb + 2
        else:
            right.append((ra, rb))
            last.append("right")
            ra, rb = ra - 2, ra - 1
    if gap == 1:
        c = lb + 1
        if d[c, la : lb + 1].min() <= d[c, ra : rb + 1].min():
            lb = c
        else:
            ra = c
    if good(la, lb) and good(ra, rb):
        return sorted([*left, (la, lb), (ra, rb), *right])
    ua, ub = la, rb
    while not good(ua, ub):
        before, after = (left[-1] if left else None), (right[-1] if right else None)
        best = None
        for cut in range(ua - 1, ub + 1):  # cells up to cut go left
            if (before is None and cut >= ua) or (after is None and cut < ub):
                continue
            parts = []
            if before is not None:
                parts.append((before[0], cut))
            if after is not None:
                parts.append((cut + 1, after[1]))
            if all(good(*s) for s in parts):
                score = sum(seg.mass[s] * seg.reach[s] for s in parts) / sum(seg.mass[s] for s in parts)
                if best is None or score < best[0] - TINY:
                    best = (score, parts)
        if best is not None:
            if before is not None:
                left.pop()
            if after is not None:
                right.pop()
            return sorted([*left, *best[1], *right])
        if last.pop() == "left":
            ua = left.pop()[0]
        else:
            ub = right.pop()[1]
    return sorted([*left, (ua, ub), *right])


def best_contiguous(seg: Segments, e_min: float) -> list[tuple[int, int]] | None:
    """Runs of least mass-weighted reach among all ways to cut the curve (dynamic programme)."""
    n = len(seg.mass)
    ok = seg.outer >= np.exp(seg.eps) * e_min - TINY
    cost, back = np.full(n + 1, np.inf), np.full(n + 1, -1)
    cost[0] = 0.0
    for b in range(1, n):
        for a in range(b):
            if ok[a, b] and cost[a] + seg.mass[a, b] * seg.reach[a, b] < cost[b + 1] - TINY:
                cost[b + 1], back[b + 1] = cost[a] + seg.mass[a, b] * seg.reach[a, b], a
    if not np.isfinite(cost[n]):
        return None
    out, b = [], n
    while b > 0:
        out.append((int(back[b]), b - 1))
        b = int(back[b])
    return out[::-1]


def average_reach(zones: list[np.ndarray], p: np.ndarray, d: np.ndarray) -> float:
    return float(sum(p[z].sum() * reach(z, d) for z in zones) / sum(p[z].sum() for z in zones))


def kernel(scale: np.ndarray, d: np.ndarray) -> np.ndarray:
    """Rows proportional to exp(-scale_i d(i, j)); scale is eps / (2 reach)."""
    w = np.exp(-scale[:, None] * d)
    return w / w.sum(1, keepdims=True)


def zonal_scale(zone: np.ndarray, eps: np.ndarray, d: np.ndarray) -> np.ndarray:
    """eps_zone / (2 reach) of each cell's zone, with the least budget of the zone."""
    out = np.empty(len(zone))
    for z in np.unique(zone):
        at = np.flatnonzero(zone == z)
        out[at] = eps[at].min() / (2 * reach(at, d))
    return out


def guesses(k: np.ndarray, p: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per report: the optimal guess, its cost (joint with the report) and the most probable cell; ties to the lower cell."""
    joint = p[:, None] * k
    cost = np.round(d @ joint, 12)
    best = cost.argmin(0)
    return best, (d @ joint)[best, np.arange(len(p))], np.round(joint, 14).argmax(0)


def measures(k: np.ndarray, p: np.ndarray, d: np.ndarray) -> dict[str, np.ndarray | float]:
    """ExpErr, QLoss, worst conditional error, and per cell AvgErr, success probability and loss."""
    opt, cost, likely = guesses(k, p, d)
    evidence = p @ k
    n = len(p)
    loss = (k * d).sum(1)
    return {
        "exp_err": float(cost.sum()), "q_loss": float(p @ loss), "min_exper": float((cost / evidence).min()),
        "avg_err": (k * d[:, opt]).sum(1), "success": (k * (likely[None, :] == np.arange(n)[:, None])).sum(1), "loss": loss,
    }


def uniforms(*key: int | str, size: int) -> np.ndarray:
    """Repeatable uniforms from a key, the same on any executor."""
    import hashlib

    seed = int.from_bytes(hashlib.md5(":".join(map(str, key)).encode()).digest()[:8], "little")
    return np.random.default_rng(seed).random(size)


def quasi_k_means(k: int, restart: int, p: np.ndarray, xy: np.ndarray, d: np.ndarray, eps: np.ndarray, e_min: float, max_iter: int = 20, tol: float = 1e-6, min_size: int = 2, lam: float | None = None, linkage: str = "centre", seed: int = 0) -> tuple[float, np.ndarray] | None:
    """One restart for k zones: (average reach, zone of each cell) of the best feasible round, or None.

    lam turns on the budget weight on distances; linkage measures a cell's distance
    to a zone's centre or to its nearest member.
    """
    n = len(p)
    u = uniforms("qkm", seed, k, restart, size=k)
    centres = [min(int(u[0] * n), n - 1)]
    for j in range(1, k):
        near = d[:, centres].min(1)
        near[centres] = 0
        total = near.cumsum()
        if total[-1] <= 0:
            return None
        centres.append(int(min(np.searchsorted(total, u[j] * total[-1], "right"), n - 1)))
    mu = xy[centres].astype(float)
    best: tuple[float, np.ndarray] | None = None
    for _ in range(max_iter):
        zone = _fill(k, p, xy, d, eps, e_min, mu, min_size, lam, linkage)
        fit = zone is not None and (zone >= 0).all()
        if zone is None:
            break
        members = [np.flatnonzero(zone == j) for j in range(k)]
        if fit and all(len(m) >= min_size and anchor_outer(m, p, d) >= np.exp(eps[m].min()) * e_min - TINY for m in members):
            score = average_reach(members, p, d)
            if best is None or score < best[0] - TINY:
                best = (score, zone.copy())
        fresh = np.array([xy[m].mean(0) if len(m) else mu[j] for j, m in enumerate(members)])
        moved = np.abs(fresh - mu).max()
        mu = fresh
        if moved < tol:
            break
    return best


def _fill(k, p, xy, d, eps, e_min, mu, min_size, lam, linkage) -> np.ndarray:
    n = len(p)
    base = np.sqrt(((xy[:, None, :] - mu[None, :, :]) ** 2).sum(2))
    zone = np.full(n, -1)
    cost, mass, least, size = np.zeros((k, n)), np.zeros(k), np.full(k, np.inf), np.zeros(k, int)
    closed = np.zeros(k, bool)

    def weight(j: int) -> np.ndarray | float:
        if lam is None:
            return 1.0
        if not np.isfinite(least[j]):
            return lam
        return 1 + lam - np.minimum(eps, least[j]) / np.maximum(eps, least[j])

    far = np.stack([base[:, j] * weight(j) for j in range(k)], 1)

    def good(j: int, add: int | None = None) -> bool:
        c, m, e, s = cost[j], mass[j], least[j], size[j]
        if add is not None:
            c, m, e, s = c + p[add] * d[:, add], m + p[add], min(e, eps[add]), s + 1
        return s >= min_size and c.min() / m >= np.exp(e) * e_min - TINY

    def join(i: int, j: int) -> None:
        zone[i] = j
        cost[j] += p[i] * d[:, i]
        mass[j] += p[i]
        size[j] += 1
        fresh = eps[i] < least[j]
        least[j] = min(least[j], eps[i])
        if linkage == "member":
            base[:, j] = d[:, zone == j].min(1)
        if linkage == "member" or (fresh and lam is not None):
            far[:, j] = base[:, j] * weight(j)

    while not closed.all() and (zone < 0).any():
        view = np.where((zone < 0)[:, None] & ~closed[None, :], far, np.inf)
        i, j = np.unravel_index(np.argmin(view), view.shape)
        join(int(i), int(j))
        closed[j] = good(int(j))
    if closed.all():
        rest = np.flatnonzero(zone < 0)
        for i in rest[np.argsort(far[rest].min(1), kind="stable")]:
            for j in np.argsort(far[i], kind="stable"):
                if good(int(j), int(i)):
                    join(int(i), int(j))
                    break
    return zone


def choose_zoning(p, xy, d, eps, e_min, max_samp: int = 20, patience: int = 0, **how) -> np.ndarray | None:
    """Raise k while the best average reach doesn't grow; the last good k's zoning. None if one zone is too few."""
    everyone = np.arange(len(p))
    if len(p) < 2 or anchor_outer(everyone, p, d) < np.exp(eps.min()) * e_min - TINY:
        return None
    kept, score, misses = np.zeros(len(p), int), reach(everyone, d), 0
    for k in range(2, len(p) // max(2, how.get("min_size", 2)) + 1):
        found = [r for r in (quasi_k_means(k, s, p, xy, d, eps, e_min, **how) for s in range(max_samp)) if r]
        best = min(found, key=lambda r: r[0]) if found else None
        if best is None or best[0] > score + TINY:
            misses += 1
            if misses > patience:
                break
        else:
            score, kept, misses = best[0], best[1], 0
    return kept


def set_partitions(n: int, min_size: int = 2):
    """All partitions of 0..n-1 into blocks of at least min_size (n small)."""

    def grow(i: int, blocks: list[list[int]]):
        if i == n:
            if all(len(b) >= min_size for b in blocks):
                yield [list(b) for b in blocks]
            return
        for b in blocks:
            b.append(i)
            yield from grow(i + 1, blocks)
            b.pop()
        blocks.append([i])
        yield from grow(i + 1, blocks)
        blocks.pop()

    yield from grow(0, [])


def best_zoning(p, d, eps, e_min) -> list[list[int]] | None:
    """Least average reach among all zonings that meet the floor."""
    best = None
    for blocks in set_partitions(len(p)):
        parts = [np.array(b) for b in blocks]
        if all(anchor_outer(b, p, d) >= np.exp(eps[b].min()) * e_min - TINY for b in parts):
            score = average_reach(parts, p, d)
            if best is None or score < best[0] - TINY:
                best = (score, blocks)
    return best and best[1]
