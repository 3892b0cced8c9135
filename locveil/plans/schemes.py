"""The compared schemes under one identifier each, evaluated for whole parameter grids in one plan."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import core, geometry, lp

#: Values of k without a better clustering before the experiments' search ends; 0 is the plain stop rule.
PATIENCE = 0

MEASURES = "domain_id string, scheme string, eps_param double, e_min double, measure string, cell_id long, value double"


@dataclass(frozen=True)
class Scheme:
    """How a scheme zones, which budget it takes, and which kernel it builds."""

    zoning: str  # curve, qkm, adaptive, adaptive_outer, none
    budget: str = "common"  # common, cell (each zone's least), least (the domain's least for all)
    kernel: str = "zonal"  # zonal, tuned, max_reach, common_reach, geo_lp, joint_lp, identity
    lam: float | None = None
    base: str = "curve"  # zoning whose error or reach the kernel is matched to


SCHEMES = {
    "zonal_curve": Scheme("curve"),
    "zonal_qkm": Scheme("qkm"),
    "unified_curve": Scheme("curve", "least"),
    "unified_qkm": Scheme("qkm", "least"),
    "personal_curve": Scheme("curve", "cell"),
    "personal_qkm_general": Scheme("qkm", "cell"),
    "personal_qkm": Scheme("qkm", "cell", lam=0.5),
    "em_tuned": Scheme("none", kernel="tuned"),
    "em_maxreach": Scheme("none", kernel="max_reach"),
    "geo_lp": Scheme("none", kernel="geo_lp"),
    "joint_lp": Scheme("none", kernel="joint_lp"),
    "joint_lp_qkm": Scheme("none", kernel="joint_lp", base="qkm"),
    "adaptive": Scheme("adaptive"),
    "adaptive_outer": Scheme("adaptive_outer"),
    "common_reach": Scheme("adaptive_outer", kernel="common_reach"),
    "none": Scheme("none", kernel="identity"),
}


@dataclass
class Domain:
    """One domain's arrays: curve ranks of four rotations come as columns."""

    p: np.ndarray
    xy: np.ndarray
    d: np.ndarray
    eps: np.ndarray
    ranks: list[np.ndarray]


def curve_zones(dom: Domain, eps: np.ndarray, e_min: float) -> np.ndarray | None:
    """Best of the rotations by average reach."""
    best = None
    for rank in dom.ranks:
        at = np.argsort(rank)
        runs = core.curve_walk(core.segment_table(at, dom.p, dom.d, eps), dom.d[np.ix_(at, at)], e_min)
        if runs is None:
            return None
        zones = [at[a : b + 1] for a, b in runs]
        score = core.average_reach(zones, dom.p, dom.d)
        if best is None or score < best[0] - core.TINY:
            zone = np.empty(len(dom.p), int)
            for z, m in enumerate(zones):
                zone[m] = z
            best = (score, zone)
    return best[1]


def zoned(dom: Domain, how: str, eps: np.ndarray, e_min: float, lam: float | None, max_samp: int, patience: int = PATIENCE) -> np.ndarray | None:
    if how == "curve":
        return curve_zones(dom, eps, e_min)
    return core.choose_zoning(dom.p, dom.xy, dom.d, eps, e_min, max_samp, patience, lam=lam)


def adaptive_reaches(dom: Domain, eps: np.ndarray, e_min: float, kind: str, search: int = 10) -> np.ndarray | None:
    """The predecessor: each cell's own run of least reach on the first curve."""
    at = np.argsort(dom.ranks[0])
    seg = core.segment_table(at, dom.p, dom.d, eps)
    err = seg.inner if kind == "inner" else seg.outer
    n = len(at)
    out = np.full(n, np.nan)
    for r in range(n):
        wide = [seg.reach[a, b] for a in range(max(0, r - search + 1), r + 1) for b in range(max(r, a + 1), min(n, a + search)) if err[a, b] >= np.exp(seg.eps[a, b]) * e_min - core.TINY]
        if wide:
            out[at[r]] = min(wide)
    return None if np.isnan(out).any() else out


def tuned_reach(dom: Domain, eps: float, target: float, tol: float) -> float:
    """The constant reach whose expected inference error is the target: a grid first, then bisection."""
    err = lambda r: lp.exp_err(core.kernel(np.full(len(dom.p), eps / (2 * r)), dom.d), dom.p, dom.d)
    grid = np.geomspace(dom.d[dom.d > 0].min() / 50, dom.d.max() * 4, 40)
    errs = [err(r) for r in grid]
    at = min(int(np.searchsorted(np.maximum.accumulate(errs), target)), len(grid) - 1)
    lo, hi = grid[max(0, at - 1)], grid[at]
    for _ in range(40):
        mid = (lo + hi) / 2
        e = err(mid)
        if abs(e - target) <= tol / 10:
            break
        lo, hi = (mid, hi) if e < target else (lo, mid)
    return mid


def evaluate(dom: Domain, name: str, eps_param: float, e_min: float, max_samp: int, geo_eps: float | None, delta: float, tol: float, cache: dict) -> dict | None:
    """All measures of one scheme; None where the setting is infeasible."""
    s = SCHEMES[name]
    n = len(dom.p)
    common = np.full(n, eps_param) if eps_param > 0 else np.full(n, dom.eps.min())
    eps = {"common": common, "cell": dom.eps, "least": np.full(n, dom.eps.min())}[s.budget]
    extra: dict[str, float] = {}

    def reference(how: str) -> tuple[np.ndarray, float] | None:
        if how not in cache:
            zone = zoned(dom, how, common, e_min, None, max_samp)
            cache[how] = None if zone is None else (zone, lp.exp_err(core.kernel(core.zonal_scale(zone, common, dom.d), dom.d), dom.p, dom.d))
        return cache[how]

    if s.zoning in ("curve", "qkm"):
        if s.budget == "common":
            ref = reference(s.zoning)
            zone = ref and ref[0]
        else:
            zone = zoned(dom, s.zoning, eps, e_min, s.lam, max_samp)
        if zone is None:
            return None
        k = core.kernel(core.zonal_scale(zone, eps, dom.d), dom.d)
        extra = {"avg_reach": core.average_reach([np.flatnonzero(zone == z) for z in np.unique(zone)], dom.p, dom.d), "zones": float(len(np.unique(zone))), "max_reach": max(core.reach(np.flatnonzero(zone == z), dom.d) for z in np.unique(zone))}
    elif s.zoning.startswith("adaptive"):
        wide = adaptive_reaches(dom, eps, e_min, "outer" if s.zoning.endswith("outer") else "inner")
        if wide is None:
            return None
        k = core.kernel(eps / (2 * (np.full(n, wide.max()) if s.kernel == "common_reach" else wide)), dom.d)
    elif s.kernel == "identity":
        k = np.eye(n)
    else:
        ref = reference(s.base)
        if ref is None:
            return None
        zone, target = ref
        if s.kernel == "tuned":
            r = tuned_reach(dom, float(common[0]), target, tol)
            k, extra = core.kernel(np.full(n, common[0] / (2 * r)), dom.d), {"reach": r}
        elif s.kernel == "max_reach":
            r = max(core.reach(np.flatnonzero(zone == z), dom.d) for z in np.unique(zone))
            k, extra = core.kernel(np.full(n, common[0] / (2 * r)), dom.d), {"reach": r}
        else:
            d_min = target if s.kernel == "joint_lp" else None
            if geo_eps is not None:
                got, used = lp.solve(dom.p, dom.d, geo_eps, delta, d_min), geo_eps
            else:
                if ("eps_g", s.base) not in cache:  # the same for both programmes
                    cache["eps_g", s.base] = lp.least_eps_g(dom.p, dom.d, target, delta, tol)
                got, used = lp.tuned(dom.p, dom.d, target, delta, d_min, tol, cache["eps_g", s.base])
            if got.status != "solved":
                return {got.status: 1.0, "target": target}
            k, extra = got.kernel, {"eps_g": used, "gap": got.gap, "residual": got.residual}
        extra["target"] = target
    return core.measures(k, dom.p, dom.d) | extra


def run(cells: DataFrame, schemes: list[str], params: list[tuple[float, float]], max_samp: int = 20, geo_eps: float | None = None, delta: float = 0.05, tol: float = 0.005) -> DataFrame:
    """Long ``measures(domain_id, scheme, eps_param, e_min, measure, cell_id, value)`` for every scheme and parameter pair.

    ``cells`` carry prior and budgets; eps_param -1 means the cells' own budgets.
    One task holds one (domain, eps, e_min) with all its schemes, so that those
    matched to another scheme's error find it there.
    """
    ranked = geometry.rank_on_curve(cells, rots=(0, 1, 2, 3)).groupBy("domain_id", "cell_id", "x", "y", "prior", "eps").pivot("rot", [0, 1, 2, 3]).agg(F.first("rank"))
    table = cells.sparkSession.createDataFrame([(float(e), float(m)) for e, m in params], "eps_param double, e_min double")
    grid = ranked.crossJoin(F.broadcast(table))

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("cell_id").reset_index(drop=True)
        xy = pdf[["x", "y"]].to_numpy()
        dom = Domain(pdf["prior"].to_numpy(), xy, core.distances(xy[:, 0], xy[:, 1]), pdf["eps"].to_numpy(), [pdf[str(r)].to_numpy() for r in range(4)])
        e, m = float(pdf["eps_param"].iloc[0]), float(pdf["e_min"].iloc[0])
        rows, cache = [], {}
        for name in schemes:
            got = evaluate(dom, name, e, m, max_samp, geo_eps, delta, tol, cache)
            for key, value in (got or {"infeasible": 1.0}).items():
                if np.ndim(value) == 0:
                    rows.append((name, key, None, float(value)))
                else:
                    rows += [(name, key, int(c), float(v)) for c, v in zip(pdf["cell_id"], value, strict=True)]
        out = pd.DataFrame(rows, columns=["scheme", "measure", "cell_id", "value"])
        out["cell_id"] = out["cell_id"].astype("Int64")
        return out.assign(domain_id=pdf["domain_id"].iloc[0], eps_param=e, e_min=m)[["domain_id", "scheme", "eps_param", "e_min", "measure", "cell_id", "value"]]

    return grid.groupBy("domain_id", "eps_param", "e_min").applyInPandas(one, MEASURES)
