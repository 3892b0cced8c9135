"""Array mathematics: worked examples, exact references and invariants."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from locveil.operators import core, lp


def domain(seed, n=20, span=15):
    rng = np.random.default_rng(seed)
    xy = np.unique(rng.integers(0, span, (n, 2)), axis=0) + 0.5
    p = rng.uniform(0.01, 0.03, len(xy))
    return p / p.sum(), xy, core.distances(xy[:, 0], xy[:, 1])


def test_counterexample():
    xy = np.array([(0, 120), (-50, 0), (50, 0), (0, -2.75)], float)
    d, p = core.distances(xy[:, 0], xy[:, 1]), np.full(4, 0.25)
    zone = np.arange(3)
    assert core.anchor_inner(zone, p, d) == pytest.approx(76.6667, abs=1e-3)
    assert core.anchor_outer(zone, p, d) == pytest.approx(74.3, abs=1e-2)


@pytest.mark.parametrize("p,q,d", [(0.5, 0.5, 3.0), (0.7, 0.3, 2.0)])
def test_two_cells(p, q, d):
    dist = np.array([[0, d], [d, 0]])
    assert core.anchor_outer(np.arange(2), np.array([p, q]), dist) == pytest.approx(q * d)
    k = core.kernel(core.zonal_scale(np.zeros(2, int), np.ones(2), dist), dist)
    assert k[0, 0] == pytest.approx(1 / (1 + np.exp(-0.5)))


def valid(zones, p, d, eps, e_min):
    members = np.concatenate(zones)
    assert sorted(members.tolist()) == list(range(len(p)))
    for z in zones:
        assert len(z) >= 2 and core.anchor_outer(z, p, d) >= np.exp(eps[z].min()) * e_min - 1e-9


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 10_000), st.integers(2, 24), st.floats(0.01, 1.2), st.booleans())
def test_curve_walk_is_a_valid_zoning(seed, n, e_min, personal):
    p, xy, d = domain(seed, n)
    if len(p) < 2:
        return
    eps = np.random.default_rng(seed).uniform(0.5, 1.5, len(p)) if personal else np.ones(len(p))
    order = np.argsort(xy[:, 0] * 100 + xy[:, 1])
    runs = core.curve_walk(core.segment_table(order, p, d, eps), d[np.ix_(order, order)], e_min)
    whole = core.anchor_outer(np.arange(len(p)), p, d) >= np.exp(eps.min()) * e_min
    assert (runs is not None) == whole
    if runs:
        valid([order[a : b + 1] for a, b in runs], p, d, eps, e_min)
        exact = core.best_contiguous(core.segment_table(order, p, d, eps), e_min)
        score = [core.average_reach([order[a : b + 1] for a, b in r], p, d) for r in (runs, exact)]
        assert score[1] <= score[0] + 1e-9


@settings(max_examples=15, deadline=None)
@given(st.integers(0, 10_000), st.floats(0.05, 0.8), st.sampled_from([None, 0.5]))
def test_quasi_k_means_is_a_valid_zoning(seed, e_min, lam):
    p, xy, d = domain(seed, 14)
    eps = np.random.default_rng(seed).uniform(0.5, 1.5, len(p))
    zone = core.choose_zoning(p, xy, d, eps, e_min, max_samp=4, lam=lam)
    if zone is not None:
        valid([np.flatnonzero(zone == z) for z in np.unique(zone)], p, d, eps, e_min)


def test_quasi_k_means_against_exhaustive_search():
    xy = np.array([(0, 0), (1, 0), (0, 3), (1, 3), (9, 1), (9, 2)], float)
    p, d = np.array([0.2, 0.2, 0.15, 0.15, 0.15, 0.15]), core.distances(xy[:, 0], xy[:, 1])
    best = core.best_zoning(p, d, np.full(6, 0.5), 0.1)
    zone = core.choose_zoning(p, xy, d, np.full(6, 0.5), 0.1)
    assert sorted(np.flatnonzero(zone == z).tolist() for z in np.unique(zone)) == sorted(best) == [[0, 1], [2, 3], [4, 5]]


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10_000), st.integers(2, 6))
def test_union_lemma(seed, cut):
    """The union of two zones has at least the mass-weighted mean of their errors."""
    p, _, d = domain(seed, 12)
    a, b = np.arange(cut), np.arange(cut, len(p))
    if len(b):
        both = core.anchor_outer(np.arange(len(p)), p, d)
        parts = (p[a].sum() * core.anchor_outer(a, p, d) + p[b].sum() * core.anchor_outer(b, p, d)) / p.sum()
        assert both >= parts - 1e-9


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 10_000), st.floats(0.2, 2.0))
def test_measures_and_guarantees(seed, eps):
    p, xy, d = domain(seed, 16)
    if len(p) < 4:
        return
    e = np.full(len(p), eps)
    zone = (np.arange(len(p)) // 2) * 2
    if len(p) % 2:
        zone[-1] = zone[-2]
    k = core.kernel(core.zonal_scale(zone, e, d), d)
    m = core.measures(k, p, d)
    assert m["exp_err"] == pytest.approx(float(p @ m["avg_err"])) and m["q_loss"] == pytest.approx(float(p @ m["loss"]))
    assert m["exp_err"] <= min(m["q_loss"], (d @ p).min()) + 1e-9
    assert float(p @ m["success"]) == pytest.approx(float((p[:, None] * k).max(0).sum()))
    for z in np.unique(zone):
        at = np.flatnonzero(zone == z)
        l = np.log(k[at])  # noqa: E741
        assert (l.max(0) - l.min(0)).max() <= eps + 1e-9
    least = min(core.anchor_outer(np.flatnonzero(zone == z), p, d) for z in np.unique(zone))
    assert m["min_exper"] >= np.exp(-eps) * least - 1e-9
    none = core.measures(np.eye(len(p)), p, d)
    assert none["q_loss"] == none["exp_err"] == 0 and (none["success"] == 1).all()


def test_geo_lp_closed_form_and_certificate():
    d = np.array([[0, 2.0], [2.0, 0]])
    s = lp.solve(np.array([0.5, 0.5]), d, 0.7, delta=0)
    assert s.kernel[0, 0] == pytest.approx(np.exp(1.4) / (1 + np.exp(1.4)), abs=1e-5)
    p, _, d = domain(3, 25)
    full, spanner = lp.solve(p, d, 0.3, 0), lp.solve(p, d, 0.3, 0.05)
    assert full.gap < 1e-3 and full.residual < 1e-5 and full.loss <= spanner.loss + 1e-4
    for s in (full, spanner):
        ratio = np.log(s.kernel[:, None, :] / s.kernel[None, :, :]).max(2)
        assert (ratio <= 0.3 * d + 1e-3).all()
    # No exponential kernel that meets the same constraints loses less.
    k = core.kernel(np.full(len(p), 0.15), d)
    assert full.loss <= float((p[:, None] * k * d).sum()) + 1e-6


def test_joint_lp_meets_its_bound():
    p, _, d = domain(4, 20)
    target = 0.7 * (d @ p).min()
    s = lp.solve(p, d, 1.0, 0.05, target)
    assert lp.exp_err(s.kernel, p, d) >= target - 1e-4
    free, geo = lp.solve(p, d, 1.0, 0.05, 0.0), lp.solve(p, d, 1.0, 0.05)
    assert free.loss == pytest.approx(geo.loss, abs=1e-3) and s.loss >= geo.loss - 1e-6


def test_spanner_stretch():
    _, _, d = domain(5, 30)
    edges = lp.greedy_spanner(d, 1.05)
    path = np.full(d.shape, np.inf)
    np.fill_diagonal(path, 0)
    for a, b in edges:
        path[a, b] = path[b, a] = d[a, b]
    for m in range(len(d)):
        path = np.minimum(path, path[:, [m]] + path[[m], :])
    assert (path <= 1.05 * d + 1e-9).all() and len(edges) < len(d) * (len(d) - 1) / 2
