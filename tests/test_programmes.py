"""Convergence, infeasibility and tuning of the linear programmes, and the audit of their zeros."""

from __future__ import annotations

import numpy as np
import pytest

from locveil.operators import core, lp


def domain(n=30, seed=4, spread=12):
    rng = np.random.default_rng(seed)
    xy = rng.permutation(spread * spread)[:n]
    p = rng.uniform(0.01, 0.03, n)
    return p / p.sum(), core.distances(xy % spread + 0.5, xy // spread + 0.5)


@pytest.mark.parametrize("eps_g", [0.1, 0.35, 0.38, 0.4, 1.0, 2.0])
@pytest.mark.parametrize("share", [None, 0.5, 0.8, 0.95])
def test_programmes_converge(eps_g, share):
    p, d = domain()
    target = None if share is None else share * float((d @ p).min())
    got = lp.solve(p, d, eps_g, 0.05, target)
    assert got.status == "solved" and got.residual < 1e-6 and got.gap < 1e-4
    assert np.allclose(got.kernel.sum(1), 1) and got.kernel.min() > 0
    ratio = np.log(got.kernel[:, None, :] / got.kernel[None, :, :]).max(2)
    assert (ratio <= eps_g * d + 1e-4).all()
    if target is not None:
        assert lp.exp_err(got.kernel, p, d) >= target - 1e-5


def test_error_above_the_best_blind_guess_is_infeasible():
    p, d = domain()
    most = float((d @ p).min())
    assert lp.solve(p, d, 0.5, 0.05, most * 1.01).status == "infeasible"
    assert lp.tuned(p, d, most * 1.1)[0].status == "infeasible"
    assert lp.solve(p, d, 0.5, 0.05, 0.5 * most, max_steps=5).status == "unsolved"


def test_tuning_finds_the_least_eps_g():
    p, d = domain()
    for share in (0.2, 0.6, 0.9):
        target = share * float((d @ p).min())
        got, eps_g = lp.tuned(p, d, target, d_min=target)
        assert got.status == "solved" and abs(lp.exp_err(got.kernel, p, d) - target) <= 0.0051
        assert lp.exp_err(lp.solve(p, d, 0.97 * eps_g).kernel, p, d) > target + 0.005


def test_audit_counts_reports_that_only_one_cell_gives(spark):
    from locveil.operators import metrics

    k = spark.createDataFrame([("a", 0, 0, 1.0), ("a", 0, 1, 0.0), ("a", 1, 0, 0.5), ("a", 1, 1, 0.5)], "domain_id string, i long, j long, k double")
    dist = spark.createDataFrame([("a", 0, 0, 0.0), ("a", 0, 1, 1.0), ("a", 1, 0, 1.0), ("a", 1, 1, 0.0)], "domain_id string, i long, j long, d double")
    row = metrics.geoind_all_pairs(k, dist, 5.0).first()
    assert row.unbounded == 1 and not row.ok


def test_infinite_mass_counts_as_none(spark):
    from pyspark.sql import functions as F

    from locveil.operators import domains

    cells = domains.toy6(spark).drop("prior")
    got = domains._normalised(cells, F.when(F.col("cell_id") == 0, float("inf")).otherwise(1.0)).collect()
    assert {r.cell_id: round(r.prior, 9) for r in got} == {0: 0.0, **{i: 0.2 for i in range(1, 6)}}


def test_pings_with_a_domain_meet_its_cells_only(spark):
    from locveil.operators import domains

    cells = spark.createDataFrame([("a", 0, 1, 1), ("b", 0, 1, 1), ("b", 1, 2, 2)], "domain_id string, cell_id long, cx int, cy int")
    pings = spark.createDataFrame([(1, "a", 1, 1), (2, "a", 2, 2), (3, "b", 2, 2)], "event_id long, domain_id string, cx int, cy int")
    assert sorted(r.event_id for r in domains.inside(pings, cells).collect()) == [1, 3]
    assert [r.event_id for r in domains.outside(pings, cells).collect()] == [2]
    assert sorted(r.event_id for r in domains.inside(pings.drop("domain_id"), cells).collect()) == [1, 2, 3]
