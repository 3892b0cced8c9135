"""Spark operators on toys and edge cases; registered queries against their SQL."""

import math

import pytest
from pyspark.sql import functions as F

from locveil.operators import attack, condition, crowd, domains, exponential, geometry, metrics, sample, zoning
from locveil.plans import experiments, registry, schemes
from locveil.sources import read_cells, read_kernel, write_kernel, write_reports

SF = "/root/testdata/sf0.001"


def test_hilbert_properties(spark):
    from pyspark.sql import functions as F

    from locveil.functions import hilbert

    n = 8
    for rot in range(4):
        rows = spark.range(n * n).select((F.col("id") % n).cast("int").alias("x"), F.floor(F.col("id") / n).cast("int").alias("y")).withColumn("h", hilbert("x", "y", 3, rot)).orderBy("h").collect()
        assert [r.h for r in rows] == list(range(1, n * n + 1))
        assert all(abs(a.x - b.x) + abs(a.y - b.y) == 1 for a, b in zip(rows, rows[1:], strict=False))
        assert {rows[0].x, rows[0].y, rows[-1].x, rows[-1].y} <= {0, n - 1}


def test_toy_counterexample(spark):
    cells = domains.toy4(spark)
    zones = cells.select("domain_id", "cell_id", F.when(F.col("cell_id") < 3, 0).otherwise(3).cast("long").alias("zone_id"))
    r = registry._counterexamples(cells, zones).where("zone_id = 0").first()
    assert (round(r.a_in, 4), round(r.a_out, 4), r.gap, r.convex) == (76.6667, 74.3004, True, True)


def test_exhaustive_search_and_methods_agree(spark):
    cells = domains.toy6(spark)
    best = zoning.best_partition(cells, [(0.5, 0.1)]).toPandas().sort_values("cell_id")["zone_id"].tolist()
    assert best == [0, 0, 2, 2, 4, 4]
    assert zoning.zone_qkm(cells, [(0.5, 0.1)]).toPandas().sort_values("cell_id")["zone_id"].tolist() == best
    none = zoning.zone_curve(cells, [(3.0, 9.0)]).collect()
    assert len(none) == 1 and none[0].status == "infeasible" and none[0].cell_id is None


def test_small_and_odd_domains(spark):
    for points in ([(0, 0), (3, 0)], [(0, 0), (3, 0), (0, 4)], [(0, 0), (3, 0), (0, 4), (9, 9), (9, 8)]):
        cells = domains.literal(spark, "d", points)
        zones = zoning.zone_curve(cells, [(0.1, 0.01)]).where("status = 'ok'")
        stats = condition.zone_stats(zones, cells, geometry.pairs(cells))
        got = zoning.validate(zones, cells, stats, 0.01).first()
        assert (got.uncovered, got.doubled, got.small, got.below_floor) == (0, 0, 0, 0)
    cells = domains.dense(spark, SF)
    raw = domains._normalised(cells, __import__("pyspark.sql.functions", fromlist=["lit"]).when(cells.cell_id < 5, -1.0).when(cells.cell_id < 9, float("nan")).otherwise(2.0))
    p = [r.prior for r in raw.collect()]
    assert math.isclose(sum(p), 1) and min(p) == 0


def test_bayesian_attack_is_the_optimal_one_under_hamming(spark):
    cells = domains.prior_table2(domains.dense(spark, SF, 20)).withColumn("eps", __import__("pyspark.sql.functions", fromlist=["lit"]).lit(1.0))
    k = exponential.constant_kernel(geometry.pairs(cells), 2.0, 1.0)
    a = {r.j: r.guess_opt for r in attack.optimal(k, cells, geometry.pairs(cells, "hamming")).collect()}
    assert a == {r.j: r.guess_map for r in attack.bayesian(k, cells).collect()}


def test_sampling_follows_the_kernel(spark):
    from pyspark.sql import functions as F

    cells = domains.toy6(spark)
    dist = geometry.pairs(cells)
    zones = zoning.blocks_by_id(cells, 2)
    stats = condition.zone_stats(zones, cells, dist)
    k = exponential.zonal_kernel(zones, stats, dist)
    pings = spark.range(12000).select(F.lit("toy6").alias("domain_id"), F.col("id").alias("event_id"), (F.col("id") % 6).alias("cell_id"))
    ways = {
        "cdf": sample.draw(pings, exponential.packed(k), 1, 36), "shuffled": sample.draw(pings, exponential.packed(k), 1), "secret": sample.draw(pings, exponential.packed(k), "key"),
        "gumbel": sample.draw_gumbel(pings, cells, zones, stats, 1), "alias": sample.draw_alias(pings, sample.alias_rows(k), 1),
    }
    for name, df in ways.items():
        got = df.select("domain_id", "event_id", "cell_id", "reported_cell")
        assert got.count() == 12000
        for r in sample.goodness(got, k).collect():
            assert r.chi2 < 30, name  # 5 degrees of freedom: far beyond the 99.9 % point
    a, b = (ways[w].orderBy("event_id").collect() for w in ("cdf", "shuffled"))
    assert [r.reported_cell for r in a] == [r.reported_cell for r in b]


def test_ping_path_has_no_python(spark):
    p = registry._Plain(spark, SF, "sparse")
    _, at = registry._inside(spark, SF)
    plan = sample.draw(at, exponential.packed(p.kernel), 42)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan


def test_personal_with_equal_budgets_is_the_common_scheme(spark):
    cells = experiments.both(spark, SF, 1.0).where("domain_id = 'dense'")
    got = schemes.run(cells, ["zonal_curve", "personal_curve", "unified_curve"], [(1.0, 0.2)]).where("measure = 'q_loss'").collect()
    assert len({round(r.value, 9) for r in got}) == 1


def test_schemes_reproduce_the_reported_order(spark):
    """At equal error the zonal scheme has the fewest exposed cells; the constant kernel of the largest reach loses most."""
    t = {(r.domain_id, r.measure): r for r in experiments.table3(spark, "/root/testdata/sf0.01").collect()}
    for d in ("dense", "sparse"):
        for other in ("em_tuned", "geo_lp", "joint_lp"):
            assert abs(t[d, "exp_err"].zonal_curve - t[d, "exp_err"][other]) <= 0.006
            assert t[d, "over_50"].zonal_curve <= t[d, "over_50"][other]
    m = {(r.domain_id, r.scheme): r.value for r in experiments.em_maxreach(spark, "/root/testdata/sf0.01").collect() if r.measure == "q_loss"}
    for d in ("dense", "sparse"):
        assert m[d, "em_maxreach"] > 1.2 * m[d, "zonal_curve"]


def test_audits_of_the_predecessor(spark):
    rows = experiments.audit_adaptive(spark, SF).collect()
    assert len(rows) == 4 and any(r.breaks_budget for r in rows)


def test_crowd_order(spark):
    r = {x.scheme: x.wtd for x in experiments.crowd_wtd(spark, SF, n_tasks=20).collect()}
    assert r["none"] <= r["zonal_qkm"] and r["none"] <= r["joint_lp"]


def test_relative_and_improved(spark):
    m = spark.createDataFrame([("d", s, 1.0, e, "q_loss", v) for e, a, b in ((0.1, 2.0, 3.0), (0.2, 4.0, 4.0)) for s, v in (("x", a), ("y", b))], "domain_id string, scheme string, eps_param double, e_min double, measure string, value double")
    r = metrics.relative(m, "x", "y").first()
    assert (round(r.mean_change, 6), round(r.max_change, 6), r.settings) == (0.25, 0.5, 2)


def test_sources(spark, tmp_path):
    cells = domains.toy6(spark)
    path = f"file://{tmp_path}"
    cells.write.option("header", True).csv(f"{path}/cells")
    assert sorted(map(tuple, read_cells(spark, f"{path}/cells").collect())) == sorted(map(tuple, cells.collect()))
    (tmp_path / "bad.csv").write_text("domain_id,cell_id,cx,cy,x,y,prior,eps\nd,0,0,0,0.5,0.5,-1,1\n")
    with pytest.raises(Exception, match="invalid cell"):
        read_cells(spark, f"{path}/bad.csv").collect()
    k = exponential.identity_kernel(geometry.pairs(cells))
    write_kernel(k, f"{path}/kernels", "v1")
    assert read_kernel(spark, f"{path}/kernels", "v1", "toy6").count() == 36
    with pytest.raises(ValueError, match="true positions"):
        write_reports(cells, f"{path}/reports")
    write_reports(k.select("domain_id", "j"), f"{path}/reports")
    assert spark.read.parquet(f"{path}/reports").count() == 36


def test_sql_functions(spark):
    from locveil.functions import register_sql

    register_sql(spark)
    r = spark.sql("SELECT cell_distance(0, 0, 3, 4) d, portable_uniform('0', '7') u, eps_weight(0.5, 1.0, 0.5) w, privacy_floor(0.0, 2.0) f").first()
    assert (r.d, r.w, r.f) == (5.0, 1.0, 2.0) and r.u == pytest.approx(0.5269208679748765, abs=1e-15)


def test_interval_join_and_asof(spark):
    _, at = registry._inside(spark, "/root/testdata/sf0.01")
    t = crowd.tasks(at, 10)
    assert crowd.workers_asof(t, at).groupBy("task_id").count().agg({"count": "max"}).first()[0] <= 30


FAST = [
    "cells_dense", "cells_sparse", "prior_table2", "prior_visits", "eps_levels_by_segment", "pair_distance", "hilbert_8x8", "curve_rotations", "segments_curve", "domain_feasible_grid", "zone_condition", "kernel_personal", "kernel_constant_maxreach",
    "attack_optimal", "attack_narrow", "avg_err", "success_prob", "weak_dp_audit", "zones_adaptive_inner", "sample_reports", "three_nearest_workers", "reports_sliding", "stream_reports", "stream_session_trips", "stream_dedup", "valid_curve_sparse",
]


@pytest.mark.parametrize("name", FAST)
def test_query_matches_sql(spark, name):
    import duckdb

    df = registry.QUERIES[name](spark, SF)
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "lineitem", "events", "embeddings"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    con.execute(registry.SQL[name])
    cols = [c[0] for c in con.description]
    assert sorted(cols) == sorted(df.columns)
    flat = lambda v: round(float(v), 6) + 0.0 if isinstance(v, float) else v
    want = sorted(tuple(flat(v) for v in r) for r in con.fetchall())
    assert sorted(tuple(flat(r[c]) for c in cols) for r in df.collect()) == want


def test_crowd_grid_has_every_setting(spark):
    from locveil.plans import experiments

    params = [("dense", 0.5, 0.1), ("dense", 0.5, 0.2), ("sparse", 1.5, 0.1), ("dense", 9.0, 0.2)]
    rows = experiments.wtd_grid(spark, SF, params, n_tasks=20, max_samp=2).collect()
    got = {(r.domain_id, r.eps_param, r.e_min, r.scheme): r.wtd for r in rows}
    assert len(rows) == len(got) == 3 * len(params)
    for p in params[:3]:
        assert got[*p, "none"] <= got[*p, "zonal_qkm"] and got[*p, "joint_lp"] > 0
    assert got[*params[3], "zonal_qkm"] is None


def test_joint_and_personal_grids_are_whole(spark, monkeypatch):
    from locveil.plans import experiments

    asked = []
    monkeypatch.setattr(experiments.schemes, "run", lambda cells, names, params, *a: asked.append(params) or spark.createDataFrame([], schemes.MEASURES))
    experiments.joint_loss(spark, SF)
    experiments.personal_gain(spark, SF)
    dense, sparse, own = map(set, asked)
    assert dense == {(e, 0.2) for e in experiments.EPS_DENSE} | {(1.0, m) for m in experiments.E_MINS} and len(dense) == 21
    assert sparse == {(e, 0.2) for e in experiments.EPS_SPARSE} | {(1.0, m) for m in experiments.E_MINS} and len(sparse) == 23
    assert own == {(-1.0, m) for m in experiments.E_MINS}


def test_restarts_and_k_are_whole(spark, monkeypatch):
    import inspect

    from locveil.plans import experiments

    for f in (experiments.vary_eps, experiments.vary_emin, experiments.joint_loss, experiments.personal_gain):
        assert inspect.signature(f).parameters["max_samp"].default == 20
    asked = []
    monkeypatch.setattr(registry.zoning, "qkm_by_k", lambda cells, params, ks, max_samp=20, **how: asked.append((ks, max_samp)) or spark.createDataFrame([("dense", 1.0, 0.2, 1, 4.0)], "domain_id string, eps_param double, e_min double, k int, avg_reach double"))
    registry.QUERIES["zones_qkm_by_k"](spark, SF)
    registry.QUERIES["zones_qkm_choose_k"](spark, SF)
    assert asked == [(list(range(1, 26)), 20)] * 2
