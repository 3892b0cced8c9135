"""The Python aggregate and table function, alias tables from packed rows, and the cost of a run."""

import math

import pytest

from locveil.operators import condition, domains, exponential, geometry, sample, table_functions, zoning
from locveil.plans import cost


@pytest.fixture(scope="module")
def toy(spark):
    table_functions.register(spark)
    cells = domains.toy6(spark)
    cells.createOrReplaceTempView("toy_cells")
    return cells


def _zones(rows):
    return sorted((r.cell_id, r.zone_id) for r in rows)


def test_aggregate_equals_the_joins(spark, toy):
    zones = zoning.blocks_by_id(toy, 2)
    want = {r.zone_id: r.a_out for r in condition.zone_stats(zones, toy, geometry.pairs(toy)).collect()}
    zones.createOrReplaceTempView("toy_zones")
    got = spark.sql(
        """WITH at AS (SELECT domain_id, collect_list(struct(x, y)) at FROM toy_cells GROUP BY domain_id)
        SELECT zone_id, anchor_outer_agg(x, y, prior, at.x, at.y) a FROM toy_cells JOIN toy_zones USING (domain_id, cell_id) JOIN at USING (domain_id) GROUP BY zone_id"""
    ).collect()
    assert {r.zone_id for r in got} == set(want) and all(math.isclose(r.a, want[r.zone_id], abs_tol=1e-12) for r in got)


def test_aggregate_without_mass(spark, toy):
    got = spark.sql("SELECT anchor_outer_agg(x, y, 0D * prior, array(0D), array(0D)) a, anchor_outer_agg(x, y, prior, array(), array()) b FROM toy_cells").first()
    assert got.a is None and got.b is None


def test_table_function_equals_the_operators(spark, toy):
    call = "SELECT * FROM make_zones(TABLE({}) PARTITION BY (domain_id), 0.5D, {}D, '{}')"
    got = spark.sql(call.format("toy_cells", 0.1, "qkm")).collect()
    assert _zones(got) == _zones(zoning.zone_qkm(toy, [(0.5, 0.1)]).collect())
    geometry.rank_on_curve(toy, None, (0,)).createOrReplaceTempView("toy_ranked")
    for method, exact in (("curve", False), ("contiguous", True)):
        got = spark.sql(call.format("toy_ranked", 0.1, method)).collect()
        assert _zones(got) == _zones(zoning.zone_curve(toy, [(0.5, 0.1)], exact=exact).collect())
    none = spark.sql(call.format("toy_ranked", 99, "curve")).collect()
    assert [(r.status, r.avg_reach, r.cell_id) for r in none] == [("infeasible", None, None)]
    assert spark.sql(call.format("(SELECT * FROM toy_cells WHERE false)", 0.1, "qkm").replace("TABLE((", "TABLE(").replace("false))", "false)")).collect() == []


def test_alias_tables_hold_the_kernel(spark, toy):
    dist = geometry.pairs(toy)
    zones = zoning.blocks_by_id(toy, 2)
    kernel = exponential.zonal_kernel(zones, condition.zone_stats(zones, toy, dist), dist)
    want = {(r.i, r.j): r.k for r in kernel.collect()}
    for row in sample.alias_rows(kernel).collect():
        got = dict.fromkeys(row.outs, 0.0)
        for own, keep, other in zip(row.outs, row.keep, row.other, strict=True):
            got[own] += keep / len(row.outs)
            got[other] += (1 - keep) / len(row.outs)
        assert all(math.isclose(v, want[row.i, j], abs_tol=1e-12) for j, v in got.items())


def test_cost_of_a_run(spark):
    got = cost.cost(spark.range(1000).repartition(3, "id"), "spread").first()
    assert (got.query, got.rows) == ("spread", 1000)
    assert got.seconds > 0 and got.jobs > 0 and got.shuffle_bytes > 0
    assert cost.cost(spark.range(10), "plain").first().shuffle_bytes == 0
