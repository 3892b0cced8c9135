"""Queries that once made their data up read a given table, with the results of their SQL."""

import duckdb
import pytest

from locveil.plans import registry

SF = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", ["eps_weight_curve", "hilbert_4x4", "hilbert_8x8", "lp_geo_toy2", "toy_counterexample", "zones_bruteforce_toy6"])
def test_reads_a_given_table(spark, name):
    df = registry.QUERIES[name](spark, SF)
    assert any(f.startswith(f"file://{SF}/") for f in df.inputFiles())
    rows = df.collect()
    assert rows
    if name not in registry.SQL:
        return
    con = duckdb.connect()
    for t in ("events", "lineitem"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    con.execute(registry.SQL[name])
    cols = [c[0] for c in con.description]
    assert sorted(cols) == sorted(df.columns)
    flat = lambda v: round(v, 6) + 0.0 if isinstance(v, float) else v
    assert sorted(tuple(flat(r[c]) for c in cols) for r in rows) == sorted(tuple(map(flat, r)) for r in con.fetchall())


def test_exhaustive_search_takes_every_type_of_event(spark):
    rows = registry.zones_bruteforce_toy6(spark, SF).collect()
    assert len({r.domain_id for r in rows}) == 5
    assert all(r.avg_reach is None or r.avg_reach >= 0 for r in rows)
