"""Disk of the written tables and of the Jaccard join's segments."""

import numpy as np
from pyspark.sql import functions as F


def _shuffle_files(spark):
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {n for n in (files.apply(i).getName() for i in range(files.size())) if n.startswith("shuffle_") and n.endswith(".data")}


def test_shuffles_of_a_written_table_go_with_the_write(spark):
    from locveil.llm._scratch import written

    before = _shuffle_files(spark)
    got = written(spark.range(5000).groupBy((F.col("id") % 700).alias("k")).count(), "counts")
    assert not _shuffle_files(spark) - before
    assert got.count() == 700 and got.agg(F.sum("count")).first()[0] == 5000


def test_segments_take_every_wanted_row_and_few_others(spark):
    from locveil.llm import jaccard_join as jj

    docs = spark.createDataFrame([(i, f"w{i} a{i} b{i} c{i} d{i}") for i in range(2000)], "doc_id long, text string")
    rows = [r.key for r in jj._keyed(docs).collect()]
    assert min(rows) < 0 < max(rows)
    wanted = spark.createDataFrame([(k,) for k in rows[:300]], "key long")
    order = jj._order(docs, 4)
    got = jj._segments(docs, wanted, 4, order)
    exact = jj._segments(docs.where("doc_id < 300"), wanted, 4, order)
    names = {r.rep for r in exact.collect()}
    assert len(names) == 300 and names <= {r.rep for r in got.collect()}
    assert got.select("rep").distinct().count() < 400
    assert "Exchange" not in got._jdf.queryExecution().toString()
    assert np.unpackbits(jj._bitmap(wanted)).sum() <= 300
