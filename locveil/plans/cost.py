"""What one run of a query costs: time, rate, jobs and shuffled bytes, read from the executed plan."""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame

COST = "query string, rows long, seconds double, rows_per_s double, jobs int, stages int, shuffle_bytes long"


def _nodes(plan) -> Iterator:
    """Every operator of an executed plan, through the wrappers of adaptive execution."""
    yield plan
    name = plan.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        yield from _nodes(plan.executedPlan())
    elif name.endswith("QueryStageExec"):
        yield from _nodes(plan.plan())
    children = plan.children()
    for i in range(children.size()):
        yield from _nodes(children.apply(i))


def cost(df: DataFrame, name: str) -> DataFrame:
    """Run ``df`` once, all columns, and return one row of COST; only counts reach the driver.

    An exchange that is used twice is written, and counted, once.
    """
    spark = df.sparkSession
    sc, group = spark.sparkContext, f"cost-{uuid.uuid4().hex}"
    before = sc.getLocalProperty("spark.jobGroup.id")
    sc.setJobGroup(group, name)
    began = time.perf_counter()
    try:
        run = df._jdf.queryExecution()
        rows = run.toRdd().count()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before)
    seconds = time.perf_counter() - began
    tracker = sc.statusTracker()
    jobs = tracker.getJobIdsForGroup(group)
    infos = [j for j in map(tracker.getJobInfo, jobs) if j]
    written = {}
    for node in _nodes(run.executedPlan()):
        metric = node.metrics().get("shuffleBytesWritten")
        if metric.isDefined() and node.getClass().getSimpleName() == "ShuffleExchangeExec":
            written[metric.get().id()] = metric.get().value()
    stages = len({s for j in infos for s in j.stageIds})
    return spark.createDataFrame([(name, rows, seconds, rows / seconds, len(jobs), stages, sum(written.values()))], COST)
