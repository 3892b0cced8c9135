"""Spatial crowdsourcing: tasks, workers as of the task's time, the three nearest, and the travel distance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import portable_uniform


def tasks(pings: DataFrame, n: int = 100) -> DataFrame:
    """The last n purchases: ``domain_id, task_id, ts, task_cell``."""
    df = pings.where("event_type = 'purchase'").orderBy(F.desc("event_id")).limit(n)
    return df.select("domain_id", F.col("event_id").alias("task_id"), "ts", F.col("cell_id").alias("task_cell"))


def workers_asof(task: DataFrame, pings: DataFrame, per_task: int = 30, seed: int = 5) -> DataFrame:
    """As-of join: each worker's last position at or before the task's time, ``per_task`` workers by hash.

    ``domain_id, task_id, task_cell, worker_id, event_id, cell_id``.  Workers are picked
    from their first positions, one row each; only the picked ones' pings meet the tasks.
    """
    seen = pings.where("event_type <> 'purchase'").select("domain_id", F.concat_ws("/", F.col("user_id").cast("string"), "event_type").alias("worker_id"), "event_id", F.col("ts").alias("at"), "cell_id")
    t = task.select("domain_id", "task_id", "task_cell", "ts")
    since = seen.groupBy("domain_id", "worker_id").agg(F.min("at").alias("since"))
    luck = portable_uniform(F.concat_ws("-", F.col("task_id").cast("string"), "worker_id"), seed)
    w = W.partitionBy("domain_id", "task_id").orderBy("luck", "worker_id")
    able = since.join(t, "domain_id").where("since <= ts").withColumn("luck", luck)
    picked = able.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= per_task).drop("luck", "rn", "since")
    both = seen.join(picked, ["domain_id", "worker_id"]).where("at <= ts")
    last = both.groupBy("domain_id", "task_id", "task_cell", "worker_id").agg(F.max(F.struct("at", "event_id", "cell_id")).alias("l"))
    return last.select("domain_id", "task_id", "task_cell", "worker_id", F.col("l.event_id").alias("event_id"), F.col("l.cell_id").alias("cell_id"))


def pings_near(task: DataFrame, pings: DataFrame, minutes: int = 10) -> DataFrame:
    """Interval join: pings within some minutes before a task, by an equi-join on time buckets of that width."""
    width = minutes * 60
    unix = lambda c: F.unix_timestamp(F.col(c).cast("timestamp"))
    t = task.withColumn("t", unix("ts")).withColumn("bucket", F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) - 1)))
    p = pings.select("domain_id", "event_id", "user_id", F.col("ts").alias("at"), "cell_id").withColumn("p", unix("at")).withColumn("bucket", F.floor(F.col("p") / width))
    return p.join(t.select("domain_id", "task_id", "t", "bucket"), ["domain_id", "bucket"]).where((F.col("p") <= F.col("t")) & (F.col("p") > F.col("t") - width)).select("domain_id", "task_id", "event_id", "user_id", "cell_id")


def assign(workers: DataFrame, dist: DataFrame, k: int = 3, by: str = "reported_cell") -> DataFrame:
    """The k workers nearest to each task by their reported (or true) cell, ties by worker_id; a worker may serve several tasks."""
    far = dist.select("domain_id", F.col("i").alias("task_cell"), F.col("j").alias(by), F.col("d").alias("seen_d"))
    w = W.partitionBy("domain_id", "task_id").orderBy(F.round("seen_d", 9), "worker_id")
    return workers.join(far, ["domain_id", "task_cell", by]).withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= k)


def wtd(assigned: DataFrame, dist: DataFrame) -> DataFrame:
    """Mean distance from the assigned workers' true cells to the task, averaged over tasks: ``domain_id, wtd, tasks``."""
    far = dist.select("domain_id", F.col("i").alias("task_cell"), F.col("j").alias("cell_id"), "d")
    per = assigned.join(far, ["domain_id", "task_cell", "cell_id"]).groupBy("domain_id", "task_id").agg(F.avg("d").alias("d"))
    return per.groupBy("domain_id").agg(F.avg("d").alias("wtd"), F.count("*").alias("tasks"))
