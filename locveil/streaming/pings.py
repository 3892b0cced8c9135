"""Reporting pings as they come: only dedup, windows and budgets keep state, all bounded by a watermark."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import draw_from_cdf, portable_uniform, secret_uniform
from ..operators.domains import place
from ..sources.scratch import folder

EVENTS = T.StructType([
    T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()),
    T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
])


def pings(spark: SparkSession, path: str, max_files: int = 64, schema: T.StructType = EVENTS) -> DataFrame:
    """Parquet files of a folder or pattern as a stream; event time becomes a timestamp, which watermarks need."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def rate_pings(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    """A synthetic stream for smoke runs."""
    df = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return df.select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), (F.col("value") % 50).alias("user_id"), (F.col("value") % 30).cast("int").alias("cx"), (F.col("value") % 7).cast("int").alias("cy"))


def with_lateness(df: DataFrame, late: str = "10 minutes") -> DataFrame:
    return df.withWatermark("ts", late)


def dedup(df: DataFrame) -> DataFrame:
    """A replayed ping must not be drawn anew: repeated draws leak."""
    return df.dropDuplicatesWithinWatermark(["event_id"])


def obfuscate(df: DataFrame, cells: DataFrame, rows: DataFrame, seed: int | str) -> DataFrame:
    """Pseudo-location of each ping inside the domain: ``domain_id, event_id, ts, user_id, reported_cell``.

    The kernel rows are static; draws are keyed by event, so order, batches and
    replays don't change them.
    """
    near = cells.select("domain_id", "cell_id", "cx", "cy")
    side = near.join(rows.withColumnRenamed("i", "cell_id"), ["domain_id", "cell_id"]).select("domain_id", "cx", "cy", "outs", "cdf")  # pings that carry a domain_id meet its cells only
    u = portable_uniform("event_id", seed) if isinstance(seed, int) else secret_uniform("event_id", seed)
    return df.join(side, place(df)).select("domain_id", "event_id", "ts", "user_id", draw_from_cdf("outs", "cdf", u).alias("reported_cell"))


def sticky(df: DataFrame, cells: DataFrame, rows: DataFrame, key: str, epoch: str = "1 day") -> DataFrame:
    """One draw for each user, cell and epoch, however often it is asked: guards against averaging; needs no state."""
    near = cells.select("domain_id", "cell_id", "cx", "cy").join(rows.withColumnRenamed("i", "cell_id"), ["domain_id", "cell_id"])
    when = F.window("ts", epoch)["start"]
    u = secret_uniform(F.concat_ws("|", F.col("user_id").cast("string"), F.col("cell_id").cast("string"), when.cast("string")), key)
    return df.join(near, place(df)).select("domain_id", "event_id", "ts", "user_id", draw_from_cdf("outs", "cdf", u).alias("reported_cell"))


def reports_per_window(reports: DataFrame, window: str = "1 hour", slide: str | None = None) -> DataFrame:
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return reports.groupBy("domain_id", span.alias("w"), "reported_cell").agg(F.count("*").alias("reports")).select("domain_id", F.col("w.start").alias("window_start"), "reported_cell", "reports")


def windowed_visits(df: DataFrame, cells: DataFrame, window: str = "1 day", slide: str = "6 hours") -> DataFrame:
    """Visits per sliding window and cell: a prior that follows the traffic."""
    inside = df.join(cells.select("domain_id", "cell_id", "cx", "cy"), ["cx", "cy"])
    return inside.groupBy("domain_id", F.window("ts", window, slide).alias("w"), "cell_id").agg(F.count("*").alias("visits")).select("domain_id", F.col("w.start").alias("window_start"), "cell_id", "visits")


def trips(df: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Session windows of each user."""
    return df.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("pings")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "pings")


def budget_spent(reports: DataFrame, cells: DataFrame, window: str = "1 day") -> DataFrame:
    """Budget each user has spent in a window, by sequential composition of the reported cells' budgets."""
    eps = cells.select("domain_id", F.col("cell_id").alias("reported_cell"), "eps")
    return reports.join(eps, ["domain_id", "reported_cell"]).groupBy("user_id", F.window("ts", window).alias("w")).agg(F.sum("eps").alias("spent"), F.count("*").alias("reports")).select("user_id", F.col("w.start").alias("window_start"), "spent", "reports")


def match_tasks(tasks: DataFrame, reports: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream join: reports within some minutes before a task; both sides need a watermark."""
    t = tasks.select("domain_id", "task_id", F.col("ts").alias("task_ts"))
    near = (F.col("r.ts") <= F.col("t.task_ts")) & (F.col("r.ts") >= F.col("t.task_ts") - F.expr(f"INTERVAL {int(minutes)} MINUTES"))
    return reports.alias("r").join(t.alias("t"), (F.col("r.domain_id") == F.col("t.domain_id")) & near).select("t.domain_id", "t.task_id", "r.event_id", "r.user_id", "r.reported_cell")


def run_available(df: DataFrame, mode: str = "append", name: str = "stream") -> DataFrame:
    """Process what is there and return the result as a table.

    Batches are written by their id, so that a repeated batch replaces itself;
    ``complete`` keeps the last one.
    """
    spark = df.sparkSession
    out, check = folder(spark, f"{name}-out"), folder(spark, f"{name}-check")
    schema = df.schema

    def write(batch: DataFrame, batch_id: int) -> None:
        at = f"{out}/all" if mode == "complete" else f"{out}/batch={batch_id}"
        batch.write.mode("overwrite").parquet(at)

    query = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", check).trigger(availableNow=True).start()
    query.awaitTermination()
    got = spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(out)
    return got
