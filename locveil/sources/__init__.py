"""Tables in and out: pruned scans, user-supplied cells, kernel store and report sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events")
CELLS = "domain_id string, cell_id long, cx int, cy int, x double, y double, prior double, eps double"


def read(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A Parquet table, only the named columns."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def read_cells(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """A user's own cells with prior and budget; malformed rows fail at once, invalid numbers are refused."""
    reader = spark.read.schema(CELLS).option("mode", "FAILFAST")
    df = reader.option("header", True).csv(path) if fmt == "csv" else getattr(reader, fmt)(path)
    bad = F.col("prior").isNull() | F.isnan("prior") | (F.col("prior") < 0) | F.col("x").isNull() | F.col("y").isNull() | F.isnan("x") | F.isnan("y")
    return df.withColumn("prior", F.when(bad, F.raise_error(F.concat(F.lit("invalid cell "), F.col("cell_id").cast("string")))).otherwise(F.col("prior")))


def write_kernel(df: DataFrame, path: str, version: str, buckets: int = 64) -> str:
    """A kernel or zoning, public and fixed once its parameters are: one versioned folder, partitioned for pruning."""
    target = f"{path}/version={version}"
    df.withColumn("domain_bucket", F.pmod(F.xxhash64("domain_id"), F.lit(buckets)).cast("int")).write.mode("errorifexists").partitionBy("domain_bucket").parquet(target)
    return target


def read_kernel(spark: SparkSession, path: str, version: str, domain_id: str | None = None, buckets: int = 64) -> DataFrame:
    df = spark.read.parquet(f"{path}/version={version}")
    if domain_id is not None:
        df = df.where(F.col("domain_bucket") == F.pmod(F.xxhash64(F.lit(domain_id)), F.lit(buckets)).cast("int")).where(F.col("domain_id") == domain_id)
    return df.drop("domain_bucket")


def write_reports(df: DataFrame, path: str) -> None:
    """Only pseudo-locations leave: a true cell among the columns is an error."""
    leak = {"true_cell", "cell_id", "cx", "cy", "x", "y"} & set(df.columns)
    if leak:
        raise ValueError(f"reports must not carry true positions: {sorted(leak)}")
    df.write.mode("append").parquet(path)


def register(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = TABLES) -> None:
    """Temporary views for SQL users."""
    for name in tables:
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)
