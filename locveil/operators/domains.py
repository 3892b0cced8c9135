"""Domains of cells with priors and budgets.

``cells(domain_id, cell_id, cx, cy, x, y, prior, eps)``: one call may hold one domain
or a million; every operator is keyed by domain_id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import portable_uniform
from ..sources import read

# The printed prior, in hundredths, in order of the cells.
PRIOR = (
    1.53, 2.41, 1.11, 1.23, 2.29, 2.00, 2.13, 2.06, 1.87, 1.43,
    1.84, 2.24, 1.54, 1.50, 1.50, 2.53, 2.15, 2.59, 2.46, 1.90,
    2.43, 2.10, 2.46, 1.62, 1.50, 1.32, 2.55, 1.97, 2.61, 2.82,
    2.69, 2.27, 1.81, 1.79, 2.78, 2.84, 1.66, 2.69, 1.07, 1.99,
    1.99, 1.92, 1.06, 2.49, 1.09, 2.68, 1.93, 2.40, 1.84, 1.64,
)

#: Named budget levels; a user's choice, to be adjusted.
LEVELS = {"conservative": 0.5, "moderate": 1.0, "liberal": 1.5}
SEGMENT_LEVEL = {"AUTOMOBILE": "conservative", "BUILDING": "conservative", "FURNITURE": "moderate", "HOUSEHOLD": "liberal", "MACHINERY": "liberal"}


def to_cell(x: Column, y: Column, size: float = 1.0) -> tuple[Column, Column]:
    """Grid coordinates of a point."""
    return F.floor(x / size).cast("int"), F.floor(y / size).cast("int")


def _first_cells(points: DataFrame, n: int, extra: tuple[str, ...] = ()) -> DataFrame:
    """``points(domain_id, cx, cy, at)`` to the first n distinct cells of each domain, numbered by first occurrence."""
    cells = points.groupBy("domain_id", "cx", "cy").agg(F.min("at").alias("at"))
    order = W.partitionBy("domain_id").orderBy("at", "cx", "cy")
    cells = cells.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= n)
    return cells.select("domain_id", (F.col("rn") - 1).cast("long").alias("cell_id"), "cx", "cy", (F.col("cx") + 0.5).alias("x"), (F.col("cy") + 0.5).alias("y"))


def dense(spark: SparkSession, sf_dir: str, n: int = 50) -> DataFrame:
    """Stand-in for the dense set: first cells of the first two vector components, scaled."""
    df = read(spark, sf_dir, "embeddings", "vec_id", "embedding")
    cx, cy = (F.floor(22.0 * F.element_at("embedding", i).cast("double")).cast("int") for i in (1, 2))
    return _first_cells(df.select(F.lit("dense").alias("domain_id"), cx.alias("cx"), cy.alias("cy"), F.col("vec_id").alias("at")), n)


def event_cells(events: DataFrame) -> DataFrame:
    """``cx, cy`` of each ping, from its properties and value."""
    k = F.get_json_object("props", "$.k").cast("int")
    return events.withColumn("cx", F.floor(3 * k / 10).cast("int")).withColumn("cy", F.floor(F.col("value") / 5).cast("int"))


def sparse(spark: SparkSession, sf_dir: str, n: int = 50) -> DataFrame:
    """Stand-in for the sparse set: first cells of the pings; exponential values leave isolated ones."""
    df = event_cells(read(spark, sf_dir, "events", "event_id", "props", "value"))
    return _first_cells(df.select(F.lit("sparse").alias("domain_id"), "cx", "cy", F.col("event_id").alias("at")), n)


def by_type(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """Small domains for exact methods: the first n cells of each type of event."""
    df = event_cells(read(spark, sf_dir, "events", "event_id", "event_type", "props", "value"))
    return _first_cells(df.select(F.concat(F.lit("type:"), "event_type").alias("domain_id"), "cx", "cy", F.col("event_id").alias("at")), n)


def tiles(spark: SparkSession, sf_dir: str, n: int = 50) -> DataFrame:
    """Many domains: one per supplier."""
    df = read(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_quantity", "l_extendedprice")
    df = df.select(F.concat(F.lit("tile:"), F.col("l_suppkey").cast("string")).alias("domain_id"), F.col("l_quantity").cast("int").alias("cx"), F.floor(F.col("l_extendedprice") / 2000).cast("int").alias("cy"), F.col("l_orderkey").alias("at"))
    return _first_cells(df, n)


def literal(spark: SparkSession, domain_id: str, points: list[tuple[float, float]], prior: list[float] | None = None, eps: float = 1.0) -> DataFrame:
    """A domain written out; positions are the points themselves."""
    p = prior or [1 / len(points)] * len(points)
    rows = [(domain_id, i, int(x // 1), int(y // 1), float(x), float(y), float(w), float(eps)) for i, ((x, y), w) in enumerate(zip(points, p, strict=True))]
    return spark.createDataFrame(rows, "domain_id string, cell_id long, cx int, cy int, x double, y double, prior double, eps double")


def toy4(spark: SparkSession) -> DataFrame:
    """Three cells far apart and one between two of them: a guess from outside beats every guess inside."""
    return literal(spark, "toy4", [(0, 120), (-50, 0), (50, 0), (0, -2.75)])


def toy2(spark: SparkSession, d: float = 2.0) -> DataFrame:
    return literal(spark, "toy2", [(0, 0), (d, 0)])


def toy6(spark: SparkSession) -> DataFrame:
    return literal(spark, "toy6", [(0, 0), (1, 0), (0, 3), (1, 3), (9, 1), (9, 2)], [0.2, 0.2, 0.15, 0.15, 0.15, 0.15])


def grid(spark: SparkSession, side: int) -> DataFrame:
    return literal(spark, f"grid{side}", [(i + 0.5, j + 0.5) for j in range(side) for i in range(side)])


def _normalised(cells: DataFrame, raw: Column) -> DataFrame:
    """Prior proportional to ``raw``; missing, negative or non-finite mass counts as none."""
    raw = F.when(raw.isNull() | F.isnan(raw) | (raw < 0) | (raw == float("inf")), 0.0).otherwise(raw)
    return cells.withColumn("raw", raw).withColumn("prior", F.col("raw") / F.sum("raw").over(W.partitionBy("domain_id"))).drop("raw")


def prior_table2(cells: DataFrame) -> DataFrame:
    """The printed prior by cell_id; its sum is not 1, so it is normalised. Cells beyond the fiftieth start over."""
    values = F.array(*(F.lit(v) for v in PRIOR))
    return _normalised(cells, F.get(values, (F.col("cell_id") % len(PRIOR)).cast("int")))


def prior_uniform(cells: DataFrame, seed: int = 7) -> DataFrame:
    """U[0.01, 0.03], normalised."""
    return _normalised(cells, 0.01 + 0.02 * portable_uniform("cell_id", seed))


def place(pings: DataFrame) -> list[str]:
    """What pings and cells meet on: the coordinates, and the domain where pings already have one."""
    return [c for c in ("domain_id", "cx", "cy") if c in pings.columns]


def prior_visits(cells: DataFrame, pings: DataFrame, smoothing: float = 1.0) -> DataFrame:
    """From history: visits of each cell plus ``smoothing``. The history is taken as public."""
    seen = pings.groupBy(*place(pings)).agg(F.count("*").alias("visits"))
    cells = cells.drop("prior").join(seen, place(pings), "left")
    return _normalised(cells, F.coalesce("visits", F.lit(0)) + F.lit(float(smoothing))).drop("visits")


def prior_windowed(cells: DataFrame, pings: DataFrame, window: str = "1 day", slide: str | None = None) -> DataFrame:
    """``domain_id, window_start, cell_id, prior``: shares of visits in each window."""
    inside = pings.join(cells.select("domain_id", "cell_id", "cx", "cy"), place(pings))
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    seen = inside.groupBy("domain_id", span.alias("w"), "cell_id").agg(F.count("*").alias("visits"))
    share = F.col("visits") / F.sum("visits").over(W.partitionBy("domain_id", "w"))
    return seen.select("domain_id", F.col("w.start").alias("window_start"), "cell_id", share.alias("prior"))


def eps_constant(cells: DataFrame, eps: float) -> DataFrame:
    return cells.withColumn("eps", F.lit(float(eps)))


def eps_uniform(cells: DataFrame, lo: float = 0.5, hi: float = 1.5, seed: int = 11) -> DataFrame:
    return cells.withColumn("eps", F.lit(lo) + F.lit(hi - lo) * portable_uniform("cell_id", seed))


def eps_levels(cells: DataFrame, pings: DataFrame, customers: DataFrame, levels: dict[str, float] | None = None, default: float = 1.0) -> DataFrame:
    """Each cell's least budget among the users seen there, by their named level."""
    levels = levels or LEVELS
    table = F.create_map(*(x for seg, name in SEGMENT_LEVEL.items() for x in (F.lit(seg), F.lit(levels[name]))))
    users = customers.select(F.col("c_custkey").alias("user_id"), F.element_at(table, F.col("c_mktsegment")).alias("level_eps"))
    seen = pings.select("user_id", *place(pings)).join(users, "user_id").groupBy(*place(pings)).agg(F.min("level_eps").alias("level_eps"))
    return cells.drop("eps").join(seen, place(pings), "left").withColumn("eps", F.coalesce("level_eps", F.lit(default))).drop("level_eps")


def eps_floor(cells: DataFrame) -> DataFrame:
    """One budget for all: the least of the domain, for the comparison without personal budgets."""
    return cells.withColumn("eps", F.min("eps").over(W.partitionBy("domain_id")))


def inside(pings: DataFrame, cells: DataFrame) -> DataFrame:
    """Pings on a cell; cells are broadcast where Spark finds them small enough."""
    return pings.join(cells.select(*place(pings)), place(pings), "left_semi")


def outside(pings: DataFrame, cells: DataFrame) -> DataFrame:
    return pings.join(cells.select(*place(pings)), place(pings), "left_anti")
