"""The zone condition: a prior-weighted guessing error that clears exp(eps) * e_min."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import geometry


def _costs(zones: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """``domain_id, zone_id, g, err``: normalised cost of each guess for each zone."""
    member = zones.select("domain_id", "cell_id", "zone_id").join(cells.select("domain_id", "cell_id", "prior"), ["domain_id", "cell_id"]).withColumnRenamed("cell_id", "i")
    joined = dist.join(member, ["domain_id", "i"])
    return joined.groupBy("domain_id", "zone_id", F.col("j").alias("g")).agg((F.sum(F.col("prior") * F.col("d")) / F.sum("prior")).alias("err"))


def _least(costs: DataFrame, name: str) -> DataFrame:
    best = costs.groupBy("domain_id", "zone_id").agg(F.min(F.struct(F.round("err", 12).alias("r"), "g", "err")).alias("b"))
    return best.select("domain_id", "zone_id", F.col("b.err").alias(name), F.col("b.g").alias(f"{name}_guess"))


def anchor_outer(zones: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """Least error of one guess anywhere in the domain: ``domain_id, zone_id, a_out, a_out_guess``."""
    return _least(_costs(zones, cells, dist), "a_out")


def anchor_inner(zones: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """The same with the guess confined to the zone (the older, insufficient quantity)."""
    own = zones.select("domain_id", "zone_id", F.col("cell_id").alias("g"))
    return _least(_costs(zones, cells, dist).join(own, ["domain_id", "zone_id", "g"], "left_semi"), "a_in")


def zone_stats(zones: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """``domain_id, zone_id, size, mass, eps_zone, reach, a_out, a_in`` of each zone."""
    member = zones.select("domain_id", "cell_id", "zone_id").join(cells.select("domain_id", "cell_id", "prior", "eps"), ["domain_id", "cell_id"])
    base = member.groupBy("domain_id", "zone_id").agg(F.count("*").alias("size"), F.sum("prior").alias("mass"), F.min("eps").alias("eps_zone"))
    keys = ["domain_id", "zone_id"]
    out = base.join(geometry.reach(zones, dist), keys).join(anchor_outer(zones, cells, dist), keys).join(anchor_inner(zones, cells, dist), keys)
    return out.select(*keys, "size", "mass", "eps_zone", "reach", "a_out", "a_in")


def satisfied(stats: DataFrame, e_min: float, kind: str = "a_out", eps: float | None = None) -> DataFrame:
    """Adds ``floor, ok``; eps None takes each zone's own budget."""
    budget = F.col("eps_zone") if eps is None else F.lit(float(eps))
    return stats.withColumn("floor", F.exp(budget) * F.lit(float(e_min))).withColumn("ok", F.col(kind) >= F.col("floor") - 1e-12)


def inner_outer_gap(stats: DataFrame, e_min: float) -> DataFrame:
    """Zones that pass the older test and fail the right one."""
    floor = F.exp("eps_zone") * F.lit(float(e_min))
    return stats.where((F.col("a_in") >= floor - 1e-12) & (F.col("a_out") < floor - 1e-12))


def whole(cells: DataFrame) -> DataFrame:
    """The zoning with one zone."""
    return cells.select("domain_id", "cell_id", F.lit(0).cast("long").alias("zone_id"))


def feasible(cells: DataFrame, dist: DataFrame, params: DataFrame) -> DataFrame:
    """For each ``(eps, e_min)`` of ``params``: does the whole domain clear the floor? By the union lemma exactly then some zoning does."""
    out = anchor_outer(whole(cells), cells, dist).select("domain_id", "a_out")
    floor = F.exp("eps") * F.col("e_min")
    return out.crossJoin(F.broadcast(params)).select("domain_id", "eps", "e_min", "a_out", floor.alias("floor"), (F.col("a_out") >= floor - 1e-12).alias("ok"))


def segments(ranked: DataFrame) -> DataFrame:
    """Every run a..b of a curve: ``domain_id, rot, a, b, mass, reach, a_out, a_in, eps_min``.

    Prefix sums along the curve for each guess, then differences for each run: n^3
    values per domain, all within one hash partitioning on (domain_id, rot).
    """
    keys = ["domain_id", "rot"]
    one = ranked.select(*keys, F.col("rank").alias("r"), "x", "y", "prior", "eps")
    g = one.select(*keys, F.col("r").alias("g"), F.col("x").alias("gx"), F.col("y").alias("gy"))
    d = F.sqrt(F.pow(F.col("x") - F.col("gx"), 2) + F.pow(F.col("y") - F.col("gy"), 2))
    dist = one.join(g, keys).select(*keys, "r", "g", "prior", "eps", d.alias("d"))
    starts = one.select(*keys, F.col("r").alias("a"))
    grown = starts.join(dist, keys).where("r >= a")
    run = W.partitionBy(*keys, "a", "g").orderBy("r").rowsBetween(W.unboundedPreceding, W.currentRow)
    grown = grown.select(*keys, "a", F.col("r").alias("b"), "g", F.sum(F.col("prior") * F.col("d")).over(run).alias("cost"), F.sum("prior").over(run).alias("mass"), F.max("d").over(run).alias("far"), F.min("eps").over(run).alias("eps_min"))
    member = (F.col("g") >= F.col("a")) & (F.col("g") <= F.col("b"))
    return grown.groupBy(*keys, "a", "b").agg(
        F.min("mass").alias("mass"), F.max(F.when(member, F.col("far"))).alias("reach"), F.min(F.col("cost") / F.col("mass")).alias("a_out"),
        F.min(F.when(member, F.col("cost") / F.col("mass"))).alias("a_in"), F.min("eps_min").alias("eps_min"),
    )
