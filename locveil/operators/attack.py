"""Bayesian adversaries that know the prior, the kernel and both parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def joint(kernel: DataFrame, cells: DataFrame) -> DataFrame:
    """``domain_id, i, j, w``: probability of true cell i and report j."""
    prior = cells.select("domain_id", F.col("cell_id").alias("i"), "prior")
    return kernel.join(prior, ["domain_id", "i"]).select("domain_id", "i", "j", (F.col("prior") * F.col("k")).alias("w"))


def evidence(kernel: DataFrame, cells: DataFrame) -> DataFrame:
    return joint(kernel, cells).groupBy("domain_id", "j").agg(F.sum("w").alias("pr"))


def posterior(kernel: DataFrame, cells: DataFrame) -> DataFrame:
    """``domain_id, j, i, post``; reports of probability 0 have none."""
    w = W.partitionBy("domain_id", "j")
    return joint(kernel, cells).withColumn("pr", F.sum("w").over(w)).where("pr > 0").select("domain_id", "j", "i", (F.col("w") / F.col("pr")).alias("post"))


def guess_costs(kernel: DataFrame, cells: DataFrame, dist: DataFrame, zones: DataFrame | None = None) -> DataFrame:
    """``domain_id, [zone_id,] j, g, cost``: joint expected distance of each guess (n^3 products; a matmul in groups for larger n)."""
    df = joint(kernel, cells)
    keys = ["domain_id"]
    if zones is not None:
        df = df.join(zones.select("domain_id", F.col("cell_id").alias("i"), "zone_id"), ["domain_id", "i"])
        keys = ["domain_id", "zone_id"]
    far = dist.select("domain_id", "i", F.col("j").alias("g"), "d")
    return df.join(far, ["domain_id", "i"]).groupBy(*keys, "j", "g").agg(F.sum(F.col("w") * F.col("d")).alias("cost"))


def _best(costs: DataFrame, keys: list[str]) -> DataFrame:
    best = costs.groupBy(*keys).agg(F.min(F.struct(F.round("cost", 12).alias("r"), "g", "cost")).alias("b"))
    return best.select(*keys, F.col("b.g").alias("guess_opt"), F.col("b.cost").alias("cost"))


def optimal(kernel: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """``domain_id, j, guess_opt, cost``: the guess of least expected distance, ties to the lower cell."""
    return _best(guess_costs(kernel, cells, dist), ["domain_id", "j"])


def known_zone(kernel: DataFrame, cells: DataFrame, dist: DataFrame, zones: DataFrame, narrow: bool = False) -> DataFrame:
    """An adversary that also knows the zone; ``narrow`` confines the guess to it: ``domain_id, zone_id, j, guess_opt, cost``."""
    costs = guess_costs(kernel, cells, dist, zones)
    if narrow:
        costs = costs.join(zones.select("domain_id", "zone_id", F.col("cell_id").alias("g")), ["domain_id", "zone_id", "g"], "left_semi")
    return _best(costs, ["domain_id", "zone_id", "j"])


def bayesian(kernel: DataFrame, cells: DataFrame) -> DataFrame:
    """``domain_id, j, guess_map, w``: the most probable cell, ties to the lower."""
    best = joint(kernel, cells).groupBy("domain_id", "j").agg(F.max(F.struct(F.round("w", 14).alias("r"), (-F.col("i")).alias("neg"), "w")).alias("b"))
    return best.select("domain_id", "j", (-F.col("b.neg")).alias("guess_map"), F.col("b.w").alias("w"))
