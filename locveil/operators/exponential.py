"""Report kernels ``domain_id, i, j, k``: exponential mechanisms over zones, constant reach, and none."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import lp


def _normalised(weights: DataFrame) -> DataFrame:
    return weights.select("domain_id", "i", "j", (F.col("w") / F.sum("w").over(W.partitionBy("domain_id", "i"))).alias("k"))


def generic_kernel(scores: DataFrame, eps: Column | float, sensitivity: Column | float) -> DataFrame:
    """Exponential mechanism for any ``scores(domain_id, i, j, score)``; weights exp(eps score / (2 sensitivity))."""
    eps = F.lit(eps) if isinstance(eps, (int, float)) else eps
    sensitivity = F.lit(sensitivity) if isinstance(sensitivity, (int, float)) else sensitivity
    return _normalised(scores.withColumn("w", F.exp(eps * F.col("score") / (2 * sensitivity))))


def sensitivity(zones: DataFrame, dist: DataFrame) -> DataFrame:
    """Largest change of the distance score between two cells of a zone, over all reports; equals the zone's reach."""
    a = zones.select("domain_id", "zone_id", F.col("cell_id").alias("i"))
    one = dist.join(a, ["domain_id", "i"]).select("domain_id", "zone_id", "j", "d")
    ends = one.groupBy("domain_id", "zone_id", "j").agg((F.max("d") - F.min("d")).alias("change"))
    return ends.groupBy("domain_id", "zone_id").agg(F.max("change").alias("sensitivity"))


def zonal_kernel(zones: DataFrame, stats: DataFrame, dist: DataFrame, eps: float | None = None) -> DataFrame:
    """Each zone's own reach as sensitivity; one budget for all, or with eps None the zone's least (personal)."""
    budget = F.col("eps_zone") if eps is None else F.lit(float(eps))
    scale = stats.select("domain_id", "zone_id", (budget / (2 * F.col("reach"))).alias("scale"))
    rows = zones.select("domain_id", F.col("cell_id").alias("i"), "zone_id").join(scale, ["domain_id", "zone_id"])
    return _normalised(dist.join(rows, ["domain_id", "i"]).select("domain_id", "i", "j", F.exp(-F.col("scale") * F.col("d")).alias("w")))


def constant_kernel(dist: DataFrame, reach: float | DataFrame, eps: float) -> DataFrame:
    """One reach for every row: a number, or ``(domain_id, reach)``."""
    df = dist.withColumn("reach", F.lit(float(reach))) if isinstance(reach, (int, float)) else dist.join(reach.select("domain_id", "reach"), "domain_id")
    return _normalised(df.select("domain_id", "i", "j", F.exp(-F.lit(float(eps)) * F.col("d") / (2 * F.col("reach"))).alias("w")))


def largest_reach(stats: DataFrame) -> DataFrame:
    return stats.groupBy("domain_id").agg(F.max("reach").alias("reach"))


def adaptive_kernel(per_cell: DataFrame, dist: DataFrame, eps: float | None = None) -> DataFrame:
    """The predecessor's: every row has the reach of its own zone."""
    budget = F.col("eps_zone") if eps is None else F.lit(float(eps))
    rows = per_cell.select("domain_id", F.col("cell_id").alias("i"), (budget / (2 * F.col("reach"))).alias("scale"))
    return _normalised(dist.join(rows, ["domain_id", "i"]).select("domain_id", "i", "j", F.exp(-F.col("scale") * F.col("d")).alias("w")))


def identity_kernel(dist: DataFrame) -> DataFrame:
    """No privacy."""
    return dist.select("domain_id", "i", "j", F.when(F.col("i") == F.col("j"), 1.0).otherwise(0.0).alias("k"))


def lp_kernel(cells: DataFrame, eps_g: float, delta: float = 0.05, d_min: float | None = None) -> DataFrame:
    """The linear programmes, one task per domain: ``domain_id, i, j, k, loss, gap, residual``."""
    from . import core

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("cell_id").reset_index(drop=True)
        d = core.distances(pdf["x"].to_numpy(), pdf["y"].to_numpy())
        s = lp.solve(pdf["prior"].to_numpy(), d, eps_g, delta, d_min)
        ids = pdf["cell_id"].to_numpy()
        n = len(ids)
        return pd.DataFrame({"domain_id": pdf["domain_id"].iloc[0], "i": ids.repeat(n), "j": list(ids) * n, "k": s.kernel.ravel(), "loss": s.loss, "gap": s.gap, "residual": s.residual})

    return cells.select("domain_id", "cell_id", "x", "y", "prior").groupBy("domain_id").applyInPandas(solve, "domain_id string, i long, j long, k double, loss double, gap double, residual double")


def packed(kernel: DataFrame) -> DataFrame:
    """``domain_id, i, outs array, cdf array``: one row per true cell, for sampling."""
    w = W.partitionBy("domain_id", "i").orderBy("j").rowsBetween(W.unboundedPreceding, W.currentRow)
    run = kernel.withColumn("c", F.sum("k").over(w))
    rows = run.groupBy("domain_id", "i").agg(F.array_sort(F.collect_list(F.struct("j", "c"))).alias("r"))
    return rows.select("domain_id", "i", F.col("r.j").alias("outs"), F.col("r.c").alias("cdf"))
