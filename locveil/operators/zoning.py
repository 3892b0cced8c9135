"""Zonings: curve walk, quasi-k-means, the adaptive predecessor, exact references and a validator."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import core, geometry

ZONES = "domain_id string, eps_param double, e_min double, rot int, status string, avg_reach double, cell_id long, zone_id long"


def with_params(cells: DataFrame, params: list[tuple[float | None, float]]) -> DataFrame:
    """Cells for each (eps, e_min); eps None keeps the cells' own budgets. A grid is one plan, not a loop."""
    spark = cells.sparkSession
    table = spark.createDataFrame([(e, m) for e, m in params], "eps_param double, e_min double")
    df = cells if "eps" in cells.columns else cells.withColumn("eps", F.lit(1.0))
    df = df.crossJoin(F.broadcast(table))
    return df.withColumn("eps", F.coalesce("eps_param", "eps")).withColumn("eps_param", F.coalesce("eps_param", F.lit(-1.0)))


def _zoned(pdf: pd.DataFrame, rot: int, zones: list[np.ndarray] | None, d: np.ndarray) -> pd.DataFrame:
    p = pdf["prior"].to_numpy()
    base = {"domain_id": pdf["domain_id"].iloc[0], "eps_param": pdf["eps_param"].iloc[0], "e_min": pdf["e_min"].iloc[0], "rot": rot}
    if zones is None:
        return pd.DataFrame([base | {"status": "infeasible", "avg_reach": None, "cell_id": None, "zone_id": None}]).astype({"avg_reach": "float64", "cell_id": "Int64", "zone_id": "Int64"})
    ids = pdf["cell_id"].to_numpy()
    zone = np.empty(len(ids), np.int64)
    for z in zones:
        zone[z] = ids[z].min()
    return pd.DataFrame(base | {"status": "ok", "avg_reach": core.average_reach(zones, p, d), "cell_id": ids, "zone_id": zone})


def _arrays(pdf: pd.DataFrame):
    pdf = pdf.sort_values("cell_id").reset_index(drop=True)
    d = core.distances(pdf["x"].to_numpy(), pdf["y"].to_numpy())
    return pdf, d, pdf["prior"].to_numpy(), pdf["eps"].to_numpy()


def zone_curve(cells: DataFrame, params: list[tuple[float | None, float]], rots: tuple[int, ...] = (0,), kind: str = "outer", exact: bool = False, order: int | None = None) -> DataFrame:
    """Curve zoning for each domain, parameter pair and rotation (exact: the best contiguous zoning instead).

    zone_id is the least cell_id of a zone; an infeasible domain gives one row with
    that status.
    """
    ranked = _ranked_params(cells, params, rots, order)
    return ranked.groupBy("domain_id", "eps_param", "e_min", "rot").applyInPandas(lambda pdf: walked(pdf, kind, exact), ZONES)


def walked(pdf: pd.DataFrame, kind: str = "outer", exact: bool = False) -> pd.DataFrame:
    """The curve zoning of one domain, parameter pair and rotation."""
    pdf, d, p, eps = _arrays(pdf)
    at = np.argsort(pdf["rank"].to_numpy())
    seg = core.segment_table(at, p, d, eps)
    e_min = float(pdf["e_min"].iloc[0])
    runs = core.best_contiguous(seg, e_min) if exact else core.curve_walk(seg, d[np.ix_(at, at)], e_min, kind)
    return _zoned(pdf, int(pdf["rot"].iloc[0]), None if runs is None else [at[a : b + 1] for a, b in runs], d)


def _ranked_params(cells: DataFrame, params, rots, order) -> DataFrame:
    ranked = geometry.rank_on_curve(cells, order, rots)
    return with_params(ranked, params).select("domain_id", "eps_param", "e_min", "rot", "rank", "cell_id", "x", "y", "prior", "eps")


def zone_best_curve(cells: DataFrame, params: list[tuple[float | None, float]], order: int | None = None) -> DataFrame:
    """The rotation of least average reach among four; ties to the lowest."""
    zones = zone_curve(cells, params, (0, 1, 2, 3), order=order)
    keys = W.partitionBy("domain_id", "eps_param", "e_min")
    best = F.min(F.struct(F.coalesce(F.round("avg_reach", 12), F.lit(float("inf"))), "rot")).over(keys)
    return zones.withColumn("best", best).where(F.col("rot") == F.col("best.rot")).drop("best")


def zone_qkm(cells: DataFrame, params: list[tuple[float | None, float]], max_samp: int = 20, max_iter: int = 20, tol: float = 1e-6, min_size: int = 2, lam: float | None = None, linkage: str = "centre", patience: int = 0, seed: int = 0) -> DataFrame:
    """Quasi-k-means zoning, one task for each domain and parameter pair; ``qkm_by_k`` spreads one domain's search wider.

    Restarts depend on (k, restart, seed) alone, so both ways agree.
    """
    live = with_params(cells, params).select("domain_id", "eps_param", "e_min", "cell_id", "x", "y", "prior", "eps")
    how = {"max_samp": max_samp, "patience": patience, "max_iter": max_iter, "tol": tol, "min_size": min_size, "lam": lam, "linkage": linkage, "seed": seed}
    return live.groupBy("domain_id", "eps_param", "e_min").applyInPandas(lambda pdf: searched(pdf, **how), ZONES)


def searched(pdf: pd.DataFrame, **how) -> pd.DataFrame:
    """The quasi-k-means zoning of one domain and parameter pair."""
    pdf, d, p, eps = _arrays(pdf)
    zone = core.choose_zoning(p, pdf[["x", "y"]].to_numpy(), d, eps, float(pdf["e_min"].iloc[0]), **how)
    return _zoned(pdf, 0, None if zone is None else [np.flatnonzero(zone == z) for z in np.unique(zone)], d)


def qkm_by_k(cells: DataFrame, params: list[tuple[float | None, float]], ks: list[int], max_samp: int = 20, **how) -> DataFrame:
    """``..., k, avg_reach``: the best restart for each k, all k and restarts in parallel (null where none is feasible)."""
    spark = cells.sparkSession
    grid = spark.createDataFrame([(k, s) for k in ks for s in range(max_samp)], "k int, restart int")
    df = with_params(cells, params).select("domain_id", "eps_param", "e_min", "cell_id", "x", "y", "prior", "eps").crossJoin(F.broadcast(grid))

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf, d, p, eps = _arrays(pdf)
        k, s = int(pdf["k"].iloc[0]), int(pdf["restart"].iloc[0])
        got = core.quasi_k_means(k, s, p, pdf[["x", "y"]].to_numpy(), d, eps, float(pdf["e_min"].iloc[0]), **how)
        return pd.DataFrame({"domain_id": [pdf["domain_id"].iloc[0]], "eps_param": [pdf["eps_param"].iloc[0]], "e_min": [pdf["e_min"].iloc[0]], "k": [k], "avg_reach": [got[0] if got else np.nan]})

    got = df.groupBy("domain_id", "eps_param", "e_min", "k", "restart").applyInPandas(one, "domain_id string, eps_param double, e_min double, k int, avg_reach double")
    return got.groupBy("domain_id", "eps_param", "e_min", "k").agg(F.min(F.when(~F.isnan("avg_reach"), F.col("avg_reach"))).alias("avg_reach"))


def choose_k(by_k: DataFrame) -> DataFrame:
    """First k without a feasible clustering, or of larger average reach than k - 1, ends the search; the answer is the k before."""
    w = W.partitionBy("domain_id", "eps_param", "e_min").orderBy("k")
    before = F.lag("avg_reach").over(w)
    stop = F.col("avg_reach").isNull() | (F.col("avg_reach") > before + 1e-12)
    return by_k.withColumn("stop", stop).groupBy("domain_id", "eps_param", "e_min").agg((F.coalesce(F.min(F.when(F.col("stop"), F.col("k"))), F.max("k") + 1) - 1).cast("long").alias("k_best"))


def zone_per_cell(segments: DataFrame, ranked: DataFrame, e_min: float, search_range: int = 10, kind: str = "a_in") -> DataFrame:
    """The adaptive predecessor: for each true cell the run of least reach around it that passes its own test.

    Zones overlap and differ in reach.  ``domain_id, rot, cell_id, a, b, reach, eps_zone``.
    """
    near = segments.where((F.col("b") - F.col("a") < search_range) & (F.col("b") > F.col("a")))
    near = near.where(F.col(kind) >= F.exp("eps_min") * F.lit(float(e_min)) - 1e-12)
    # A run of bounded length covers few ranks: unfolding them turns the range join into an equi-join.
    cover = near.withColumn("rank", F.explode(F.sequence("a", "b"))).withColumn("rank", F.col("rank").cast("int"))
    mine = ranked.select("domain_id", "rot", "cell_id", F.col("rank").cast("int").alias("rank"))
    best = mine.join(cover, ["domain_id", "rot", "rank"]).groupBy("domain_id", "rot", "cell_id").agg(F.min(F.struct(F.round("reach", 12).alias("r"), "a", "b", "reach", "eps_min")).alias("z"))
    return best.select("domain_id", "rot", "cell_id", F.col("z.a").cast("long").alias("a"), F.col("z.b").cast("long").alias("b"), F.col("z.reach").alias("reach"), F.col("z.eps_min").alias("eps_zone"))


def overlaps(per_cell: DataFrame) -> DataFrame:
    """Pairs of the predecessor's zones that share cells without being equal."""
    z = per_cell.select("domain_id", "rot", "a", "b", "reach").distinct()
    left = z.withColumn("rank", F.explode(F.sequence("a", "b")))
    right = z.select("domain_id", "rot", F.col("a").alias("a2"), F.col("b").alias("b2"), F.col("reach").alias("reach2")).withColumn("rank", F.explode(F.sequence("a2", "b2")))
    both = left.join(right, ["domain_id", "rot", "rank"]).where("a < a2 or (a = a2 and b < b2)")
    return both.groupBy("domain_id", "rot", "a", "b", "a2", "b2").agg(F.count("*").alias("shared"), F.first(F.abs(F.col("reach") - F.col("reach2")) > 1e-12).alias("reach_differs"))


def common_reach(per_cell: DataFrame) -> DataFrame:
    """First repair of the predecessor: overlapping zones, all with the largest reach."""
    return per_cell.withColumn("reach", F.max("reach").over(W.partitionBy("domain_id", "rot")))


def best_partition(cells: DataFrame, params: list[tuple[float | None, float]]) -> DataFrame:
    """Exact optimum over all set partitions (a dozen cells at most)."""

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf, d, p, eps = _arrays(pdf)
        if len(pdf) > 12:
            raise ValueError("exhaustive search takes at most 12 cells")
        blocks = core.best_zoning(p, d, eps, float(pdf["e_min"].iloc[0]))
        return _zoned(pdf, 0, None if blocks is None else [np.array(b) for b in blocks], d)

    df = with_params(cells, params).select("domain_id", "eps_param", "e_min", "cell_id", "x", "y", "prior", "eps")
    return df.groupBy("domain_id", "eps_param", "e_min").applyInPandas(search, ZONES)


def blocks_by_id(cells: DataFrame, size: int = 5) -> DataFrame:
    """A plain zoning by runs of cell_id, for checks of kernels and measures."""
    return cells.select("domain_id", "cell_id", (F.floor(F.col("cell_id") / size) * size).cast("long").alias("zone_id"))


def validate(zones: DataFrame, cells: DataFrame, stats: DataFrame, e_min: float, min_size: int = 2) -> DataFrame:
    """``domain_id, uncovered, doubled, small, below_floor``: all zero for a valid zoning."""
    member = zones.select("domain_id", "cell_id", "zone_id")
    missing = cells.join(member, ["domain_id", "cell_id"], "left_anti").groupBy("domain_id").agg(F.count("*").alias("uncovered"))
    twice = member.groupBy("domain_id", "cell_id").count().groupBy("domain_id").agg(F.sum(F.when(F.col("count") > 1, 1).otherwise(0)).alias("doubled"))
    floor = F.exp("eps_zone") * F.lit(float(e_min)) - 1e-9
    bad = stats.groupBy("domain_id").agg(F.count_if(F.col("size") < min_size).alias("small"), F.count_if(F.col("a_out") < floor).alias("below_floor"))
    out = twice.join(bad, "domain_id", "full").join(missing, "domain_id", "left")
    return out.select("domain_id", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("uncovered", "doubled", "small", "below_floor")))


def zone_arrays(zones: DataFrame) -> DataFrame:
    """Compact form: one sorted array of cells for each zone."""
    return zones.groupBy("domain_id", "zone_id").agg(F.array_sort(F.collect_list("cell_id")).alias("cells"))


Zoning = Callable[[DataFrame, list[tuple[float | None, float]]], DataFrame]
