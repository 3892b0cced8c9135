"""Distances, reaches and the Hilbert order of domains."""

from __future__ import annotations

from math import ceil, log2

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import distance, hilbert


def pairs(cells: DataFrame, metric: str = "euclidean") -> DataFrame:
    """``domain_id, i, j, d`` of all ordered pairs within a domain (n^2 rows each; n is bounded by tiling)."""
    a = cells.select("domain_id", F.col("cell_id").alias("i"), F.col("x").alias("xa"), F.col("y").alias("ya"))
    b = cells.select("domain_id", F.col("cell_id").alias("j"), F.col("x").alias("xb"), F.col("y").alias("yb"))
    d = distance(F.col("xa"), F.col("ya"), F.col("xb"), F.col("yb"), metric)
    return a.join(b, "domain_id").select("domain_id", "i", "j", d.cast("double").alias("d"))


def reach(zones: DataFrame, dist: DataFrame) -> DataFrame:
    """``domain_id, zone_id, reach``: largest distance inside each zone."""
    a = zones.select("domain_id", "zone_id", F.col("cell_id").alias("i"))
    b = zones.select("domain_id", "zone_id", F.col("cell_id").alias("j"))
    return dist.join(a, ["domain_id", "i"]).join(b, ["domain_id", "zone_id", "j"]).groupBy("domain_id", "zone_id").agg(F.max("d").alias("reach"))


def shifted(cells: DataFrame) -> DataFrame:
    """Adds ``gx, gy``: grid coordinates from 0."""
    w = W.partitionBy("domain_id")
    return cells.withColumn("gx", F.col("cx") - F.min("cx").over(w)).withColumn("gy", F.col("cy") - F.min("cy").over(w))


def curve_order(cells: DataFrame) -> int:
    """Bits of the smallest square that holds every domain (one small aggregate)."""
    span = shifted(cells).agg(F.max(F.greatest("gx", "gy"))).first()[0] or 0
    return max(1, ceil(log2(span + 1)))


def rank_on_curve(cells: DataFrame, order: int | None = None, rots: tuple[int, ...] = (0,)) -> DataFrame:
    """Adds ``rot, h, rank`` (from 0): one copy of the cells for each rotation of the curve."""
    order = order or curve_order(cells)
    df = shifted(cells).withColumn("rot", F.explode(F.array(*(F.lit(r) for r in rots))))
    df = df.withColumn("h", hilbert("gx", "gy", order, F.col("rot")))
    by = W.partitionBy("domain_id", "rot").orderBy("h", "cell_id")
    return df.withColumn("rank", F.row_number().over(by) - 1).drop("gx", "gy")


def curve_gap(ranked: DataFrame) -> DataFrame:
    """Neighbours in the plane and how far apart they are on the curve: ``domain_id, rot, i, j, gap``."""
    a = ranked.select("domain_id", "rot", F.col("cell_id").alias("i"), "cx", "cy", F.col("rank").alias("ra"))
    steps = F.explode(F.array(F.struct(F.lit(1).alias("sx"), F.lit(0).alias("sy")), F.struct(F.lit(0).alias("sx"), F.lit(1).alias("sy"))))
    a = a.withColumn("s", steps).select("domain_id", "rot", "i", "ra", (F.col("cx") + F.col("s.sx")).alias("cx"), (F.col("cy") + F.col("s.sy")).alias("cy"))
    b = ranked.select("domain_id", "rot", F.col("cell_id").alias("j"), "cx", "cy", F.col("rank").alias("rb"))
    return a.join(b, ["domain_id", "rot", "cx", "cy"]).select("domain_id", "rot", "i", "j", F.abs(F.col("ra") - F.col("rb")).cast("long").alias("gap"))


def isolation(dist: DataFrame) -> DataFrame:
    """``domain_id, cell_id, nearest, isolation_rank``: cells far from all others rank last."""
    near = dist.where("i <> j").groupBy("domain_id", F.col("i").alias("cell_id")).agg(F.min("d").alias("nearest"))
    return near.withColumn("isolation_rank", F.row_number().over(W.partitionBy("domain_id").orderBy("nearest", "cell_id")).cast("long"))


def snap(pings: DataFrame, cells: DataFrame) -> DataFrame:
    """Nearest cell of each ping outside the grid, ties to the lower cell_id.

    The search runs once for each place, not for each ping: distances are between the
    distinct places and the cells (at most some dozens a domain), and pings join the result.
    """
    spot = ["domain_id", "cx", "cy"] if "domain_id" in pings.columns else ["cx", "cy"]
    side = cells.select("domain_id", "cell_id", "x", "y")
    at = pings.select(*spot).distinct()
    near = at.join(side, "domain_id") if len(spot) == 3 else at.crossJoin(side)
    d = distance(F.col("cx") + 0.5, F.col("cy") + 0.5, F.col("x"), F.col("y"))
    best = near.groupBy("domain_id", "cx", "cy").agg(F.min(F.struct(d.alias("d"), "cell_id")).alias("b"))
    return pings.join(best, spot).select("domain_id", "event_id", F.col("b.cell_id").alias("cell_id"), F.col("b.d").alias("d"))


def is_convex_in(cells: DataFrame, zones: DataFrame) -> DataFrame:
    """``domain_id, zone_id, convex``: no other cell of the domain lies in the zone's hull (a grouped function, for checks)."""

    def check(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        xy = pdf[["x", "y"]].to_numpy()
        for z, at in pdf.groupby("zone_id").indices.items():
            hull = _hull(xy[at])
            rest = np.setdiff1d(np.arange(len(pdf)), at)
            out.append((pdf["domain_id"].iloc[0], int(z), not any(_within(xy[r], hull) for r in rest)))
        return pd.DataFrame(out, columns=["domain_id", "zone_id", "convex"])

    return cells.join(zones.select("domain_id", "cell_id", "zone_id"), ["domain_id", "cell_id"]).groupBy("domain_id").applyInPandas(check, "domain_id string, zone_id long, convex boolean")


def _cross(o, a, b) -> float:
    return (a[0] - o[0]) * (b[1] - o[1]) - (a[1] - o[1]) * (b[0] - o[0])


def _hull(points: np.ndarray) -> list:
    pts = sorted(map(tuple, points))
    if len(pts) < 3:
        return pts
    half = []
    for seq in (pts, pts[::-1]):
        part: list = []
        for q in seq:
            while len(part) > 1 and _cross(part[-2], part[-1], q) <= 0:
                part.pop()
            part.append(q)
        half += part[:-1]
    return half


def _within(q: np.ndarray, hull: list) -> bool:
    if len(hull) < 3:
        return False
    return all(_cross(hull[i], hull[(i + 1) % len(hull)], q) >= 0 for i in range(len(hull)))
