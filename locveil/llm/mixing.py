"""Mixing sources to target weights by pivotal dependent rounding.

Each source's target over its size is the number of copies every document of it
should get on average.  The whole part is certain; the fractional parts are rounded
by pivotal steps: two documents trade probability, weighted by size so that the
words of the source are kept exactly, until one of them is whole.  Buckets of
documents leave one fractional document per source each; these residuals meet in a
reduction tree until one is left, which goes to the nearer whole number.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._scratch import written
from ._tokens import mix

WORD = r"[^\x20\x09-\x0D]+"
# Weights of the sources by code point, repeating, and the share of all words.
WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
CAP = 2.0

#: Documents in a bucket on average, and residual buckets that meet in one task.
BUCKET_ROWS = 8192
FAN_IN = 32


def targets(sizes: list[tuple[str | None, int]], share: float = SHARE, cap: float = CAP, weights: tuple[float, ...] = WEIGHTS) -> list[float]:
    """Words to take of each source, given in order: ``share`` of all by weight, at most ``cap`` times a source, the excess reshared."""
    size = np.array([s for _, s in sizes], np.float64)
    weight = np.array([weights[i % len(weights)] for i in range(len(sizes))])
    most, total = cap * size, share * size.sum()
    out, open_ = np.zeros(len(sizes)), np.ones(len(sizes), bool)
    while open_.any():
        left = max(0.0, total - out[~open_].sum())
        out[open_] = left * weight[open_] / weight[open_].sum()
        over = open_ & (out > most)
        if not over.any():
            break
        out[over] = most[over]
        open_ &= ~over
    return out.tolist()


def pivot(key: np.ndarray, size: np.ndarray, part: np.ndarray, seed: int) -> np.ndarray:
    """Round fractional ``part`` of one source until at most one is fractional; sum(size * part) stays.

    Expected values stay too.  Random numbers are a function of the keys and the seed.
    """
    x = part.copy()
    open_ = -1
    draw = [float(v) for v in _stream(key, seed)]
    for i in range(len(x)):
        if not 0 < x[i] < 1:
            continue
        if open_ < 0:
            open_ = i
            continue
        a, b = float(size[open_]), float(size[i])
        up = min(a * (1 - x[open_]), b * x[i])
        down = min(a * x[open_], b * (1 - x[i]))
        if draw[i] * (up + down) < down:
            x[open_], x[i] = x[open_] + up / a, x[i] - up / b
        else:
            x[open_], x[i] = x[open_] - down / a, x[i] + down / b
        for j in (open_, i):
            if x[j] < 1e-9:
                x[j] = 0.0
            elif x[j] > 1 - 1e-9:
                x[j] = 1.0
        if not 0 < x[open_] < 1:
            open_ = i if 0 < x[i] < 1 else -1
    return x


def _stream(key: np.ndarray, seed: int) -> np.ndarray:
    at = np.arange(len(key), dtype=np.uint64)
    step = np.uint64(seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    h = mix(mix(key.view(np.uint64) + step) ^ (at * np.uint64(0xD1342543DE82EF95)))
    return (h >> np.uint64(11)).astype(np.float64) / (1 << 53)


_ROW = "doc_id long, source string, size long, source_size long, target double, whole long, part double, key long, bucket long"


def sized(docs: DataFrame) -> DataFrame:
    """``doc_id, source, size``: words of each whole text, 0 for null."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))


def mix_sources(docs: DataFrame, seed: int = 17, share: float = SHARE, cap: float = CAP, weights: tuple[float, ...] = WEIGHTS) -> DataFrame:
    """``doc_id, source, size, source_size, target, copies, taken`` for every row of ``docs`` (``doc_id, text, source``).

    A source's taken words miss its target by at most half of its last residual document.
    Documents of size 0 are taken 0 times as words; a source without words has
    target 0.  A null source is a source, last in order; rows that repeat are rows
    of their own; an empty table gives an empty table.  The result is a function of
    the rows, whatever their order and partitions.
    """
    spark: SparkSession = docs.sparkSession
    sizes = written(sized(docs), "sizes")  # texts are read once
    # One row per source reaches the driver: a few numbers each, as many as there are sources.
    stats = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("rows")).collect()
    stats = sorted(stats, key=lambda r: (r["source"] is None, r["source"] or ""))
    goal = targets([(r["source"], r["source_size"]) for r in stats], share, cap, weights)
    plan = [(r["source"], r["source_size"], t, min(cap, t / r["source_size"]) if r["source_size"] else 0.0) for r, t in zip(stats, goal, strict=True)]
    table = spark.createDataFrame(plan, "source string, source_size long, target double, rate double")
    if len(plan) < 100_000:
        table = F.broadcast(table)
    buckets = max(1, -(-sum(r["rows"] for r in stats) // BUCKET_ROWS))
    rows = sizes.alias("d").join(table.alias("t"), F.col("d.source").eqNullSafe(F.col("t.source"))).select("doc_id", "d.source", "size", "source_size", "target", F.floor("rate").alias("whole"), (F.col("rate") - F.floor("rate")).alias("part"))
    rows = rows.withColumn("part", F.when(F.col("size") > 0, F.col("part")).otherwise(F.lit(0.0))).withColumn("key", F.xxhash64("doc_id", "size", "source", F.lit(seed))).withColumn("bucket", F.pmod("key", F.lit(buckets)))
    names = [f.name for f in T._parse_datatype_string(_ROW).fields]
    rows = rows.select(*names)
    done = None
    level = 0
    while True:
        left = buckets > 1

        got = rows.groupBy("bucket").applyInPandas(_rounding(seed + 1 + level, last=not left), _ROW)
        if not left:
            done = got if done is None else done.unionByName(got)
            break
        got = written(got, "mix")
        whole = got.where("part = 0 or part = 1")
        done = whole if done is None else done.unionByName(whole)
        buckets = -(-buckets // FAN_IN)
        rows = got.where("part > 0 and part < 1").withColumn("bucket", F.floor(F.col("bucket") / FAN_IN)).select(*names)
        level += 1
    copies = (F.col("whole") + F.col("part").cast("long")).alias("copies")
    return done.select("doc_id", "source", "size", "source_size", "target", copies).withColumn("taken", F.col("copies") * F.col("size"))


def _rounding(seed: int, last: bool):
    return lambda pdf: _round_bucket(pdf, seed, last)


def _round_bucket(pdf: pd.DataFrame, seed: int, last: bool) -> pd.DataFrame:
    # Large documents first: the one left open in the end is then small, and so is the miss.
    pdf = pdf.sort_values(["source", "size", "key", "doc_id"], ascending=[True, False, True, True], na_position="last", kind="stable").reset_index(drop=True)
    part = pdf["part"].to_numpy(np.float64).copy()
    key, size = pdf["key"].to_numpy(np.int64), pdf["size"].to_numpy(np.int64)
    source = pdf["source"].factorize()[0]  # rows of a source are neighbours, and null has a number of its own
    for at in np.split(np.arange(len(source)), np.flatnonzero(np.diff(source)) + 1):
        x = pivot(key[at], size[at], part[at], seed)
        if last:
            open_ = np.flatnonzero((x > 0) & (x < 1))
            if len(open_):
                i = open_[0]
                x[i] = float(x[i] >= 0.5)
        part[at] = x
    return pdf.assign(part=part)
