"""Approximate nearest neighbours by a forest of hash prefixes, in blocks.

Each block of vectors holds one sorted array of long hash strings (signs of random
projections) per tree.  A query descends to its longest matching prefix in every
tree, then all trees ascend together, one bit at a time, until the ranges hold
enough candidates; these are scored exactly.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TREES = 32
BITS = 32
BLOCK = 16_384
QUERY_BLOCK = 4_096
#: Candidates to reach while ascending, counted over all trees, as a multiple of the block's rows.
DEPTH = 1.0
#: Different candidates of a block to reach in any case (all, in a smaller block).
LEAST = 64

_ROW = "query_id long, vec_id long, score double"


def _planes(dim: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed * 1000 + dim).normal(size=(dim, TREES * BITS))


def _strings(x: np.ndarray, planes: np.ndarray) -> np.ndarray:
    """Hash strings as integers, most significant bit first: (row, tree)."""
    bits = ((x @ planes) > 0).reshape(len(x), TREES, BITS)
    return bits @ (np.uint64(1) << np.arange(BITS - 1, -1, -1, dtype=np.uint64))


def candidates(keys: np.ndarray, asked: np.ndarray, depth: float) -> list[np.ndarray]:
    """Rows of the block each asked string set reaches (keys and asked: row by tree)."""
    n = len(keys)
    want = min(depth * n, TREES * n)
    order = [np.argsort(keys[:, t], kind="stable") for t in range(TREES)]
    arrays = [keys[o, t] for t, o in enumerate(order)]
    lows, highs = np.zeros((BITS + 1, len(asked), TREES), np.int64), np.zeros((BITS + 1, len(asked), TREES), np.int64)
    for level in range(BITS + 1):
        rest = np.uint64((1 << (BITS - level)) - 1)
        for t in range(TREES):
            lows[level, :, t] = np.searchsorted(arrays[t], asked[:, t] & ~rest, "left")
            highs[level, :, t] = np.searchsorted(arrays[t], asked[:, t] | rest, "right")
    reached = (highs - lows).sum(2)  # grows as the level falls
    out = []
    for q in range(len(asked)):
        level = int(np.flatnonzero(reached[:, q] >= want).max())
        while True:
            seen = np.zeros(n, bool)
            for t in range(TREES):
                seen[order[t][lows[level, q, t] : highs[level, q, t]]] = True
            found = np.flatnonzero(seen)
            if len(found) >= min(n, LEAST) or level == 0:
                break
            level -= 1  # the same few rows in many trees
        out.append(found)
    return out


def _scaled(v: np.ndarray) -> np.ndarray:
    """Each row by a power of two, which is exact, so that squares neither vanish nor overflow."""
    _, power = np.frexp(np.abs(v).max(1))
    half = -power // 2  # in two steps, as 2^-power itself may overflow
    return np.ldexp(np.ldexp(v, half[:, None]), (-power - half)[:, None])


def _search(queries: pd.DataFrame, rows: pd.DataFrame, k: int, depth: float, seed: int) -> pd.DataFrame:
    if not len(queries) or not len(rows):
        return pd.DataFrame({"query_id": pd.Series(dtype="int64"), "vec_id": pd.Series(dtype="int64"), "score": pd.Series(dtype="float64")})
    q, x = np.stack(queries["v"].to_numpy()).astype(np.float64), np.stack(rows["v"].to_numpy()).astype(np.float64)
    ids, qids = rows["vec_id"].to_numpy(np.int64), queries["vec_id"].to_numpy(np.int64)
    q, x = _scaled(q), _scaled(x)
    size, qsize = np.sqrt((x * x).sum(1)), np.sqrt((q * q).sum(1))
    planes = _planes(x.shape[1], seed)
    found = candidates(_strings(x / size[:, None], planes), _strings(q / qsize[:, None], planes), depth)
    made = []
    for i, at in enumerate(found):
        at = at[ids[at] != qids[i]]
        score = (x[at] * q[i]).sum(1) / (size[at] * qsize[i])  # each row by itself: equal vectors score alike wherever they are
        best = np.lexsort((ids[at], -score))
        _, first = np.unique(ids[at][best], return_index=True)
        best = best[np.sort(first)[:k]]
        made.append(pd.DataFrame({"query_id": qids[i], "vec_id": ids[at][best], "score": score[best]}))
    return pd.concat(made, ignore_index=True)


def usable(vectors: DataFrame) -> DataFrame:
    """``vec_id, v, dim`` of the vectors that take part: no null, all components finite, not zero."""
    v = F.col("embedding").cast("array<double>")
    bad = lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
    df = vectors.where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))
    return df.where(~F.exists("v", bad) & F.exists("v", lambda c: c != 0)).select("vec_id", "v", F.size("v").alias("dim"))


def nearest(vectors: DataFrame, every: int = 50, k: int = 5, depth: float = DEPTH, seed: int = 3) -> DataFrame:
    """``query_id, rank, vec_id, score``: for each row with ``vec_id % every == 0``, its k nearest found by cosine.

    Candidates are all other vec_ids of the same dimension; ties go to the smaller
    vec_id; rows that repeat a vec_id count once, with their best score.  Null, zero
    or non-finite vectors and null ids take no part.  Fewer candidates give fewer
    rows; an empty table gives none.
    """
    rows = usable(vectors)
    asked = rows.where(F.col("vec_id") % every == 0)
    n, m = rows.count(), asked.count()
    blocks, asks = max(1, -(-n // BLOCK)), max(1, -(-m // QUERY_BLOCK))
    # Every query block meets every block of rows, as the whole table is to be searched.
    left = asked.withColumn("ask", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(asks)).cast("int")).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = rows.withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(2)), F.lit(blocks)).cast("int")).withColumn("ask", F.explode(F.sequence(F.lit(0), F.lit(asks - 1))))

    def met(queries: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
        return _search(queries, own, k, depth, seed)

    keys = ["dim", "ask", "block"]
    found = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(met, _ROW)
    found = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    ranked = found.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("far"), "vec_id"))), 1, k).alias("best"))
    out = ranked.select("query_id", F.posexplode("best").alias("at", "b"))
    return out.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("b.vec_id").alias("vec_id"), (-F.col("b.far")).alias("score"))
