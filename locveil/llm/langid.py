"""Language ID: sparse multinomial logistic regression on TF-IDF character n-grams (FTRL, elastic net, temperature)."""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tokens import pieces
from .quality import fold_of

#: Buckets of character n-grams; bucket 0 stands for none.
BUCKETS = 1 << 16
ORDERS = (1, 2, 3)
#: About this many labelled rows at most (by a hash of doc_id) train the model.
MAX_LABELLED = 2_000

_SALT = [np.uint32(0x9E3779B1), np.uint32(0x85EBCA77), np.uint32(0xC2B2AE3D), np.uint32(0x27D4EB2F)]


def _fold_table() -> np.ndarray:
    """Code point to its lower-case letter; 0 for what is no letter."""
    table = np.zeros(0x110000, np.uint32)
    for c in range(0x110000):
        ch = chr(c)
        if unicodedata.category(ch)[0] == "L":
            low = ch.lower()
            table[c] = ord(low) if len(low) == 1 else c
    return table


_fold: list[np.ndarray] = []


def _grams(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, list[np.ndarray]]]:
    """For each piece: first row, end row, row offsets in code points, letters, and a bucket array for each order."""
    if not _fold:
        _fold.append(_fold_table())
    for row, end, data, offsets in pieces(column):
        points = np.frombuffer(data.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
        ahead = np.zeros(len(data) + 1, np.int64)
        np.cumsum((data & 0xC0) != 0x80, out=ahead[1:])
        at = ahead[offsets]
        low = _fold[0][np.minimum(points, 0x10FFFF)]
        made = []
        for order in ORDERS:
            wide = max(len(low) - order + 1, 0)
            h = np.full(wide, order, np.uint32)
            some = np.zeros(wide, bool)
            for j in range(order):
                h = (h ^ low[j : j + wide]) * _SALT[j]
                h ^= h >> np.uint32(15)
                some |= low[j : j + wide] > 0
            h = (h * _SALT[3]) >> np.uint32(16)
            h = np.where(some, np.maximum(h, 1), 0).astype(np.int64)
            for back in range(1, order):  # n-grams that would reach into the next text
                over = at[1:-1] - back
                h[over[(over >= 0) & (over < wide)]] = 0
            full = np.zeros(len(low), np.int64)
            full[:wide] = h
            made.append(full)
        yield row, end, at, low, made


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """Documents each bucket occurs in, over all texts, and the number of texts; one fixed-size table per task."""

    def counted(batches):
        total, n = np.zeros(BUCKETS, np.int64), 0
        for batch in batches:
            n += batch.num_rows
            for row, end, at, _, made in _grams(batch.column(0)):
                for r in range(end - row):
                    seen = np.zeros(BUCKETS, bool)
                    for g in made:
                        seen[g[at[r] : at[r + 1]]] = True
                    total += seen
        total[0] = n
        for block in range(64):
            own = total[block * (BUCKETS // 64) : (block + 1) * (BUCKETS // 64)]
            if own.any():
                yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([own], pa.list_(pa.int64()))], ["block", "part"])

    parts = docs.select("text").mapInArrow(counted, "block int, part array<long>")
    cells = parts.select("block", F.posexplode("part").alias("cell", "v")).groupBy("block", "cell").agg(F.sum("v").alias("v")).where("v > 0").toPandas()
    out = np.zeros(BUCKETS, np.int64)
    out[cells["block"].to_numpy(np.int64) * (BUCKETS // 64) + cells["cell"].to_numpy(np.int64)] = cells["v"].to_numpy(np.int64)
    n = int(out[0])
    out[0] = 0
    return out, n


class Model(NamedTuple):
    classes: list[str]
    table: np.ndarray  # bucket x class: idf times weight
    bias: np.ndarray
    temperature: float


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def fit_ftrl(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, k: int, alpha: float = 2.0, beta: float = 1.0, l1: float = 1e-3, l2: float = 1e-4, epochs: int = 4, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Follow the regularised leader, per coordinate, over sparse rows; elastic-net penalties leave most weights zero."""
    z, s = np.zeros((BUCKETS, k)), np.zeros((BUCKETS, k))
    zb, sb = np.zeros(k), np.zeros(k)
    rng = np.random.default_rng(seed)

    def weights(z, s, l1):
        return np.where(np.abs(z) <= l1, 0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(s)) / alpha + l2))

    for _ in range(epochs):
        for r in rng.permutation(len(rows)):
            at, x = rows[r]
            w, b = weights(z[at], s[at], l1), weights(zb, sb, 0)
            g = _softmax(x @ w + b)
            g[y[r]] -= 1
            gw = x[:, None] * g
            z[at] += gw - (np.sqrt(s[at] + gw * gw) - np.sqrt(s[at])) / alpha * w
            s[at] += gw * gw
            zb += g - (np.sqrt(sb + g * g) - np.sqrt(sb)) / alpha * b
            sb += g * g
    return weights(z, s, l1), weights(zb, sb, 0)


def train(docs: DataFrame) -> Model:
    """Fit on a hash sample of the labelled rows outside the held-out fold; IDF from all texts."""
    df, n = document_frequencies(docs)
    idf = np.where(df > 0, np.log((1 + n) / (1 + df)) + 1, 0)
    usable = docs.where("lang is not null and text is not null and doc_id is not null").where(fold_of("doc_id") != 0)
    share = min(1.0, MAX_LABELLED / max(1, usable.select("doc_id").count()))
    usable = usable.where(F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(1_000_000)) < int(share * 1_000_000))

    def counted(batches):
        for batch in batches:
            for row, end, at, _, made in _grams(batch.column(0)):
                grams, counts = [], []
                for r in range(end - row):
                    g, c = np.unique(np.concatenate([m[at[r] : at[r + 1]] for m in made]), return_counts=True)
                    grams.append(g[g > 0].astype(np.int32))
                    counts.append(c[g > 0].astype(np.int32))
                yield pa.RecordBatch.from_arrays([*(c.slice(row, end - row) for c in batch.columns[1:]), pa.array(grams, pa.list_(pa.int32())), pa.array(counts, pa.list_(pa.int32()))], ["doc_id", "lang", "grams", "counts"])

    got = usable.select("text", F.col("doc_id").cast("long").alias("doc_id"), "lang").mapInArrow(counted, "doc_id long, lang string, grams array<int>, counts array<int>").toPandas()
    got = got[np.array([len(g) > 0 for g in got["grams"]], bool)].sort_values(["doc_id", "lang"], kind="stable").reset_index(drop=True)
    classes = sorted(got["lang"].unique().tolist())
    if not classes:
        return Model([], np.zeros((BUCKETS, 0), np.float32), np.zeros(0), 1.0)
    y = np.array([classes.index(c) for c in got["lang"]])
    rows = [(np.asarray(g, np.int64), np.asarray(c, np.float64) / np.sum(c) * idf[np.asarray(g, np.int64)]) for g, c in zip(got["grams"], got["counts"], strict=True)]
    fifth = np.arange(len(rows)) % 5 == 0
    if len(rows) < 10:
        fifth[:] = False
    used = np.flatnonzero(~fifth)
    w, b = fit_ftrl([rows[i] for i in used], y[used], len(classes))
    held = np.flatnonzero(fifth) if fifth.any() else used
    logits = np.stack([rows[i][1] @ w[rows[i][0]] + b for i in held])
    loss = lambda t: -np.log(_softmax(logits / t)[np.arange(len(held)), y[held]] + 1e-12).mean()
    temperature = float(min(np.exp(np.linspace(np.log(0.1), np.log(10), 80)), key=loss))
    table = (w * idf[:, None]).astype(np.float32)
    table[0] = 0
    return Model(classes, table, b, temperature)


def identify_language(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` for every row of ``docs`` (``doc_id, text, lang``).

    ``und`` with score 0 for a null text or one without a letter (and for all rows
    when no labelled row exists).  lang, source and doc_id are no inputs of a
    prediction.  Rows that repeat are predicted each; an empty table gives an empty
    result; ties go to the first class in order.
    """
    model = model or train(docs)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def predicted(batches):
        m = sent.value
        names = np.array([*m.classes, "und"], dtype=object)
        for batch in batches:
            for row, end, at, low, made in _grams(batch.column(0)):
                n, k = end - row, len(m.classes)
                logits, count = np.zeros((n, k)), np.zeros(n)
                has = np.flatnonzero(np.diff(at))
                letters = np.zeros(n, np.int64)
                if len(has) and k:
                    first = at[:-1][has]
                    letters[has] = np.add.reduceat((low > 0).astype(np.int64), first)
                    for g in made:
                        logits[has] += np.add.reduceat(m.table[g], first, axis=0, dtype=np.float64)
                        count[has] += np.add.reduceat((g > 0).astype(np.int64), first)
                    p = _softmax((logits / np.maximum(count, 1)[:, None] + m.bias) / m.temperature)
                    pick, score = p.argmax(1), np.round(p.max(1), 6)
                else:
                    pick, score = np.zeros(n, np.int64), np.zeros(n)
                none = letters == 0
                pick[none], score[none] = k, 0
                yield pa.RecordBatch.from_arrays([batch.column(1).slice(row, n), pa.array(names[pick], pa.string()), pa.array(score)], ["doc_id", "lang_pred", "score"])

    out = docs.select("text", F.col("doc_id").cast("long").alias("doc_id")).mapInArrow(predicted, "doc_id long, lang_pred string, score double")
    return out.select("doc_id", (fold_of("doc_id") == 0).alias("held_out"), "lang_pred", "score")
