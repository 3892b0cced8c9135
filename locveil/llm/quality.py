"""Quality classifier: random-indexing word vectors pooled per document, a two-layer network and a temperature."""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._tokens import distinct_sets, mix, pieces, words

#: Word types share this many vectors (a type's vector is that of its hash bucket).
BUCKETS = 1 << 12
DIM = 32
NONZERO = 4
WINDOW = 2
SHAPES = 64
EXTRA = 4
FEATURES = DIM + SHAPES + EXTRA
#: About this many labelled rows at most (by a hash of doc_id) reach the driver to fit the network.
MAX_LABELLED = 20_000
HIDDEN = 32


def _index_vectors() -> np.ndarray:
    """Sparse ternary index vectors, a fixed function of the bucket: (bucket, NONZERO) places with signs."""
    seed = mix(np.arange(1, BUCKETS * NONZERO + 1, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407)).reshape(BUCKETS, NONZERO)
    place = (seed % np.uint64(DIM)).astype(np.int32)
    sign = np.where((seed >> np.uint64(40)) & np.uint64(1), 1.0, -1.0)
    return np.stack([place, sign], 2)


_KIND = np.zeros((4, 256), np.int32)  # upper, digit, symbol, beyond ASCII
_KIND[0, 65:91] = 1
_KIND[1, 48:58] = 1
_KIND[2, [c for c in range(33, 127) if not chr(c).isalnum() and chr(c) not in ".,;:'-"]] = 1
_KIND[3, 128:] = 1


def _shapes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Surface form of each word: upper case, digits, symbols and length, in SHAPES kinds."""
    count = []
    for kind in _KIND[:3]:
        total = np.zeros(len(data) + 1, np.int32)
        np.cumsum(kind[data], out=total[1:])
        count.append(total[ends] - total[starts])
    upper, digit, symbol = count
    size = ends - starts
    form = np.where(upper == 0, 0, np.where(upper == 1, 1, np.where(2 * upper > size, 3, 2)))
    signs = np.minimum(symbol, 3)
    long = np.where(size > 24, 1, 0)
    return form * 16 + signs * 4 + np.minimum(digit, 1) * 2 + long


def _parts(column: pa.Array) -> Iterator[tuple]:
    for row, end, data, offsets in pieces(column):
        hashes, starts, ends, rows = words(data, offsets)
        yield row, end, hashes, rows, data, starts, ends


def word_vectors(docs: DataFrame) -> np.ndarray:
    """Context vectors of all word buckets, summed over every word of every text; unit length.

    Each task sums its own table of BUCKETS x DIM numbers; the tables are added by
    blocks in one aggregate, and what reaches the driver has that fixed size.
    """

    def summed(batches):
        index = _index_vectors()
        place, sign = index[:, :, 0].astype(np.int64), index[:, :, 1]
        total = np.zeros(BUCKETS * DIM)
        for batch in batches:
            for _, _, hashes, rows, *_ in _parts(batch.column(0)):
                bucket = (hashes >> np.uint64(20)).astype(np.int64) % BUCKETS
                row = np.repeat(np.arange(len(rows) - 1), np.diff(rows))
                for step in range(1, WINDOW + 1):
                    same = row[step:] == row[:-step]
                    a, b = bucket[:-step][same], bucket[step:][same]
                    for x, y in ((a, b), (b, a)):
                        for z in range(NONZERO):
                            total += np.bincount(x * DIM + place[y, z], sign[y, z], BUCKETS * DIM)
        wide = 64 * DIM
        for block in range(BUCKETS // 64):
            own = total[block * wide : (block + 1) * wide]
            if own.any():
                yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([own], pa.list_(pa.float64()))], ["block", "part"])

    parts = docs.select("text").mapInArrow(summed, "block int, part array<double>")
    cells = parts.select("block", F.posexplode("part").alias("cell", "v")).groupBy("block", "cell").agg(F.sum("v").alias("v")).where("v <> 0").toPandas()
    out = np.zeros(BUCKETS * DIM)
    out[cells["block"].to_numpy() * 64 * DIM + cells["cell"].to_numpy()] = np.round(cells["v"].to_numpy())  # whole numbers: the order of sums is no matter
    out = out.reshape(BUCKETS, DIM)
    return (out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)).astype(np.float32)


def features(column: pa.Array, vectors: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """First row and feature rows: mean word vector, shares of surface forms, size and repetition."""
    for row, end, hashes, rows, data, starts, ends in _parts(column):
        n = end - row
        size = np.diff(rows)
        out = np.zeros((n, FEATURES), np.float32)
        has = np.flatnonzero(size)
        if len(has):
            first = rows[:-1][has]
            bucket = (hashes >> np.uint64(20)).astype(np.int64) % BUCKETS
            out[has, :DIM] = np.add.reduceat(vectors[bucket], first, axis=0) / size[has, None]
            owner = np.repeat(np.arange(n), size)
            form = np.bincount(owner * SHAPES + _shapes(data, starts, ends), minlength=n * SHAPES).reshape(n, SHAPES)
            out[has, DIM : DIM + SHAPES] = form[has] / size[has, None]
            _, ptr = distinct_sets(hashes, rows)
            again = np.zeros(len(hashes))
            again[1:] = hashes[1:] == hashes[:-1]
            again[first] = 0
            length = np.add.reduceat((ends - starts).astype(np.float64), first)
            out[has, -4] = np.log1p(size[has])
            out[has, -3] = np.diff(ptr)[has] / size[has] ** 0.8
            out[has, -2] = np.add.reduceat(again, first) / size[has]
            out[has, -1] = length / size[has] / 10
        yield row, out


class Network(NamedTuple):
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        return np.tanh(z @ self.w1 + self.b1) @ self.w2 + self.b2

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, epochs: int = 60, seed: int = 11) -> Network:
    """Train on four rows of five; the fifth chooses the epoch and the temperature."""
    rng = np.random.default_rng(seed)
    if not len(y) or y.min() == y.max():
        share = float(y.mean()) if len(y) else 0.5
        zero = np.zeros(x.shape[1])
        return Network(zero, zero + 1, np.zeros((x.shape[1], 1)), np.zeros(1), np.zeros(1), float(np.log((share + 1e-3) / (1 - share + 1e-3))), 1.0)
    order = rng.permutation(len(y))
    held, used = order[: max(1, len(y) // 5)], order[max(1, len(y) // 5) :]
    mean, scale = x[used].mean(0), x[used].std(0) + 1e-4
    z = np.clip((x - mean) / scale, -8, 8)
    p = [rng.normal(0, 1 / np.sqrt(x.shape[1]), (x.shape[1], HIDDEN)), np.zeros(HIDDEN), rng.normal(0, 0.2, HIDDEN), np.zeros(())]
    m, v, t = [0 * q for q in p], [0 * q for q in p], 0
    best, kept = np.inf, p
    for _ in range(epochs):
        for batch in np.array_split(rng.permutation(used), max(1, len(used) // 64)):
            a, b = z[batch], y[batch]
            h = np.tanh(a @ p[0] + p[1])
            g = 1 / (1 + np.exp(-np.clip(h @ p[2] + p[3], -30, 30))) - b
            back = g[:, None] * p[2] * (1 - h * h)
            grad = [a.T @ back / len(b) + 1e-4 * p[0], back.mean(0), h.T @ g / len(b) + 1e-4 * p[2], g.mean()]
            t += 1
            for i in range(4):
                m[i] = 0.9 * m[i] + 0.1 * grad[i]
                v[i] = 0.999 * v[i] + 0.001 * grad[i] ** 2
                p[i] = p[i] - 3e-3 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
        s = 2 * y[held] - 1
        logit = np.tanh(z[held] @ p[0] + p[1]) @ p[2] + p[3]
        loss = np.logaddexp(0, -s * logit).mean()
        if loss < best:
            best, kept = loss, [q.copy() for q in p]
    net = Network(mean, scale, kept[0], kept[1], kept[2], float(kept[3]), 1.0)
    s, logit = 2 * y[held] - 1, net.logits(x[held])
    grid = np.exp(np.linspace(np.log(0.25), np.log(8), 60))
    return net._replace(temperature=float(min(grid, key=lambda q: np.logaddexp(0, -s * logit / q).mean())))


def fold_of(doc_id: str | Column) -> Column:
    return F.pmod(F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")) if isinstance(doc_id, str) else doc_id), F.lit(5))


def train(docs: DataFrame, labels: DataFrame) -> tuple[np.ndarray, Network]:
    """Word vectors from all texts; a network from a bounded hash sample of the labelled rows outside the held-out fold."""
    spark = docs.sparkSession
    vectors = word_vectors(docs)
    usable = labels.where("doc_id is not null and quality is not null").where(fold_of("doc_id") != 0).select("doc_id", F.col("quality").cast("int").alias("quality")).distinct()
    share = min(1.0, MAX_LABELLED / max(1, usable.count()))
    usable = usable.where(F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(1_000_000)) < int(share * 1_000_000))
    sent = spark.sparkContext.broadcast(vectors)

    def made(batches):
        for batch in batches:
            for row, x in features(batch.column(0), sent.value):
                yield pa.RecordBatch.from_arrays([batch.column(1).slice(row, len(x)), batch.column(2).slice(row, len(x)), pa.array(list(x), pa.list_(pa.float32()))], ["doc_id", "quality", "x"])

    # At most about MAX_LABELLED small rows: a proven bound for the broadcast.
    rows = docs.select("text", F.col("doc_id").cast("long").alias("doc_id")).join(F.broadcast(usable), "doc_id").select("text", "doc_id", "quality")
    rows = rows.mapInArrow(made, "doc_id long, quality int, x array<float>").toPandas()
    if not len(rows):
        return vectors, fit(np.zeros((0, FEATURES)), np.zeros(0))
    rows = rows.sort_values(["doc_id", "quality"], kind="stable")
    x = np.array(rows["x"].tolist(), np.float64).reshape(len(rows), FEATURES)
    return vectors, fit(x, rows["quality"].to_numpy(np.float64))


def score_quality(docs: DataFrame, labels: DataFrame, keep: list[str] | None = None, cut: float = 0.3) -> DataFrame:
    """``keep`` columns (doc_id by default), ``held_out``, ``score`` and ``predicted`` for every row of ``docs``.

    Only ``text`` is an input of the score; ``labels(doc_id, quality)`` of rows whose
    crc32(doc_id) mod 5 is not 0 train it.  Null, empty or wordless texts have zero
    features and the score the network gives those.  Rows that repeat are scored
    each; a null doc_id is never a training row.  Without usable labels every score
    is 0.5.  Empty tables give empty results.
    """
    keep = keep or ["doc_id"]
    sent = docs.sparkSession.sparkContext.broadcast(train(docs, labels))
    rows = docs.select(F.col("text").alias("__text"), F.col("doc_id").alias("__id"), *keep)
    out = T.StructType([*rows.schema.fields[1:], T.StructField("__score", T.DoubleType())])

    def scored(batches):
        vectors, net = sent.value
        for batch in batches:
            for row, x in features(batch.column(0), vectors):
                part = batch.slice(row, len(x))
                yield pa.RecordBatch.from_arrays([*part.columns[1:], pa.array(np.round(net.scores(x.astype(np.float64)), 6))], [*batch.schema.names[1:], "__score"])

    got = rows.mapInArrow(scored, out)
    score = F.col("__score")
    return got.select(*keep, (fold_of("__id") == 0).alias("held_out"), score.alias("score"), F.when(score >= cut, 1).otherwise(0).alias("predicted"))


def accepted(docs: DataFrame, labels: DataFrame, cut: float = 0.3) -> DataFrame:
    """The rows of ``docs``, all columns, whose score reaches ``cut``."""
    sent = docs.sparkSession.sparkContext.broadcast(train(docs, labels))
    at = docs.columns.index("text")

    def kept(batches):
        vectors, net = sent.value
        for batch in batches:
            for row, x in features(batch.column(at), vectors):
                yield batch.slice(row, len(x)).filter(pa.array(np.round(net.scores(x.astype(np.float64)), 6) >= cut))

    return docs.mapInArrow(kept, docs.schema)
