"""Masked pseudo-likelihood: a bidirectional window network predicts every word from both sides.

The network predicts a frequent word itself, and of any other word one of OTHERS
hash buckets; the word within the bucket follows from the counts of all words, a
table that grows with the corpus and is joined, so that every token has its own
probability.  A bucket keeps half a count for each of as many unseen words as it
has seen ones.  The vocabulary grows with the token count.

Counts of the most frequent of those words are sent to the tasks, which spares most of that join's rows.
Vocabulary counts and training both cover the whole corpus.  Training is local
gradient descent in every task from shared parameters, followed by one weighted
average; every position of every text is a target in one of the rounds.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._scratch import written
from ._tokens import hashed_words, mix, pieces

#: Groups of words at least, and the token count from which there are more (by its fourth root: every
#: task returns all weights, so shuffled data would otherwise grow much faster than the input).
GROUPS, WIDTH = 32, 32
GROWS_FROM = 1 << 22
MOST_GROUPS = 1000  # ids are 16-bit; reached at 4e12 tokens
VOCAB = GROUPS * WIDTH
#: Words outside the vocabulary share these last ids, by hash.
OTHERS = 24
EDGE = VOCAB  # the id beyond either end of a text, in the smallest network
SIDES = (-2, -1, 1, 2)
DIM = 32
ROUNDS = 2
BATCH = 4096
RATE = 0.35
#: Positions handled at once: their numbers stay in the processor's cache.
CHUNK = 2048
#: The count an unseen word stands for; there are as many of them in a bucket as seen ones.
UNSEEN = 0.5
#: So many of the most frequent words at most go to every task with their counts; the others' counts are joined.
NEAR = 1 << 16


class Params(NamedTuple):
    words: np.ndarray  # vocabulary hashes, sorted
    ids: np.ndarray
    flat: np.ndarray  # all weights, float32
    spread: np.ndarray  # log of each bucket's total count, with its unseen words
    near: np.ndarray  # hashes of frequent words, sorted
    logs: np.ndarray  # the logs of their counts
    counts: DataFrame | None  # word, n of every word; not sent to the tasks


def _shapes(groups: int) -> tuple[tuple[int, ...], ...]:
    # The last row of both softmax levels is the bias: the hidden row ends with a one.
    return (len(SIDES), groups * WIDTH + 1, DIM), (DIM,), (DIM + 1, groups), (groups, DIM + 1, WIDTH)


def _n_weights(groups: int) -> int:
    return sum(int(np.prod(s)) for s in _shapes(groups))


def _groups(flat: np.ndarray) -> int:
    """The number of groups: the number of weights is linear in it."""
    return (len(flat) - _n_weights(0)) // (_n_weights(1) - _n_weights(0))


def _groups_for(tokens: int) -> int:
    return min(MOST_GROUPS, max(GROUPS, int(GROUPS * (tokens / GROWS_FROM) ** 0.25)))


def _views(flat: np.ndarray) -> list[np.ndarray]:
    at, out = 0, []
    for shape in _shapes(_groups(flat)):
        size = int(np.prod(shape))
        out.append(flat[at : at + size].reshape(shape))
        at += size
    return out


def _start(groups: int = GROUPS, seed: int = 1) -> np.ndarray:
    rng = np.random.default_rng(seed)
    flat = np.zeros(_n_weights(groups), np.float32)
    emb, _, top, low = _views(flat)
    for w, scale in ((emb, 0.1), (top[:DIM], 0.2), (low[:, :DIM], 0.2)):
        w[...] = rng.normal(0, scale, w.shape)
    return flat


def word_counts(docs: DataFrame) -> DataFrame:
    """``word, n``: every word's hash and count over every text."""

    def counted(batches):
        held: list[np.ndarray] = []
        size = 0
        for batch in batches:
            for _, _, data, offsets in pieces(batch.column(0)):
                held.append(hashed_words(data, offsets)[0])
                size += len(held[-1])
                if size > 1 << 21:
                    yield _counts(held)
                    held, size = [], 0
        if size:
            yield _counts(held)

    sums = docs.select("text").mapInArrow(counted, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return written(sums, "word-counts")


def vocabulary(counts: DataFrame) -> tuple[np.ndarray, np.ndarray, int, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes and ids of the most frequent words (ties go by hash), the number of groups, each bucket's log total,
    and hashes and log counts of up to NEAR frequent words."""
    # Signed longs stand for unsigned hashes: the remainder by OTHERS from that of the upper 63 bits.
    bucket = (F.shiftrightunsigned("word", 1) % (OTHERS // 2) * 2 + F.col("word").bitwiseAND(1)).cast("int")
    level = F.floor(8 * F.log2("n")).cast("int")  # a few hundred values, whatever the corpus
    sums = counts.groupBy(bucket.alias("bucket"), level.alias("level")).agg(F.sum("n").alias("n"), F.count("*").alias("types")).toPandas()
    above = sums.groupby("level")["types"].sum().sort_index(ascending=False).cumsum()
    least = above.index[above <= NEAR].min() if (above <= NEAR).any() else None
    near = counts.where(F.lit(False) if least is None else level >= int(least)).select("word", "n").toArrow()
    near_words = near.column("word").to_numpy().view(np.uint64)
    sort = np.argsort(near_words)
    near_logs = np.log(near.column("n").to_numpy()[sort].astype(np.float64))
    sums = sums.groupby("bucket", as_index=False)[["n", "types"]].sum()
    groups = _groups_for(int(sums["n"].sum()))
    top = counts.orderBy(F.desc("n"), "word").limit(groups * WIDTH - OTHERS).toPandas()
    hashes = top["word"].to_numpy(np.int64).view(np.uint64)
    total, types = np.zeros(OTHERS), np.zeros(OTHERS)
    total[sums["bucket"].to_numpy(np.int64)] = sums["n"]
    types[sums["bucket"].to_numpy(np.int64)] = sums["types"]
    own = (hashes % np.uint64(OTHERS)).astype(np.int64)
    total -= np.bincount(own, top["n"].to_numpy(np.float64), OTHERS)
    types -= np.bincount(own, minlength=OTHERS)
    order = np.argsort(hashes)
    return hashes[order], order.astype(np.int16), groups, np.log(total + UNSEEN * np.maximum(types, 1)), near_words[sort], near_logs


def _counts(held: list[np.ndarray]) -> pa.RecordBatch:
    word, n = np.unique(np.concatenate(held), return_counts=True)
    return pa.RecordBatch.from_arrays([pa.array(word.view(np.int64)), pa.array(n.astype(np.int64))], ["word", "n"])


def _ids(column: pa.Array, params: Params) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """First row, end row, word ids and each row's first word."""
    for row, end, _, ids, rows in _hashed(column, params):
        yield row, end, ids, rows


def _hashed(column: pa.Array, params: Params) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """First row, end row, word hashes, word ids and each row's first word."""
    others = _groups(params.flat) * WIDTH - OTHERS
    find = _Finder(params.words)
    for row, end, data, offsets in pieces(column):
        hashes, rows = hashed_words(data, offsets)
        ids = (hashes % np.uint64(OTHERS)).astype(np.int16)
        ids += np.int16(others)
        at, found = find(hashes)
        np.copyto(ids, params.ids.take(at, mode="clip") if len(params.ids) else ids, where=found)
        yield row, end, hashes, ids, rows


class _Finder:
    """Places of hashes in a sorted array without repeats, by their upper bits."""

    def __init__(self, words: np.ndarray):
        bits = max(len(words).bit_length() + 3, 8)
        self.words, self.shift = words, np.uint64(64 - bits)
        self.first = np.searchsorted(words, np.arange(1 << bits, dtype=np.uint64) << self.shift).astype(np.int32)
        self.shared = np.diff(self.first, append=np.int32(len(words))) > 1

    def __call__(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place, and whether the hash is there."""
        if not len(self.words):
            return np.zeros(len(hashes), np.int64), np.zeros(len(hashes), bool)
        upper = (hashes >> self.shift).astype(np.int64)
        at = self.first.take(upper).astype(np.int64)
        found = self.words.take(at, mode="clip") == hashes
        # Some words share their upper bits with an earlier one.
        rest = np.flatnonzero(self.shared.take(upper) & ~found)
        at[rest] = np.searchsorted(self.words, hashes[rest])
        found[rest] = self.words.take(at[rest], mode="clip") == hashes[rest]
        return at, found


def _contexts(ids: np.ndarray, rows: np.ndarray, edge: int = EDGE) -> np.ndarray:
    """Ids on each side of every word (side by word), ``edge`` beyond its text."""
    n = len(ids)
    out = np.full((len(SIDES), n), edge, np.int16)
    for s, step in enumerate(SIDES):
        by = min(abs(step), n)
        if step < 0:
            out[s, by:] = ids[: n - by]
        else:
            out[s, : n - by] = ids[by:]
        for k in range(by):
            # The k-th word from that end of its text, where there is one.
            at = rows[:-1] + k if step < 0 else rows[1:] - 1 - k
            out[s, at[at < rows[1:] if step < 0 else at >= rows[:-1]]] = edge
    return out


#: Beyond these, exp() of a float32 sum might leave its range, and the largest of the row is taken off first.
_WIDE = 60.0


class _Room:
    """Arrays of one chunk that every use fills anew: fresh ones of that size would cost page faults each time."""

    def __init__(self, n: int, groups: int):
        self.h = np.ones((n, DIM + 1), np.float32)
        self.rows, self.sum, self.scaled = (np.empty((n, w), np.float32) for w in (DIM, DIM, DIM + 1))
        self.top, self.low = np.empty((n, groups), np.float32), np.empty((n, WIDTH), np.float32)
        self.here = np.arange(n)


def _hidden(emb: np.ndarray, bias: np.ndarray, around: np.ndarray, room: _Room) -> np.ndarray:
    """tanh of the sum over the sides, and a one; tanh(x) is 1 - 2 / (exp(2x) + 1), which is right at both ends."""
    n = around.shape[1]
    x, row = room.sum[:n], room.rows[:n]
    np.take(emb[0], around[0], 0, out=x, mode="clip")
    for s in range(1, len(SIDES)):
        x += np.take(emb[s], around[s], 0, out=row, mode="clip")
    x += bias
    x *= 2
    np.minimum(x, _WIDE, out=x)
    np.exp(x, out=x)
    x += 1
    np.divide(-2, x, out=x)
    np.add(x, 1, out=room.h[:n, :DIM])
    return room.h[:n]


def _small(w: np.ndarray) -> bool:
    """Whether no product with these columns can be large: no number of a hidden row is beyond 1."""
    return bool(np.abs(w).sum(-2).max() < _WIDE)


def _exp(z: np.ndarray, small: bool = False) -> np.ndarray:
    """In place; what is taken off first where numbers are large, for each row (0 where none are, as when they're known to be small)."""
    off = np.zeros((1, 1), z.dtype)
    if z.size and not small and not (z.max() < _WIDE and z.min() > -_WIDE):
        off = z.max(1, keepdims=True)
        z -= off
    np.exp(z, out=z)
    return off[:, 0]


def _ones(n: int) -> np.ndarray:
    return np.ones(n, np.float32)


def _runs(of: np.ndarray) -> list[tuple[int, slice]]:
    """Each value of a sorted array and where it is."""
    cut = [0, *(np.flatnonzero(of[1:] != of[:-1]) + 1).tolist(), len(of)]
    return [(g, slice(i, j)) for g, i, j in zip(of[cut[:-1]].tolist(), cut[:-1], cut[1:], strict=True)]


def _by_group(ids: np.ndarray) -> np.ndarray:
    return np.argsort((ids // WIDTH).astype(np.uint16), kind="stable")


def log_probabilities(flat: np.ndarray, ids: np.ndarray, around: np.ndarray) -> np.ndarray:
    """log p(word | both sides): its group, then the word within the group."""
    emb, bias, top, low = _views(flat)
    out = np.empty(len(ids), np.float32)
    order = _by_group(ids)
    room = _Room(min(CHUNK, len(ids)), len(low))
    small_top, small_low = _small(top), _small(low)
    for start in range(0, len(ids), CHUNK):
        at = order[start : start + CHUNK]
        n, own = len(at), ids.take(at)
        group, here = own // WIDTH, room.here[: len(at)]
        h = _hidden(emb, bias, around.take(at, 1), room)
        z = np.matmul(h, top, out=room.top[:n])
        lp = z[here, group]
        lp -= _exp(z, small_top)
        total = z @ _ones(len(low))
        z = room.low[:n]
        for g, part in _runs(group):
            np.dot(h[part], low[g], out=z[part])
        lp += z[here, own - group * WIDTH]
        lp -= _exp(z, small_low)
        lp -= np.log(total)
        lp -= np.log(z @ _ones(WIDTH))
        out[at] = lp
    return out


class _Descent:
    """Adagrad on mini-batches, in place."""

    def __init__(self, flat: np.ndarray):
        self.flat = flat.copy()
        self.sums = np.full(len(flat), 1e-2, np.float32)
        groups = _groups(flat)
        self.room = _Room(CHUNK, groups)
        self.grad = np.zeros(len(flat), np.float32)
        self.views = [_views(x) for x in (self.flat, self.sums, self.grad)]
        self.work = np.empty(len(flat), np.float32)
        # Pairs of numbers are added at a time, as complex ones: where those of each word's row are.
        self.pairs = np.arange((groups * WIDTH + 1) * (DIM // 2)).reshape(-1, DIM // 2)

    def step(self, ids: np.ndarray, around: np.ndarray) -> None:
        (emb, bias, top, low), (sums, *_), (g_emb, g_bias, g_top, g_low) = self.views
        n, groups, room = len(ids), len(low), self.room
        # In the order of groups, so that each one's rows are a slice; in chunks that stay in the cache.
        order = _by_group(ids)
        ids, around = ids.take(order), around.take(order, 1)
        group = ids // WIDTH
        place = ids - group * WIDTH
        rest = slice(g_emb.size, None)
        self.grad[rest] = 0
        back_low, last = low[:, :DIM].swapaxes(1, 2), -1
        small = _small(top)
        met = np.zeros((len(SIDES), emb.shape[1]), bool)
        for start in range(0, n, CHUNK):
            part = slice(start, min(start + CHUNK, n))
            size, of = part.stop - start, group[part]
            here, runs = room.here[:size], _runs(of)
            h = _hidden(emb, bias, around[:, part], room)
            # The groups: e / total - (1 at the own one) stays in two factors.
            e = np.matmul(h, top, out=room.top[:size])
            _exp(e, small)
            total = e @ _ones(groups)
            e[here, of] -= total
            by = np.reciprocal(total)[:, None]
            back = np.matmul(e, top[:DIM].T, out=room.rows[:size])
            back *= by
            g_top += np.multiply(h, by, out=room.scaled[:size]).T @ e
            # The words of each group.
            q = room.low[:size]
            for g, at in runs:
                np.dot(h[at], low[g], out=q[at])
            _exp(q)
            total = q @ _ones(WIDTH)
            q[here, place[part]] -= total
            q *= np.reciprocal(total)[:, None]
            more = room.sum[:size]
            for g, at in runs:
                own, d = q[at], h[at]
                if g == last:  # begun in the chunk before
                    g_low[g] += d.T @ own
                else:
                    np.dot(d.T, own, out=g_low[g])
                np.dot(own, back_low[g], out=more[at])
            last = of[-1]
            back += more
            slope = np.multiply(h[:, :DIM], h[:, :DIM], out=more)
            np.subtract(1, slope, out=slope)
            back *= slope
            g_bias += _ones(size) @ back
            for s in range(len(SIDES)):
                words_here = around[s, part]
                met[s, words_here] = True
                np.add.at(g_emb[s].reshape(-1).view(np.complex64), self.pairs.take(words_here, 0).reshape(-1), back.reshape(-1).view(np.complex64))
        root = np.float32(1 / np.sqrt(n))
        self._moved(self.flat[rest], self.sums[rest], self.grad[rest], root)
        # Rows of words that don't occur get no gradient and stay.
        for s in range(len(SIDES)):
            at = np.flatnonzero(met[s])
            w, total, grad = emb[s].take(at, 0), sums[s].take(at, 0), g_emb[s].take(at, 0)
            self._moved(w, total, grad, root)
            emb[s, at], sums[s, at], g_emb[s, at] = w, total, 0

    def _moved(self, w: np.ndarray, sums: np.ndarray, grad: np.ndarray, root: np.float32) -> None:
        """One step of weights and their sums of squares, both in place; ``grad`` is used up."""
        work = self.work[: w.size].reshape(w.shape)
        grad *= root
        sums += np.multiply(grad, grad, out=work)
        grad *= np.float32(RATE)
        grad /= np.sqrt(sums, out=work)
        w -= grad


_FIXED = float(1 << 24)
#: Weights travel in so many blocks; blocks of up to a LANES-th of all tasks are added at a time.
BLOCKS, LANES = 64, 256
#: Whole numbers in two parts, so that sums over any number of tasks are exact, in whatever order.
_LOW = 24
_BLOCK_ROW = "block int, n long, high array<long>, low array<long>"


def _block(block: int, n: int, high: np.ndarray, low: np.ndarray) -> pa.RecordBatch:
    longs = pa.list_(pa.int64())
    return pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([n], pa.int64()), pa.array([high], longs), pa.array([low], longs)], ["block", "n", "high", "low"])


def _summed(rows: pa.Table) -> pa.Table:
    parts = [np.sum(np.stack([x.values.to_numpy() for x in rows.column(c)]), axis=0) for c in ("high", "low")]
    return pa.Table.from_batches([_block(rows.column("block")[0].as_py(), sum(rows.column("n").to_pylist()), *parts)])


def _targets(rows: np.ndarray, turn: int) -> np.ndarray:
    """Positions that a round trains on; over all rounds each position of each text once."""
    size = np.diff(rows)
    within = np.arange(rows[-1]) - np.repeat(rows[:-1], size)
    return np.flatnonzero((within + np.repeat(size, size)) % ROUNDS == turn)


def train(docs: DataFrame) -> Params:
    """Word counts, vocabulary and weights from all texts; the counts never move to the driver, the weights grow by the fourth root."""
    counts = word_counts(docs)
    hashes, ids, groups, spread, near, logs = vocabulary(counts)
    flat = _start(groups)
    n_weights, edge = len(flat), groups * WIDTH
    spark = docs.sparkSession
    for turn in range(ROUNDS):
        sent = spark.sparkContext.broadcast(Params(hashes, ids, flat, spread, near[:0], logs[:0], None))

        def descended(batches, sent=sent, turn=turn):
            params = sent.value
            run, n = _Descent(params.flat), 0
            for batch in batches:
                for _, _, own, rows in _ids(batch.column(0), params):
                    if not len(own):
                        continue
                    at = _targets(rows, turn)
                    if not len(at):
                        continue
                    around = _contexts(own, rows, edge)
                    at = at[np.argsort(mix(at.astype(np.uint64)))]  # no two are equal
                    for a in range(0, len(at), BATCH):
                        b = at[a : a + BATCH]
                        run.step(own.take(b).astype(np.int64), around.take(b, 1).astype(np.int64))
                    n += len(at)
            if n:
                moved = np.round((run.flat - params.flat).astype(np.float64) * _FIXED).astype(np.int64) * n
                for block, part in enumerate(np.array_split(moved, BLOCKS)):
                    yield _block(block, n, part >> _LOW, part & ((1 << _LOW) - 1))

        parts = docs.select("text").mapInArrow(descended, _BLOCK_ROW).withColumn("lane", F.spark_partition_id() % LANES)
        parts = parts.groupBy("block", "lane").applyInArrow(_summed, _BLOCK_ROW).groupBy("block").applyInArrow(_summed, _BLOCK_ROW)
        first = np.array([0, *np.cumsum([len(x) for x in np.array_split(np.arange(n_weights), BLOCKS)])])
        flat = flat.copy()
        for r in parts.collect():
            total = np.array(r.high, np.float64) * (1 << _LOW) + np.array(r.low, np.float64)
            flat[first[r.block] : first[r.block + 1]] += (total / r.n / _FIXED).astype(np.float32)
    return Params(hashes, ids, flat, spread, near, logs, counts)


def score_documents(docs: DataFrame, params: Params | None = None) -> DataFrame:
    """``doc_id, n_words, pll, pll_per_word`` for every row of ``docs`` (``doc_id, text``).

    pll is the sum over all words of log p(word | two words on both sides): of a
    word outside the vocabulary log p(bucket) + log p(word in bucket).  Null,
    empty or wordless texts: 0 words, pll 0 and a null mean.  Rows that repeat are
    scored each; an empty table gives an empty result.
    """
    params = params or train(docs)
    sent = docs.sparkSession.sparkContext.broadcast(params._replace(counts=None))

    def scored(batches):
        p = sent.value
        edge = _groups(p.flat) * WIDTH
        find = _Finder(p.near)
        for batch in batches:
            for row, end, hashes, ids, rows in _hashed(batch.column(2), p):
                n = end - row
                size = np.diff(rows)
                total = np.zeros(n)
                has = np.flatnonzero(size)
                if len(has):
                    lp = log_probabilities(p.flat, ids.astype(np.int64), _contexts(ids, rows, edge)).astype(np.float64)
                    rare = np.flatnonzero(ids >= edge - OTHERS)
                    lp[rare] -= p.spread[ids[rare] - (edge - OTHERS)]
                    at, found = find(hashes[rare])
                    lp[rare[found]] += p.logs[at[found]]
                    rare = rare[~found]
                    total[has] = np.add.reduceat(lp, rows[:-1][has])
                    ptr = np.searchsorted(rare, rows)
                    others = pa.LargeListArray.from_arrays(pa.array(ptr), pa.array(hashes[rare].view(np.int64)))
                else:
                    others = pa.array([[]] * n, pa.large_list(pa.int64()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, n), batch.column(1).slice(row, n), pa.array(size.astype(np.int64)), pa.array(total), others.cast(pa.list_(pa.int64()))], ["at", "doc_id", "n_words", "pll", "others"])

    rows = docs.select(F.monotonically_increasing_id().alias("at"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = written(rows.mapInArrow(scored, "at long, doc_id long, n_words long, pll double, others array<long>"), "lm-scores")
    # A word outside the vocabulary brings the log of its count, an unseen one that of UNSEEN; those of frequent words are in already.
    each = rows.select("at", F.explode("others").alias("word")).join(params.counts.hint("shuffle_hash"), "word", "left")
    own = each.groupBy("at").agg(F.sum(F.log(F.coalesce(F.col("n").cast("double"), F.lit(UNSEEN)))).alias("own"))
    out = rows.select("at", "doc_id", "n_words", "pll").join(own, "at", "left").select("doc_id", "n_words", F.round(F.col("pll") + F.coalesce("own", F.lit(0.0)), 3).alias("pll"))
    return out.withColumn("pll_per_word", F.when(F.col("n_words") > 0, F.round(F.col("pll") / F.col("n_words"), 6)))
