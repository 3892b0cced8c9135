"""Exact n-gram Jaccard join by vertical partitioning of the global n-gram order.

The global order puts frequent n-grams last (frequencies are counted over all
texts), the rest by hash.  It is cut into fragments; a document's set becomes one
segment per fragment.  Two documents can only link when they share an n-gram of
their prefixes in that order, which yields candidate pairs; the fragments of a pair
are joined and counted separately, and the partial overlaps are summed per pair.

Buckets of a shared n-gram do not give all their pairs.  First every document meets
one partner a bucket, the least that may still link, and of these partners again
only the least is counted; then those of them that lie between two of the components
made so far; last, every pair of any bucket that still lies between two components,
so that no link between different texts is lost.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._scratch import drop, free_name, written
from ._tokens import distinct_sets, mix, pieces, shingles, words
from .components import components

#: An n-gram in more documents than this goes to the end of the order.
COMMON = 64
#: The list of such n-grams that each task gets has at most this many entries (16 MB).
MOST_COMMON_ENTRIES = 1 << 21
#: Rows of a frequent n-gram's bucket that meet in one task.
BLOCK = 1024
#: Halves by hash of the n-grams that are not frequent, then of the frequent ones.
FRAGMENTS = 4
#: The bitmap of wanted rows has 2^15 to 2^27 bits (16 MB), 32 for each row where that is enough.
_LEAST_MAP_BITS, _MOST_MAP_BITS, _BITS_A_ROW = 15, 27, 32
#: Fingerprints are counted in 2^10 parts, and in more, up to 2^16, where the input has many tasks.
_PART_BITS, _MOST_PART_BITS = 10, 16


def _sets(column: pa.Array, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    for row, _, data, offsets in pieces(column):
        hashes, _, _, rows = words(data, offsets)
        yield row, *distinct_sets(*shingles(hashes, rows, k))


def _common(docs: DataFrame, k: int, bits: int = _PART_BITS) -> np.ndarray:
    """40-odd-bit fingerprints of the n-grams that occur in many documents, counted over all of them.

    Fingerprints travel packed by part; after one exchange on the part they are
    counted where they are.  The threshold rises with the corpus so that the list
    keeps to MOST_COMMON_ENTRIES.
    """

    def packed(batches):
        held: list[np.ndarray] = []
        size = 0

        def flush():
            prints = np.sort(np.concatenate(held) >> np.uint64(64 - bits - 32))
            part = (prints >> np.uint64(32)).astype(np.int32)
            low = (prints & np.uint64(0xFFFFFFFF)).astype(np.uint32).view(np.int32)
            ptr = np.searchsorted(part, np.arange((1 << bits) + 1)).astype(np.int32)
            return pa.RecordBatch.from_arrays([pa.array(np.arange(1 << bits, dtype=np.int32)), pa.ListArray.from_arrays(pa.array(ptr), pa.array(low))], ["part", "low"])

        for batch in batches:
            for _, values, _ in _sets(batch.column(0), k):
                held.append(values)
                size += len(values)
                if size >= 1 << min(23, 11 + bits):
                    yield flush()
                    held, size = [], 0
        if size:
            yield flush()

    rows = docs.select("text").mapInArrow(packed, "part int, low array<int>").where(F.size("low") > 0)
    counted = rows.repartition("part").select("part", F.explode("low").alias("low")).groupBy("part", "low").count().where(F.col("count") > COMMON)
    counted = written(counted, "common")
    least = COMMON
    while counted.where(F.col("count") > least).count() > MOST_COMMON_ENTRIES:
        least *= 2
    got = counted.where(F.col("count") > least).select("part", "low").toPandas()
    drop(counted)
    return np.sort((got["part"].to_numpy(np.uint64) << np.uint64(32)) | got["low"].to_numpy(np.int32).view(np.uint32).astype(np.uint64))


class _Order(NamedTuple):
    """The global order: which n-grams are frequent and so come last."""

    common: Broadcast
    bits: int

    def last(self, values: np.ndarray) -> np.ndarray:
        common = self.common.value
        if not len(common):
            return np.zeros(len(values), bool)
        prints = values >> np.uint64(64 - self.bits - 32)
        at = np.minimum(np.searchsorted(common, prints), len(common) - 1)
        return common[at] == prints


def _order(docs: DataFrame, k: int) -> _Order:
    bits = min(_MOST_PART_BITS, max(_PART_BITS, docs.rdd.getNumPartitions().bit_length() + 2))
    return _Order(docs.sparkSession.sparkContext.broadcast(_common(docs, k, bits)), bits)


def _parity(values: np.ndarray) -> bytes:
    """Parity of the set in 2^j cells: two sets differ in at least as many members as their parities do in cells."""
    cells = 1 << max(6, int(2 * len(values) - 1).bit_length())
    at = (values & np.uint64(cells - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=cells) & 1).astype(np.uint8), bitorder="little").tobytes()


def _folded(x: np.ndarray, width: int) -> np.ndarray:
    while x.shape[-1] > width:
        half = x.shape[-1] // 2
        x = x[..., :half] ^ x[..., half:]
    return x


def _most_apart(na, nb, num: int, den: int):
    """Largest symmetric difference of linked sets of these sizes."""
    need = -(-num * (na + nb) // (num + den))
    return na + nb - 2 * need


def _class_ids(values: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """A 64-bit name for each row's set, the same wherever the set occurs."""
    total = np.zeros((2, len(values) + 1), np.uint64)
    np.cumsum(values, out=total[0, 1:])
    np.cumsum(mix(values), out=total[1, 1:])
    sums = total[:, ptr[1:]] - total[:, ptr[:-1]]
    return mix(sums[0] ^ mix(sums[1] + np.diff(ptr).astype(np.uint64))).view(np.int64)


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(_key(), F.col("doc_id").cast("long").alias("doc_id"), "text")


def _key() -> Column:
    """Names a row by its id and text; rows equal in both share it."""
    return F.xxhash64(F.col("doc_id").cast("long"), "text").alias("key")


_SKETCH = "key long, doc_id long, n_shingles long, rep long, rare array<long>, often array<long>, parity binary"


def _sketches(docs: DataFrame, k: int, num: int, den: int, order: _Order) -> DataFrame:
    def made(batches):
        for batch in batches:
            keys, ids = batch.column(0), batch.column(1)
            for row, values, ptr in _sets(batch.column(2), k):
                often = order.last(values)
                sizes = np.diff(ptr)
                rare, late, parity = [], [], []
                for a, b in zip(ptr[:-1].tolist(), ptr[1:].tolist(), strict=True):
                    own, hot, n = values[a:b], often[a:b], b - a
                    prefix = n - -(-num * n // den) + 1 if n else 0
                    rare.append(own[~hot][:prefix].view(np.int64))
                    late.append(own[hot][: prefix - len(rare[-1])].view(np.int64))
                    parity.append(_parity(own))
                reps = pa.array(_class_ids(values, ptr), mask=sizes == 0)
                longs = pa.list_(pa.int64())
                cols = [keys.slice(row, len(sizes)), ids.slice(row, len(sizes)), pa.array(sizes.astype(np.int64)), reps, pa.array(rare, longs), pa.array(late, longs), pa.array(parity, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, ["key", "doc_id", "n_shingles", "rep", "rare", "often", "parity"])

    return written(_keyed(docs).mapInArrow(made, _SKETCH), "sketches")


_MET = "gram long, rep long, n int, pos int, comp long, parent long"


def _met(classes: DataFrame, num: int, den: int) -> DataFrame:
    """Rows of the buckets of n-grams in at most COMMON documents that have a partner there: with the least one, as ``parent``."""
    rows = classes.select(F.posexplode("rare").alias("pos", "gram"), "rep", F.col("n_shingles").cast("int").alias("n"), F.col("rep").alias("comp"))

    def least(block: np.ndarray) -> pa.RecordBatch | None:
        parent = np.full(len(block), -1)
        paired = np.zeros(len(block), bool)
        for i, j in _bucket_pairs(block, num, den):  # steps ascend, so that a later one is a lesser partner
            parent[j] = i
            paired[i] = paired[j] = True
        at = np.flatnonzero(paired)
        if not len(at):
            return None
        up = pa.array(block[parent[at], 1], pa.int64(), mask=parent[at] < 0)
        return _batch(block[at], up)

    return _by_bucket(rows, least, _MET)


def _between(met: DataFrame, labels: DataFrame, num: int, den: int) -> DataFrame:
    """All pairs of the buckets' rows that lie in different components and may still link."""
    rows = met.drop("parent", "comp").join(labels.select("rep", "comp"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))

    def apart(block: np.ndarray) -> pa.RecordBatch | None:
        found = [np.stack([i, j], 1) for i, j in _bucket_pairs(block, num, den)]
        if not found:
            return None
        pairs = np.sort(block[np.concatenate(found), 1], axis=1)
        pairs = np.unique(pairs, axis=0)
        return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])

    return _by_bucket(rows, apart, "a long, b long").distinct()


def _batch(block: np.ndarray, up: pa.Array) -> pa.RecordBatch:
    gram, rep, n, pos, comp = (pa.array(c) for c in block.T)
    return pa.RecordBatch.from_arrays([gram, rep, n.cast(pa.int32()), pos.cast(pa.int32()), comp, up], ["gram", "rep", "n", "pos", "comp", "parent"])


def _by_bucket(rows: DataFrame, made, schema: str) -> DataFrame:
    """Apply ``made`` to blocks ``gram, rep, n, pos, comp`` of whole buckets, in the order of gram and rep."""
    rows = rows.repartition("gram").sortWithinPartitions("gram", "rep").select("gram", "rep", "n", "pos", "comp")

    def run(batches):
        kept = np.zeros((0, 5), np.int64)  # the last bucket so far: it may go on in the next batch
        for batch in batches:
            block = np.concatenate([kept, np.stack([batch.column(i).to_numpy().astype(np.int64) for i in range(5)], 1)])
            if not len(block):
                continue
            cut = _last_run(block[:, 0])
            block, kept = block[:cut], block[cut:]
            out = made(block)
            if out is not None:
                yield out
        out = made(kept)
        if out is not None:
            yield out

    return rows.mapInArrow(run, schema)


def _last_run(grams: np.ndarray) -> int:
    other = np.flatnonzero(grams != grams[-1])
    return int(other[-1]) + 1 if len(other) else 0


def _bucket_pairs(block: np.ndarray, num: int, den: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows of one bucket and of different components whose sizes and positions still allow a link, by their distance."""
    gram, _, n, pos, comp = block.T
    for step in range(1, len(block)):
        i = np.flatnonzero(gram[step:] == gram[:-step])
        if not len(i):
            break
        j = i + step
        need = -(-num * (n[i] + n[j]) // (num + den))
        ok = (num * np.maximum(n[i], n[j]) <= den * np.minimum(n[i], n[j])) & (np.minimum(n[i] - pos[i], n[j] - pos[j]) >= need) & (comp[i] != comp[j])
        if ok.any():
            yield i[ok], j[ok]


def _common_pairs(classes: DataFrame, num: int, den: int, labels: DataFrame | None) -> DataFrame:
    """Pairs that share a frequent n-gram in their prefixes, where nearly all of both sets is frequent.

    A bucket is cut into blocks of BLOCK rows on average; each two blocks meet in a task of their own
    and compare set parities.  Without labels a task returns a spanning forest of its passing pairs,
    those of least rows first, which different buckets have in common; with labels it returns every
    passing pair of different components.
    """
    rows = classes.where(F.size("often") > 0).withColumn("comp", F.lit(None).cast("long"))
    if labels is not None:
        rows = rows.drop("comp").join(labels.select("rep", "comp"), "rep", "left")
    # With each n-gram goes the one before it in the document's prefix: two rows that agree on both met there already.
    grams = F.explode(F.transform("often", lambda g, i: F.struct(g.alias("gram"), F.coalesce(F.get("often", i - 1), F.col("rep")).alias("before"))))
    rows = rows.select("rep", F.col("n_shingles").alias("n"), "parity", F.coalesce("comp", "rep").alias("comp"), grams.alias("g")).select("*", "g.*").drop("g")
    sizes = rows.groupBy("gram").agg(F.count("*").alias("m"), F.min("comp").alias("c0"), F.max("comp").alias("c1"))
    sizes = sizes.where("m > 1 and c0 <> c1").select("gram", F.ceil(F.col("m") / BLOCK).cast("int").alias("blocks"))
    rows = rows.join(sizes, "gram").withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    rows = rows.withColumn("other", other).withColumn("x", F.least("block", "other")).withColumn("y", F.greatest("block", "other"))

    forest = labels is None

    def met(pdf: pd.DataFrame) -> pd.DataFrame:
        out = _close_pairs(pdf["rep"].to_numpy(), pdf["n"].to_numpy(), list(pdf["parity"]), pdf["comp"].to_numpy(), pdf["block"].to_numpy(), pdf["before"].to_numpy(), num, den, forest)
        return pd.DataFrame({"a": out[:, 0], "b": out[:, 1]})

    return rows.select("gram", "x", "y", "block", "rep", "n", "parity", "comp", "before").repartition("gram", "x", "y").groupBy("gram", "x", "y").applyInPandas(met, "a long, b long").distinct()


def _close_pairs(rep, n, parity, comp, block, before, num, den, forest: bool) -> np.ndarray:
    order = np.lexsort((rep, n))
    rep, n, comp, block, before = rep[order], n[order], comp[order], block[order], before[order]
    wide = np.array([len(parity[i]) for i in order])
    two = len(np.unique(block)) > 1
    found = []
    for w in np.unique(wide):
        own = np.flatnonzero(wide == w)
        mine = np.stack([np.frombuffer(parity[order[i]], np.uint64) for i in own])
        above = np.flatnonzero(wide == 2 * w)  # sizes that may link differ by less than twice
        theirs = _folded(np.stack([np.frombuffer(parity[order[i]], np.uint64) for i in above]), mine.shape[1]) if len(above) else mine[:0]
        index, cells = np.concatenate([own, above]), np.concatenate([mine, theirs])
        # Most rows may be of one component already: these meet the others only.
        names, many = np.unique(comp[index], return_counts=True)
        major = names[many.argmax()]
        minor = np.flatnonzero(comp[index] != major)
        for p in range(len(own)):
            i = own[p]
            stop = int(np.searchsorted(num * n[index], den * n[i], "right"))  # sizes ascend
            at = minor[np.searchsorted(minor, p, "right") : np.searchsorted(minor, stop)] if comp[i] == major else np.arange(p + 1, stop)
            if not len(at):
                continue
            j = index[at]
            apart = np.bitwise_count(cells[at] ^ cells[p]).sum(1, dtype=np.int64)
            ok = (apart <= _most_apart(n[i], n[j], num, den)) & (comp[j] != comp[i]) & (before[j] != before[i])
            if two:
                ok &= block[j] != block[i]
            if ok.any():
                found.append(np.stack([np.full(ok.sum(), i), j[ok]], 1))
    if not found:
        return np.zeros((0, 2), np.int64)
    pairs = np.concatenate(found)
    if forest:
        up = {}

        def root(v):
            while up.get(v, v) != v:
                up[v] = up.get(up[v], up[v])
                v = up[v]
            return v

        picked = []
        ends = np.sort(rep[pairs], axis=1)
        for i, j in pairs[np.lexsort((ends[:, 1], ends[:, 0]))].tolist():
            a, b = root(i), root(j)
            if a != b:
                up[b] = a
                picked.append((i, j))
        pairs = np.array(picked)
    a, b = rep[pairs[:, 0]], rep[pairs[:, 1]]
    return np.stack([np.minimum(a, b), np.maximum(a, b)], 1)


def _with_parity(pairs: DataFrame, classes: DataFrame, num: int, den: int) -> DataFrame:
    """Drop pairs whose parities lie too far apart to link; adds the sizes of their sets."""
    side = lambda c: classes.select(F.col("rep").alias(c), F.col("n_shingles").alias(f"n{c}"), F.col("parity").alias(f"p{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "nb", "pa", "pb")

    def near(batches):
        for batch in batches:
            a, b, na, nb, pa_, pb = (batch.column(i).to_pylist() for i in range(6))
            keep = []
            for i in range(len(a)):
                x, y = pa_[i], pb[i]
                if len(x) > len(y):
                    x, y = y, x
                y = int.from_bytes(y, "little")
                width = 8 * len(pb[i] if len(pb[i]) > len(pa_[i]) else pa_[i])
                while width > 8 * len(x):
                    width //= 2
                    y = (y >> width) ^ (y & ((1 << width) - 1))
                apart = (int.from_bytes(x, "little") ^ y).bit_count()
                if apart <= _most_apart(na[i], nb[i], num, den):
                    keep.append((a[i], b[i], na[i], nb[i]))
            if keep:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*keep, strict=True)], ["a", "b", "na", "nb"])

    return both.mapInArrow(near, "a long, b long, na long, nb long")


def _bitmap(keys: DataFrame) -> np.ndarray:
    """Bits set at the lowest bits of each key: of fixed greatest size, it lets some more keys pass but stops none."""
    bits = min(_MOST_MAP_BITS, max(_LEAST_MAP_BITS, (_BITS_A_ROW * keys.count()).bit_length()))
    place = F.col("key").bitwiseAND((1 << bits) - 1)
    at = keys.select((F.shiftright(place, 15)).cast("int").alias("part"), place.bitwiseAND((1 << 15) - 1).alias("bit"))
    out = np.zeros((1 << bits - 15, 1 << 12), np.uint8)
    for r in at.groupBy("part").agg(F.bitmap_construct_agg("bit").alias("bits")).toLocalIterator():
        out[r.part] = np.frombuffer(r.bits, np.uint8)
    return out.reshape(-1)


def _segments(docs: DataFrame, wanted: DataFrame, k: int, order: _Order) -> DataFrame:
    """One row for each document whose ``key`` is wanted (and some few more) and fragment of the global order: its n-grams there.

    Texts don't move for that: tasks get a bitmap of the wanted keys.
    """
    sent = docs.sparkSession.sparkContext.broadcast(_bitmap(wanted))

    def cut(batches):
        bitmap = sent.value
        for batch in batches:
            place = batch.column(0).to_numpy() & (8 * len(bitmap) - 1)
            texts = batch.column(1).filter(pa.array((bitmap[place >> 3] >> (place & 7).astype(np.uint8) & 1).astype(bool)))
            for _, values, ptr in _sets(texts, k):
                frag = FRAGMENTS // 2 * order.last(values) + (values >> np.uint64(63)).astype(np.int32)
                names = _class_ids(values, ptr)
                row_of = np.repeat(np.arange(len(ptr) - 1), np.diff(ptr))
                by = np.lexsort((frag, row_of))  # stable: by row and fragment, n-grams ascend
                values, frag = values[by], frag[by].astype(np.int32)
                edge = np.ones(len(values), bool)
                edge[1:] = frag[1:] != frag[:-1]
                edge[ptr[:-1][ptr[:-1] < len(values)]] = True
                start = np.flatnonzero(edge)
                owner = names[np.searchsorted(ptr, start, "right") - 1]
                list_ptr = np.append(start, len(values)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(owner), pa.array(frag[start]), pa.ListArray.from_arrays(pa.array(list_ptr), pa.array(values.view(np.int64)))], ["rep", "frag", "grams"])

    return written(_keyed(docs).select("key", "text").mapInArrow(cut, "rep long, frag int, grams array<long>"), "segments")


def _overlaps(pairs: DataFrame, segments: DataFrame, num: int, den: int) -> DataFrame:
    """Verify pairs: partial overlaps by fragment, summed per pair, against the exact threshold."""
    left = segments.select(F.col("rep").alias("a"), "frag", F.col("grams").alias("ga"))
    right = segments.select(F.col("rep").alias("b"), "frag", F.col("grams").alias("gb"))
    # Each fragment is a join of its own: a document with many partners is spread over them.
    each = pairs.withColumn("frag", F.explode(F.array(*(F.lit(f) for f in range(FRAGMENTS)))))
    both = each.join(left, ["a", "frag"]).join(right, ["b", "frag"]).select("a", "b", "na", "nb", "frag", F.size(F.array_intersect("ga", "gb")).alias("part"))
    partial = both.groupBy("a", "b", "na", "nb", "frag").agg(F.max("part").alias("part"))  # max: a repeated row gives its segments twice
    summed = partial.groupBy("a", "b", "na", "nb").agg(F.sum("part").alias("shared"))
    return summed.where(f"{den} * shared >= {num} * (na + nb - shared)").select("a", "b")


def _least(pairs: DataFrame) -> DataFrame:
    """Of each end's pairs the one with the least other end."""
    ends = pairs.select(F.col("a").alias("v"), F.struct(F.col("b").alias("w"), "a", "b", "na", "nb").alias("s"))
    ends = ends.union(pairs.select("b", F.struct(F.col("a").alias("w"), "a", "b", "na", "nb")))
    return ends.groupBy("v").agg(F.min("s").alias("s")).select("s.a", "s.b", "s.na", "s.nb").distinct()


def _across(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """Pairs of different components."""
    la, lb = (labels.select(F.col("rep").alias(c), F.col("comp").alias(f"c{c}")) for c in "ab")
    both = pairs.join(la, "a", "left").join(lb, "b", "left").withColumns({"ca": F.coalesce("ca", "a"), "cb": F.coalesce("cb", "b")})
    return both.where("ca <> cb").select("a", "b", "na", "nb")


def _labels(links: DataFrame, firsts: DataFrame) -> DataFrame:
    """``rep, comp, least`` of every linked set: its component, and the row that stands for it.

    Nodes carry their least row, so that the component is named by one and no table is joined by component.
    """
    node = F.struct("first.none", "first.doc_id", "first.key", "rep")
    a, b = (firsts.select(F.col("rep").alias(c), node.alias(f"node_{c}")) for c in "ab")
    made = components(links.join(a, "a").join(b, "b").select(F.col("node_a").alias("a"), F.col("node_b").alias("b")))
    return made.select(F.col("node.rep").alias("rep"), F.col("comp.rep").alias("comp"), F.struct("comp.none", "comp.doc_id", "comp.key").alias("least"))


def _nodes(docs: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """``key, doc_id, n_shingles, first`` of every row; first is the row ``(none, doc_id, key)`` of its component that stands for it.

    It is the one of smallest doc_id (nulls last, then by key), and null without n-grams.
    """
    order = _order(docs, k)
    sketches = _sketches(docs, k, num, den, order)
    full = sketches.where("n_shingles > 0")
    firsts = written(full.groupBy("rep").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")).alias("first")), "firsts")
    # Both columns name the row of a class: what the join deals out by them needs no other exchange to lose rows that repeat.
    classes = full.join(firsts.select("rep", F.col("first.key").alias("key")), ["key", "rep"], "left_semi").dropDuplicates(["key", "rep"])
    classes = written(classes.select("key", "rep", "n_shingles", "rare", "often", "parity"), "classes")
    size = classes.select("rep", F.col("n_shingles").alias("n"))

    def sized(pairs: DataFrame) -> DataFrame:
        na, nb = (size.select(F.col("rep").alias(c), F.col("n").alias(f"n{c}")) for c in "ab")
        return pairs.join(na, "a").join(nb, "b").select("a", "b", "na", "nb")

    met = written(_met(classes, num, den), "met")
    parents = met.where("parent is not null").select(F.least("rep", "parent").alias("a"), F.greatest("rep", "parent").alias("b")).distinct()
    tried = _with_parity(parents, classes, num, den).union(sized(_common_pairs(classes, num, den, None)))
    tried = written(tried.distinct(), "tried")

    def counted(pairs: DataFrame) -> DataFrame:
        """Pairs that link; only the texts at their ends are cut into segments."""
        ends = pairs.select(F.col("a").alias("rep")).union(pairs.select("b")).distinct()
        segments = _segments(docs, classes.select("key", "rep").join(ends, "rep", "left_semi").select("key"), k, order)
        found = written(_overlaps(pairs, segments, num, den), "links")
        drop(segments)
        return found

    # A pair of each document first; then all tried pairs between the components these make; then what lies between the rest.
    picked = written(_least(tried), "picked")
    links = counted(picked)
    labels = _labels(links, firsts)
    left = written(_across(tried.join(picked, ["a", "b"], "left_anti"), labels), "left")
    drop(tried, picked)
    if not left.isEmpty():
        links = links.union(counted(left))
        labels = _labels(links, firsts)
    rest = _with_parity(_between(met, labels, num, den), classes, num, den).union(sized(_common_pairs(classes, num, den, labels)))
    rest = written(rest.distinct(), "rest")
    drop(met, left)
    if not rest.isEmpty():
        labels = _labels(links.union(counted(rest)), firsts)
    drop(rest, classes)
    of_class = firsts.join(labels, "rep", "left").select("rep", F.coalesce("least", "first").alias("first"))
    node = sketches.select("key", "doc_id", "n_shingles", "rep").join(of_class, "rep", "left")
    out = written(node.select("key", "doc_id", "n_shingles", "first"), "nodes")
    drop(sketches, firsts)
    return out


def jaccard_components(docs: DataFrame, k: int = 4, num: int = 85, den: int = 100) -> DataFrame:
    """Group documents whose sets of k-word n-grams link: ``den * |x & y| >= num * |x | y|``.

    Takes ``doc_id, text`` (other columns are ignored) and returns, per row of
    ``docs``: ``doc_id, n_shingles, component_id`` (the smallest doc_id reachable
    by links, itself included).

    * Null, empty or wordless text: no n-grams, linked with nothing.
    * Fewer than k words: the whole sequence is the one n-gram.
    * Equal sets are one class, which takes part once; exact copies never meet in pairs.
    * Rows that share a doc_id are rows of their own; a null doc_id is never the
      smallest: component_id is null only where a component has no other id.
    * An empty table gives an empty table.
    """
    node = _nodes(docs, k, num, den)
    return node.select("doc_id", "n_shingles", F.when(F.col("first").isNull(), F.col("doc_id")).otherwise(F.col("first.doc_id")).alias("component_id"))


def deduplicated(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """The rows of ``docs``, all columns, less all but one of each component (the one of smallest doc_id, nulls last).

    Rows without n-grams are linked with nothing and all stay.  Columns of any name
    pass through as they are.
    """
    node = _nodes(docs, k, num, den).where("first is not null")
    key, twin = (free_name(docs, c) for c in ("key", "twin"))
    lost = node.where("key <> first.key").select(F.col("key").alias(key)).distinct()
    twice = node.groupBy("key").count().where("count > 1").select(F.col("key").alias(key), F.lit(True).alias(twin))
    kept = docs.withColumn(key, _key()).join(lost, key, "left_anti").join(twice, key, "left")
    one = kept.where(F.col(twin)).dropDuplicates([key])
    return kept.where(F.col(twin).isNull()).unionByName(one).select(*(F.col(f"`{c}`") for c in docs.columns))
