"""Benchmark decontamination: size-partitioned MinHash containment search, verified by exact shingle containment.

A document's distinct shingles fall into bins by the top bits of their hash; its size
class (a power of two) fixes how many bins there are, so that a bin holds half a
shingle on average and a short item is not drowned in a long document.  The sketch
is the least and the greatest hash of each bin.  Bins of one size class lie within those of
a smaller one, so that each shingle of an item is in its sketch from some size class
on: one table with that class serves all.  A document and an item that share a
sketch value are a candidate, and the exact share of the item's shingles in the
document decides.  Items of few
shingles are looked up among all shingles of the document instead, which is exact;
an item of fewer than k words is one shingle and matches a document of just these
words, as in the SQL.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tokens import distinct_sets, pieces, shingles, words

#: Characters of benchmark text whose shingles go to every task at once; a larger benchmark takes several passes.
ITEMS_CHARS = 32_000_000


#: Items of at most so many shingles are compared with all shingles of a document: the sketch may miss them.
FEW = 3


class Items(NamedTuple):
    ids: np.ndarray
    values: np.ndarray
    ptr: np.ndarray


def _shingle_sets(column: pa.Array, k: int):
    for row, end, data, offsets in pieces(column):
        hashes, _, _, rows = words(data, offsets)
        yield row, end, *distinct_sets(*shingles(hashes, rows, k))


def _sketch(values: np.ndarray, ptr: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Which of the sorted values are the least or greatest of their bin, for 2^bits bins in each row."""
    if not len(values):
        return np.zeros(0, bool)
    bin_ = values >> np.repeat(np.uint64(64) - bits.astype(np.uint64), np.diff(ptr))
    edge = np.ones(len(values) + 1, bool)
    edge[1:-1] = bin_[1:] != bin_[:-1]
    edge[ptr] = True
    return edge[:-1] | edge[1:]


def _class_bits(sizes: np.ndarray) -> np.ndarray:
    return np.ceil(np.log2(np.maximum(sizes, 1))).astype(np.int64) + 1


def _items(benchmark: pd.DataFrame, k: int) -> Items:
    sets = [(v, p) for _, _, v, p in _shingle_sets(pa.array(benchmark["text"], pa.string()), k)]
    values = np.concatenate([np.zeros(0, np.uint64), *(v for v, _ in sets)])
    sizes = np.concatenate([np.zeros(0, np.int64), *(np.diff(p) for _, p in sets)])
    return Items(benchmark["item_id"].to_numpy(), values, np.concatenate([[0], np.cumsum(sizes)]))


def _sketched_from(values: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """The least bits for which each of the sorted values is the least or greatest of its bin in its row (0: always)."""
    if not len(values):
        return np.zeros(0, np.int64)
    same = 64 - np.frexp((values[1:] ^ values[:-1]).astype(np.float64))[1]  # leading bits that neighbours share
    # Rounding to a double may carry into the next power: then the bits shared are one more.
    same += (values[1:] ^ values[:-1]) < (np.uint64(1) << (63 - np.minimum(same, 63)).astype(np.uint64))
    apart = np.zeros(len(values) + 1, np.int64)
    apart[1:-1] = same + 1
    apart[ptr] = 0
    return np.minimum(apart[:-1], apart[1:])


class _Search:
    """The items' shingles in order, each with its item and the size class from which it is in the item's sketch."""

    def __init__(self, items: Items, k: int, num: int, den: int, exact: bool):
        self.items, self.k, self.num, self.den, self.exact = items, k, num, den, exact
        self.order = np.argsort(items.values, kind="stable")
        self.values = items.values[self.order]
        self.owner = np.searchsorted(items.ptr, self.order, "right") - 1
        size = np.diff(items.ptr)[self.owner]
        self.bits = _sketched_from(items.values, items.ptr)[self.order]
        self.few = size <= FEW

    def __call__(self, column: pa.Array):
        """(row, item position, shared shingles) of every contained item."""
        items = self.items
        for row, _, values, ptr in _shingle_sets(column, self.k):
            if not len(values) or not len(self.values):
                continue
            bits = _class_bits(np.diff(ptr))
            chosen = _sketch(values, ptr, bits)
            lo, hi = np.searchsorted(self.values, values, "left"), np.searchsorted(self.values, values, "right")
            found = set()
            for i in np.flatnonzero(hi > lo):
                r = int(np.searchsorted(ptr, i, "right")) - 1
                own = slice(lo[i], hi[i])
                meets = self.few[own] | (chosen[i] & (self.bits[own] <= bits[r])) | self.exact
                found.update((r, int(j)) for j in self.owner[own][meets])
            for r, j in sorted(found):
                own, item = values[ptr[r] : ptr[r + 1]], items.values[items.ptr[j] : items.ptr[j + 1]]
                at = np.minimum(np.searchsorted(own, item), len(own) - 1)
                shared = int((own[at] == item).sum())
                if self.den * shared >= self.num * len(item):
                    yield row + r, j, shared, len(item)


def _blocks(benchmark: DataFrame, k: int):
    """The benchmark's shingles in blocks of bounded size; items without an id count as well."""
    benchmark = benchmark.where("text is not null").select("item_id", "text")
    chars = benchmark.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = max(1, -(-chars // ITEMS_CHARS))
    for b in range(blocks):
        part = benchmark.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b) if blocks > 1 else benchmark
        items = _items(part.toPandas().sort_values("item_id", kind="stable"), k)
        yield items


def contained_items(docs: DataFrame, benchmark: DataFrame, k: int = 5, num: int = 80, den: int = 100, exact: bool = False) -> DataFrame:
    """Benchmark items inside documents: ``doc_id, item_id, item_shingles, shared, containment``.

    One row for each document row and item with ``den * shared >= num * item_shingles``.
    Null, empty or wordless texts on either side match nothing; an item of fewer
    than k words matches a document of just these words.  Letters A-Z count as
    a-z.  Repeated rows are searched each; empty tables give an empty result.
    ``exact`` takes every shared shingle as a candidate instead of those in both
    sketches.
    """
    out = None
    for items in _blocks(benchmark.where("item_id is not null"), k):
        sent = docs.sparkSession.sparkContext.broadcast(items)

        def found(batches, sent=sent):
            search = _Search(sent.value, k, num, den, exact)
            for batch in batches:
                got = list(search(batch.column(1)))
                if got:
                    row, item, shared, size = zip(*got, strict=True)
                    ids = batch.column(0).take(pa.array(row, pa.int64()))
                    yield pa.RecordBatch.from_arrays([ids, pa.array(sent.value.ids[list(item)], pa.int64()), pa.array(size, pa.int64()), pa.array(shared, pa.int64()), pa.array(np.array(shared) / np.array(size))], ["doc_id", "item_id", "item_shingles", "shared", "containment"])

        one = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(found, "doc_id long, item_id long, item_shingles long, shared long, containment double")
        out = one if out is None else out.unionByName(one)
    return out


def decontaminated(docs: DataFrame, benchmark: DataFrame, k: int = 5, num: int = 80, den: int = 100, exact: bool = False) -> DataFrame:
    """The rows of ``docs``, all columns, that contain no benchmark item (``exact`` as above)."""
    out = docs
    at = docs.columns.index("text")
    for items in _blocks(benchmark, k):
        sent = docs.sparkSession.sparkContext.broadcast(items)

        def clean(batches, sent=sent):
            search = _Search(sent.value, k, num, den, exact)
            for batch in batches:
                keep = np.ones(batch.num_rows, bool)
                keep[[r for r, *_ in search(batch.column(at))]] = False
                yield batch.filter(pa.array(keep))

        out = out.mapInArrow(clean, docs.schema)
    return out
