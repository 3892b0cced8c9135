"""Sketch classes of items, the exact mode, and ties of equal vectors."""

from __future__ import annotations

import random

import numpy as np
import pandas as pd


def test_a_shingle_is_in_the_sketch_from_its_class_on():
    from locveil.llm.decontaminate import _sketch, _sketched_from

    rng = np.random.default_rng(4)
    values = np.concatenate([np.sort(rng.integers(0, 2**64, n, dtype=np.uint64)) for n in (1, 2, 7, 300, 5000)] + [np.array([5, 6, 7, 2**63 - 1, 2**63], np.uint64)])
    ptr = np.cumsum([0, 1, 2, 7, 300, 5000, 5])
    first = _sketched_from(values, ptr)
    for bits in range(1, 64):
        assert ((first <= bits) == _sketch(values, ptr, np.full(len(ptr) - 1, bits))).all()


def test_exact_mode_and_sketch_recall_by_item_length(spark):
    from locveil.llm.decontaminate import contained_items

    rng = random.Random(6)
    texts = [" ".join(f"w{rng.randint(0, 10**9)}" for _ in range(12000)) for _ in range(3)]
    items = [(d, n, " ".join(t.split()[a : a + n])) for d, t in enumerate(texts) for n in (5, 8, 12, 30) for a in range(0, 11900, 60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame([(i, t) for i, (_, _, t) in enumerate(items)], "item_id long, text string")
    want = {(d, i) for i, (d, _, _) in enumerate(items)}
    assert {(r.doc_id, r.item_id) for r in contained_items(docs, bench, exact=True).collect()} == want
    got = {(r.doc_id, r.item_id) for r in contained_items(docs, bench).collect()}
    for n in (5, 8, 12, 30):
        of_length = {x for x in want if items[x[1]][1] == n}
        assert len(got & of_length) / len(of_length) >= (1.0 if n == 5 else 0.999)


def test_equal_vectors_tie_wherever_they_are():
    from locveil.llm.hash_forest import _search

    rng = np.random.default_rng(1)
    for trial in range(1000):
        n = int(rng.integers(8, 40))
        x = rng.normal(size=(n, 64))
        twin = rng.choice(n, 6, replace=False)
        x[twin] = x[twin[0]]
        rows = pd.DataFrame({"vec_id": rng.permutation(n), "v": list(x)})
        query = pd.DataFrame({"vec_id": [n + 1], "v": [x[twin[0]] + rng.normal(size=64) * 0.01]})
        got = _search(query, rows, 5, 1.0, 3)
        assert got["vec_id"].tolist() == sorted(rows["vec_id"].to_numpy()[twin])[:5], trial
        assert got["score"].nunique() == 1


def test_cosine_of_very_small_and_large_vectors():
    from locveil.llm.hash_forest import _search

    v = np.arange(1.0, 9.0)
    rows = pd.DataFrame({"vec_id": [1, 2, 3, 4], "v": [v * 1e-200, v * 1e200, v * 5e-324 * 2**20, -v]})
    got = _search(pd.DataFrame({"vec_id": [9], "v": [v * 1e-300]}), rows, 5, 1.0, 3)
    assert np.allclose(got["score"], [1, 1, 1, -1]) and np.isfinite(got["score"]).all()
