"""Benchmark items of few words inside long texts, and items without an id."""

from __future__ import annotations

import random


def test_items_of_few_shingles_are_always_found(spark):
    from locveil.llm.decontaminate import contained_items

    rng = random.Random(3)
    texts = [" ".join(f"w{rng.randint(0, 10**9)}" for _ in range(16400)) for _ in range(3)]
    items = []
    for d, t in enumerate(texts):
        w = t.split()
        items += [(d, " ".join(w[a : a + n])) for a in range(0, 16390, 41) for n in (5, 6)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame([(i, t) for i, (_, t) in enumerate(items)], "item_id long, text string")
    got = sorted((r.doc_id, r.item_id) for r in contained_items(docs, bench).collect())
    assert got == sorted((d, i) for i, (d, _) in enumerate(items))


def test_items_without_id_count(spark):
    from locveil.llm.decontaminate import contained_items, decontaminated

    text = "one two three four five six"
    docs = spark.createDataFrame([(0, f"x y {text} z"), (1, "something else that is here now")], "doc_id long, text string")
    bench = spark.createDataFrame([(None, text)], "item_id long, text string")
    assert [r.doc_id for r in decontaminated(docs, bench).collect()] == [1]
    assert contained_items(docs, bench).count() == 0


def test_items_of_one_to_four_words_match_whole_documents(spark):
    from locveil.llm.decontaminate import contained_items

    docs = spark.createDataFrame([(n, " ".join("abcdef"[:n])) for n in range(1, 7)], "doc_id long, text string")
    bench = spark.createDataFrame([(n, " ".join("abcdef"[:n])) for n in range(1, 7)], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in contained_items(docs, bench).collect()}
    assert got == {(n, n) for n in range(1, 7)} | {(6, 5)}
