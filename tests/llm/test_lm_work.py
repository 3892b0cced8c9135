"""Less work a word in the scoring: counts of frequent words are sent, not joined; hashes are found by their upper bits."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from locveil.llm import lm_scoring as lm
from locveil.llm._tokens import hashed_words, words


@pytest.mark.parametrize("near", [0, 3000, lm.NEAR])
def test_frequent_words_are_not_joined(spark, monkeypatch, near):
    # 3,000 words thrice, of which the vocabulary takes some, and 2,000 once.
    text = " ".join(f"a{i}" for i in range(3000))
    docs = spark.createDataFrame([(0, text), (1, text), (2, text), (3, " ".join(f"b{i}" for i in range(2000))), (4, "new a1 b1 a2999 b1999")], "doc_id long, text string")
    held = {}
    write = lm.written
    monkeypatch.setattr(lm, "written", lambda df, name: held.setdefault(name, write(df, name)))
    monkeypatch.setattr(lm, "NEAR", near)
    params = lm.train(docs)
    got = {r.doc_id: r.pll for r in lm.score_documents(docs, params).collect()}
    joined = held["lm-scores"].agg(F.sum(F.size("others"))).first()[0]
    # With 3,000 the words of three and more occurrences are sent; b1 and b1999 occur twice, the rest of the b and "new" once.
    assert {0: joined > 5000, 3000: joined == 2003}.get(near, joined == 0)
    plain = params._replace(near=params.near[:0], logs=params.logs[:0])
    held.clear()
    for r in lm.score_documents(docs, plain).collect():
        assert abs(r.pll - got[r.doc_id]) < 2e-3


def test_large_weights_stay_finite():
    rng = np.random.default_rng(2)
    flat = rng.normal(0, 60, lm._n_weights(lm.GROUPS)).astype(np.float32)
    ids, around = rng.integers(0, lm.VOCAB, 300), rng.integers(0, lm.VOCAB + 1, (len(lm.SIDES), 300))
    with np.errstate(divide="ignore"):
        lp = lm.log_probabilities(flat, ids, around)
    assert np.isfinite(lp).all() and (lp <= 1e-3).all()
    run = lm._Descent(flat)
    run.step(ids, around)
    assert np.isfinite(run.flat).all()


def test_hashes_are_found():
    rng = np.random.default_rng(3)
    table = np.unique(np.concatenate([rng.integers(0, 1 << 63, 500, dtype=np.uint64) * np.uint64(2), np.arange(9, 400, 3, dtype=np.uint64), np.array([0, (1 << 64) - 1], np.uint64)]))
    asked = np.concatenate([table, table + np.uint64(1), table[::-1]])
    at, found = lm._Finder(table)(asked)
    assert (found == np.isin(asked, table)).all() and (table[at[found]] == asked[found]).all()
    assert not lm._Finder(table[:0])(asked)[1].any()


def test_blocks_make_the_same_words(monkeypatch):
    from locveil.llm import _tokens

    monkeypatch.setattr(_tokens, "BLOCK_BYTES", 40)
    texts = [b"one two", b"", b"  ", b"a\tb\x0bc\x1cd\n", "é x".encode() * 30, b"end"]
    data, offsets = np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)])
    hashes, rows = hashed_words(data, offsets)
    whole = words(data, offsets)
    assert (hashes == whole[0]).all() and (rows == whole[3]).all()
    assert len(hashed_words(data[:0], np.zeros(3, np.int64))[0]) == 0
