"""The descent's step in chunks against the whole batch at once, and against differences of the loss."""

import numpy as np

from locveil.llm import lm_scoring as lm


def _batch(n, seed=5):
    rng = np.random.default_rng(seed)
    ids = np.minimum(rng.zipf(1.3, n) - 1, lm.VOCAB - 1).astype(np.int64)
    around = rng.integers(0, lm.VOCAB + 1, (len(lm.SIDES), n))
    around[:, : n // 2] = 3
    return ids, around


def test_chunks_make_no_difference(monkeypatch):
    ids, around = _batch(900)
    moved = []
    for chunk in (64, 10_000):
        monkeypatch.setattr(lm, "CHUNK", chunk)
        run = lm._Descent(lm._start())
        for a in (0, 450):
            run.step(ids[a : a + 450], around[:, a : a + 450])
        moved.append((run.flat, lm.log_probabilities(run.flat, ids, around.astype(np.int16))))
    assert np.abs(moved[0][0] - moved[1][0]).max() < 1e-4
    assert np.abs(moved[0][1] - moved[1][1]).max() < 1e-4
    assert moved[0][1].mean() > lm.log_probabilities(lm._start(), ids, around.astype(np.int16)).mean()


def test_a_step_follows_the_gradient():
    ids, around = _batch(60)
    start = lm._start().astype(np.float32)
    run = lm._Descent(start)
    run.step(ids, around)
    grad = np.sqrt(np.maximum(run.sums - np.float32(1e-2), 0)) * np.sign(start - run.flat) * np.sqrt(len(ids))
    for at in np.argsort(-np.abs(grad))[:: 400][:8]:
        ends = []
        for by in (1e-2, -1e-2):
            flat = start.copy()
            flat[at] += by
            ends.append(-lm.log_probabilities(flat, ids, around.astype(np.int16)).sum(dtype=np.float64))
        assert abs((ends[0] - ends[1]) / 2e-2 - grad[at]) < 0.02 * max(1, abs(grad[at]))
