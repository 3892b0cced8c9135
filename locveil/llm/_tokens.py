"""Vectorised text plumbing shared by the corpus operators.

Words are maximal runs of bytes outside ``[\\x20\\x09-\\x0D]``; because every
separator is ASCII, working on UTF-8 bytes gives the same words as working on
code points.  All hashing is a fixed function of the word bytes, so any task on
any executor gets the same 64-bit value.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text handled at once inside a Python worker (a longer text is one piece of its own).
PIECE_BYTES = 1 << 20

_ODD = np.uint64(0x9E3779B97F4A7C15)
_M1 = np.uint64(0xBF58476D1CE4E5B9)
_M2 = np.uint64(0x94D049BB133111EB)
_BASE = 0xD1342543DE82EF95
_INVERSE = pow(_BASE, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """Avalanche 64-bit integers (a bijection)."""
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x ^= x >> np.uint64(27)
    x = x * _M2
    x ^= x >> np.uint64(31)
    return x


_BYTE = mix(np.arange(1, 257, dtype=np.uint64) * _ODD)
_FOLD = np.arange(256)
_FOLD[65:91] += 32
_BYTE_FOLDED = _BYTE[_FOLD]
_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        step = np.full(max(n, PIECE_BYTES + 1), base, np.uint64)
        step[0] = 1
        have = _powers[base] = np.cumprod(step, dtype=np.uint64)
    return have


def pieces(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Cut an Arrow string column into (first row, end row, bytes, row offsets); null texts are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null("").cast(pa.large_string())
    n = len(column)
    if not n:
        return
    offsets = np.frombuffer(column.buffers()[1], np.int64, n + 1, column.offset * 8)
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    row = 0
    while row < n:
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + PIECE_BYTES, "right")) - 1)
        end = min(end, n)
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


def words(data: np.ndarray, offsets: np.ndarray, fold: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, starts and ends of all words of a piece, and each row's first word (one more entry at the end)."""
    n = len(data)
    if not n:
        none = np.zeros(0, np.int64)
        return np.zeros(0, np.uint64), none, none, np.zeros(len(offsets), np.int64)
    cut = np.zeros(n + 1, bool)
    cut[offsets] = True
    space = data == 0x20
    space |= data - np.uint8(9) < 5
    solid = ~space
    first = solid.copy()
    first[1:] &= space[:-1] | cut[1:n]
    last = solid.copy()
    last[:-1] &= space[1:] | cut[1:n]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    value = (_BYTE_FOLDED if fold else _BYTE).take(data)
    value *= _power(_BASE, n)[:n]
    total = np.empty(n + 1, np.uint64)
    total[0] = 0
    np.cumsum(value, out=total[1:])
    hashes = mix((total[ends] - total[starts]) * _power(_INVERSE, n)[starts] + (ends - starts).astype(np.uint64) * _ODD)
    return hashes, starts, ends, np.searchsorted(starts, offsets)


#: Bytes whose words are hashed at once: the arrays of 8 bytes for each stay in the processor's cache.
BLOCK_BYTES = 1 << 17


def hashed_words(data: np.ndarray, offsets: np.ndarray, fold: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """The hashes and first words of `words`, by blocks of whole rows."""
    n = len(offsets) - 1
    hashes, rows, row, made = [np.zeros(0, np.uint64)], [np.zeros(1, np.int64)], 0, 0
    while row < n:
        end = min(n, max(row + 1, int(np.searchsorted(offsets, offsets[row] + BLOCK_BYTES, "right")) - 1))
        own, _, _, first = words(data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row], fold)
        hashes.append(own)
        rows.append(first[1:] + made)
        made += len(own)
        row = end
    return np.concatenate(hashes), np.concatenate(rows)


def shingles(hashes: np.ndarray, rows: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of k words (in a row of fewer words: of its whole sequence), and each row's first one."""
    n = np.diff(rows)
    made = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    ptr = np.concatenate([[0], np.cumsum(made)])
    if not len(hashes):
        return np.zeros(0, np.uint64), ptr
    wide = max(len(hashes) - k + 1, 0)
    run = hashes[:wide].copy()
    for j in range(1, k):
        run *= _ODD
        run += hashes[j : j + wide]
    run = mix(run)
    out = np.empty(ptr[-1], np.uint64)
    at = np.repeat(rows[:-1] - ptr[:-1], made) + np.arange(ptr[-1])
    short = np.repeat(n < k, made)
    out[~short] = run[at[~short]]
    for r in np.flatnonzero((n < k) & (n > 0)):
        h = np.uint64(n[r])
        for w in hashes[rows[r] : rows[r + 1]]:
            h = mix(np.array([h]) * _ODD + w)[0]
        out[ptr[r]] = h
    return out, ptr


def distinct_sets(run: np.ndarray, ptr: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each row's values sorted, without repeats, and each row's first one."""
    if not len(run):
        return run, ptr
    out = run.copy()
    for a, b in zip(ptr[:-1].tolist(), ptr[1:].tolist(), strict=True):
        if b - a > 1:
            out[a:b].sort()
    keep = np.ones(len(out), bool)
    keep[1:] = out[1:] != out[:-1]
    keep[ptr[:-1][ptr[:-1] < len(out)]] = True
    count = np.concatenate([[0], np.cumsum(keep)])
    return out[keep], count[ptr]
