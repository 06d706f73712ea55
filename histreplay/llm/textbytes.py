"""Words and shingles of UTF-8 texts as numpy arrays, straight from Arrow buffers.

A word is a run of bytes other than space and \\t \\n \\v \\f \\r. A word's hash is a polynomial over its bytes modulo
2^64, taken from prefix sums, and then mixed; equal hashes stand for equal words (64 bits).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Texts are worked off in slices of about this many bytes, which bounds the memory of a task.
SLICE = 1 << 18
_BASE = 0x9E3779B97F4A7C15 | 1
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_powers: tuple[np.ndarray, np.ndarray] = (np.ones(1, np.uint64), np.ones(1, np.uint64))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64."""
    global _powers
    if len(_powers[0]) < n:
        inverse = pow(_BASE, -1, 1 << 64)
        _powers = tuple(np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n - 1, x, np.uint64))]) for x in (_BASE, inverse))
    return _powers


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (public splitmix64 constants)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def slices(column: pa.Array | pa.ChunkedArray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets) for runs of rows of at most SLICE bytes, or one longer row. Null counts as empty."""
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    row = 0
    for chunk in chunks:
        if len(chunk) == 0:
            continue
        if chunk.null_count:
            chunk = chunk.fill_null("")
        chunk = chunk.cast(pa.large_string())
        _, offs, data = chunk.buffers()
        off = np.frombuffer(offs, np.int64)[chunk.offset : chunk.offset + len(chunk) + 1]
        raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
        k = 0
        while k < len(chunk):
            end = max(k + 1, int(np.searchsorted(off, off[k] + SLICE, "right")) - 1)
            yield row + k, raw[off[k] : off[end]], off[k : end + 1] - off[k]
            k = end
        row += len(chunk)


def word_spans(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each document the number of words before it (n + 1 values)."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(off), np.int64)
    inside = ~_SPACE[data]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    edges = off[:-1][off[:-1] < off[1:]]
    first[edges] = inside[edges]
    tails = off[1:][off[:-1] < off[1:]] - 1
    last[tails] = inside[tails]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return start, end, np.searchsorted(start, off)


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, lower: bool) -> np.ndarray:
    if not len(start):
        return np.zeros(0, np.uint64)
    up, down = powers(max(len(data) + 1, SLICE + 1))
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(((_LOWER[data] if lower else data).astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
    return mix((sums[end] - sums[start]) * down[start])


def windows(h: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of `size` words, in order; shorter input gives none."""
    n = len(h) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    v = h[:n].copy()
    for k in range(1, size):
        v *= np.uint64(_BASE)
        v += h[k : k + n]
    return mix(v)


def shingle_sets(data: np.ndarray, off: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Each document's distinct shingles, sorted, one after the other, and the offsets (n + 1). Letters A-Z count as a-z.

    A document with fewer words than `size` has its whole sequence as one shingle; one without words has none.
    """
    start, end, at = word_spans(data, off)
    h = word_hashes(data, start, end, True)
    every = windows(h, size)
    sets, lens = [], np.zeros(len(off), np.int64)
    for d in range(len(off) - 1):
        a, b = at[d], at[d + 1]
        if b - a >= size:
            own = np.sort(every[a : b - size + 1])
            keep = np.ones(len(own), bool)
            np.not_equal(own[1:], own[:-1], out=keep[1:])
            own = own[keep]
        elif b > a:
            own = windows(h[a:b], int(b - a))
        else:
            continue
        sets.append(own)
        lens[d + 1] = len(own)
    return (np.concatenate(sets) if sets else np.zeros(0, np.uint64)), np.cumsum(lens)
