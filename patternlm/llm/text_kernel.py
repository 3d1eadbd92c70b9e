"""Vectorised hashing of the words and shingles of Arrow text columns (runs inside Arrow tasks).

A word's hash is the polynomial of random values of its bytes, taken as a difference of running sums modulo 2**64 and then mixed; no
Python object is made for a word. Work goes in slices of about a quarter of a megabyte, so memory depends on the longest text only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_RNG = np.random.default_rng(20240501)
BYTE_VALUE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
LOWERED = np.arange(256)
LOWERED[65:91] += 32
LOWER_VALUE = BYTE_VALUE[LOWERED]
IN_WORD = np.ones(256, dtype=bool)
IN_WORD[[0x20, *range(0x09, 0x0E)]] = False
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 2**64)
SLICE = 1 << 18
PIECE = 1 << 21


def mix64(x: np.ndarray) -> np.ndarray:
    """A published 64-bit finaliser (shift-multiply), in place on a copy."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_POWERS: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(n, 2 * SLICE)
        _POWERS[:] = [np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(size - 1, b, np.uint64)])) for b in (BASE, INVERSE)]
    return _POWERS[0], _POWERS[1]


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a text column; null counts as empty."""
    column = column.fill_null("") if column.null_count else column
    wide = pa.types.is_large_string(column.type)
    offsets = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64) if len(column) else np.zeros(1, np.int64)
    data = column.buffers()[2]
    return (np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)), offsets


def word_hashes(data: np.ndarray, offsets: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words in order, and each text's bounds among them."""
    data, offsets = data[offsets[0] : offsets[-1]], offsets - offsets[0]
    n = len(data)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    inside = IN_WORD[data]
    before, after = np.empty(n, bool), np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    after[-1], after[:-1] = False, inside[1:]
    before[offsets[:-1][offsets[:-1] < n]] = False
    after[offsets[1:][offsets[1:] > 0] - 1] = False
    starts = np.flatnonzero(inside & ~before)
    ends = np.flatnonzero(inside & ~after) + 1
    up, down = powers(n + 1)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((LOWER_VALUE if lower else BYTE_VALUE)[data] * up[:n], out=sums[1:])
    hashes = mix64((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    return hashes, np.searchsorted(starts, offsets)


def shingle_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k words; with fewer words, the whole sequence as one; without words, none."""
    n = len(words)
    if n == 0:
        return words
    width = min(k, n)
    out = np.full(n - width + 1, width, np.uint64)
    for j in range(width):
        out *= np.uint64(0xD6E8FEB86659FD93)
        out += words[j : n - width + 1 + j]
    return mix64(out)


def slices(offsets: np.ndarray, size: int = SLICE) -> Iterator[tuple[int, int]]:
    """Runs of texts of about `size` bytes; a longer text is a run of its own."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + size, side="right")) - 1)
        yield at, min(to, n)
        at = min(to, n)


def pieces(batches: Iterator[pa.RecordBatch], text: int = 1) -> Iterator[pa.RecordBatch]:
    """The batches in runs of rows of about PIECE bytes of text (a longer text is a run of its own), without copying: what a task makes of one is
    handed on before the next. Arrow's pool gives what it holds back to the system after each batch, so idle workers keep little."""
    for batch in batches:
        _, offsets = text_buffers(batch.column(text))
        for a, b in slices(offsets, PIECE):
            yield batch.slice(a, b - a)
        del batch, offsets
        pa.default_memory_pool().release_unused()


def text_words(column: pa.Array, lower: bool = True) -> Iterator[np.ndarray]:
    """The word hashes of each text of the column."""
    data, offsets = text_buffers(column)
    for a, b in slices(offsets):
        hashes, bounds = word_hashes(data, offsets[a : b + 1], lower)
        for i in range(b - a):
            yield hashes[bounds[i] : bounds[i + 1]]


def shingle_sets(column: pa.Array, k: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    for words in text_words(column):
        yield np.unique(shingle_hashes(words, k))
