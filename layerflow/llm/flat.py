"""Flat byte views of string columns, word boundaries and word hashes in numpy.

All helpers work on the UTF-8 bytes of many texts laid end to end, so that one numpy call serves a
whole block of documents.  Blocks are cut between documents at about ``BLOCK_BYTES``; a longer text
forms a block of its own, whole.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK_BYTES = 1 << 18

#: Word characters of ``[^\x20\x09-\x0D]+``.
NOT_SPACE = np.ones(256, np.uint8)
NOT_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = 0

#: Word characters of ``[^\x00-\x2F\x3A-\x60\x7B-\x7F]+`` after A-Z became a-z.
ALNUM = np.zeros(256, np.uint8)
ALNUM[0x30:0x3A] = 1
ALNUM[0x61:0x7B] = 1
ALNUM[0x80:] = 1

LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

_BASE = np.uint64(0x9E3779B97F4A7C15)
_M1 = np.uint64(0xBF58476D1CE4E5B9)
_M2 = np.uint64(0x94D049BB133111EB)
_powers = np.ones(1, np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


def powers(n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    global _powers
    if len(_powers) < n:
        grown = np.full(max(n, 1024), _BASE, np.uint64)
        grown[0] = 1
        _powers = np.cumprod(grown, dtype=np.uint64)
    return _powers[:n]


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string or binary array; nulls count as empty."""
    if column.null_count:
        column = pc.fill_null(column, b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offs, data = column.buffers()
    if offs is None or len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    offsets = np.frombuffer(offs, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def blocks(column: pa.Array, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, bytes, offsets) of runs of whole texts of about ``limit`` bytes."""
    data, offsets = buffers(column)
    n, a = len(offsets) - 1, 0
    while a < n:
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + limit, side="right")) - 1)
        b = min(b, n)
        yield a, b, data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        a = b


def word_spans(data: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends (in bytes) of all maximal runs of word characters within one text."""
    inside = table[data]
    n = len(inside)
    before, after = np.zeros(n, np.uint8), np.zeros(n, np.uint8)
    if n:
        before[1:], after[:-1] = inside[:-1], inside[1:]
        cuts = offsets[(offsets > 0) & (offsets < n)]
        before[cuts] = 0
        after[cuts - 1] = 0
    return np.flatnonzero(inside & (before ^ 1)), np.flatnonzero(inside & (after ^ 1)) + 1


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word's bytes."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    lens = ends - starts
    total = int(lens.sum())
    first = np.cumsum(lens) - lens
    within = np.arange(total, dtype=np.int64) - np.repeat(first, lens)
    packed = data[within + np.repeat(starts, lens)]
    terms = (packed.astype(np.uint64) + np.uint64(1)) * powers(int(lens.max()))[within]
    return mix(np.add.reduceat(terms, first) + lens.astype(np.uint64))


def words_of(data: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, hashes, first word of each text and a last end) of a block."""
    starts, ends = word_spans(data, offsets, table)
    return starts, ends, word_hashes(data, starts, ends), np.searchsorted(starts, offsets)


def grams(hashes: np.ndarray, k: int) -> np.ndarray:
    """A hash of every k consecutive word hashes, ignoring text boundaries."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(k):
        out *= _BASE
        out += hashes[j : j + n]
    return mix(out)


def window_minimum(values: np.ndarray, w: int) -> np.ndarray:
    """Position of the leftmost smallest value of every w consecutive ones."""
    n = len(values) - w + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    best = values.copy()
    at = np.arange(len(values), dtype=np.int64)
    span = 1
    while span < w:
        step = min(span, w - span)
        m = len(best) - step
        worse = best[step : step + m] < best[:m]
        best = np.where(worse, best[step : step + m], best[:m])
        at = np.where(worse, at[step : step + m], at[:m])
        span += step
    return at[:n]


def runs(flags: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of true values."""
    edge = np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def trim() -> None:
    """Gives freed memory back to the system: a reused Python worker would keep it."""
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)
    pa.default_memory_pool().release_unused()


def spread(n: int, starts: np.ndarray, length: int) -> np.ndarray:
    """Flags of the n places covered by a window of ``length`` that begins at one of ``starts``."""
    mark = np.zeros(n + 1, np.int64)
    np.add.at(mark, starts, 1)
    np.add.at(mark, np.minimum(starts + length, n), -1)
    return np.cumsum(mark[:-1]) > 0
