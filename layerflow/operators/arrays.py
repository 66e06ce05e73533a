"""Pairs of integers dealt over tasks as arrays: one row of bytes for each part of a share, instead of a row a pair.

A shuffle of hundreds of millions of pairs costs most where each is a row of its own; here shares of pairs are cut by a
hash of the key, and a part's pairs come together in one task.  Pairs whose halves fit in 32 bits travel as one number
each, others as two.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layerflow import store

#: Pairs of a share that one task cuts at once, and about as many as a part has.
SHARE, PART = 1 << 18, 1 << 21
#: ``k`` holds keys and ``x`` values, or ``k`` both, if ``x`` is null.
DEALT = "part int, side int, k binary, x binary"
LISTS = DEALT + ", degree binary, pairs long"


def parts_for(pairs: int, at_least: int = 1) -> int:
    return max(at_least, -(-pairs // PART))


def part_of(key: np.ndarray, parts: int) -> np.ndarray:
    """A part for each key, the same in every task."""
    h = key.astype(np.int64, copy=False).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((h ^ (h >> np.uint64(29))) >> np.uint64(8)) % np.uint64(parts)


def trim() -> None:
    """Gives a part's memory back to the system: a reused Python worker would keep it."""
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)
    pa.default_memory_pool().release_unused()


def joined(key: np.ndarray, value: np.ndarray) -> np.ndarray | None:
    """Pairs as one number each, which sort by key, then value; nothing if some don't fit."""
    if len(key) and key.min() >= 0 and key.max() < 1 << 31 and value.min() >= -(1 << 31) and value.max() < 1 << 31:
        return (key << 32) | (value + (1 << 31))
    return None


def parted(both: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys and values of ``joined``."""
    return both >> 32, (both & ((1 << 32) - 1)) - (1 << 31)


class Dealer:
    """Cuts shares of pairs (key, value) into rows by a hash of the key."""

    def __init__(self, parts: int, side: int = 0):
        self.parts, self.side, self.held, self.size = parts, side, [], 0

    def add(self, key: np.ndarray, value: np.ndarray) -> Iterator[pa.RecordBatch]:
        for a in range(0, len(key), SHARE):
            self.held.append((key[a : a + SHARE], value[a : a + SHARE]))
            self.size += len(self.held[-1][0])
            if self.size >= SHARE:
                yield from self.rest()

    def rest(self) -> Iterator[pa.RecordBatch]:
        if self.size:
            key, value = (np.concatenate(c).astype(np.int64, copy=False) for c in zip(*self.held))
            part = part_of(key, self.parts).astype(np.uint16 if self.parts < 1 << 16 else np.int64)
            order = np.argsort(part, kind="stable")
            both = joined(key, value)
            sorts = [c[order] for c in ((key, value) if both is None else (both,))]
            part = part[order]
            cuts = np.flatnonzero(np.diff(part.astype(np.int64), prepend=-1))
            pieces = list(zip(cuts.tolist(), np.append(cuts[1:], len(part)).tolist()))
            data = [[c[a:b].tobytes() for a, b in pieces] for c in sorts] + [[None] * len(pieces)]
            cols = [pa.array(part[cuts], pa.int32()), pa.array(np.full(len(cuts), self.side), pa.int32()), *(pa.array(c, pa.binary()) for c in data[:2])]
            yield pa.RecordBatch.from_arrays(cols, names=["part", "side", "k", "x"])
        self.held, self.size = [], 0


def dealt(pairs: DataFrame, parts: int, side: int = 0, turned: bool = False) -> DataFrame:
    """The pairs of two columns, without null keys, as rows of arrays; ``turned`` deals each turned round, too."""
    key, value = pairs.columns

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dealer = Dealer(parts, side)
        for batch in batches:
            k, x = (np.asarray(c) for c in batch.columns)
            yield from dealer.add(k, x)
            if turned:
                yield from dealer.add(x, k)
        yield from dealer.rest()

    return pairs.where(f"{key} is not null and {value} is not null").mapInArrow(work, DEALT)


def meet(rows: DataFrame, parts: int) -> DataFrame:
    """Rows of arrays, each part in a partition of its own."""
    return rows.repartitionById(parts, "part")


def _pairs(batch: pa.RecordBatch, i: int) -> tuple[np.ndarray, ...]:
    """(pairs as one number,) or (keys, values) of a row."""
    return tuple(np.frombuffer(x.as_buffer(), np.int64) for x in (batch.column(2)[i], batch.column(3)[i]) if x.is_valid)


def _rows(batches: Iterator[pa.RecordBatch], n: int) -> list[list[tuple[np.ndarray, ...]]]:
    held: list[list] = [[] for _ in range(n)]
    for batch in batches:
        for i, side in enumerate(batch.column(1).to_pylist()):
            held[side].append(_pairs(batch, i))
    return held


def _both(rows: list[tuple[np.ndarray, ...]]) -> tuple[np.ndarray, np.ndarray]:
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    if all(len(r) == 1 for r in rows):
        return parted(np.concatenate([r[0] for r in rows]))
    return tuple(np.concatenate(c) for c in zip(*(r if len(r) == 2 else parted(r[0]) for r in rows)))


def sides(batches: Iterator[pa.RecordBatch], n: int = 1) -> list[tuple[np.ndarray, np.ndarray]]:
    """The keys and values of each side of a task's part."""
    held, out = _rows(batches, n), []
    for own in held:
        out.append(_both(own))
        own.clear()
    return out


def sorted_pairs(key: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs by key, then value; as one number where both fit in 32 bits."""
    both = joined(key, value)
    if both is not None:
        both.sort()
        return parted(both)
    order = np.lexsort((value, key))
    return key[order], value[order]


def sorted_part(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
    """``sorted_pairs`` of a part of one side."""
    (rows,) = _rows(batches, 1)
    if rows and all(len(r) == 1 for r in rows):
        both = np.concatenate([r[0] for r in rows])
        rows.clear()
        both.sort()
        return parted(both)
    return sorted_pairs(*_both(rows))


@dataclass
class Lists:
    """Each vertex's neighbours along edges that go both ways: rows of ``LISTS``, pairs (vertex, neighbour) in order."""

    rows: DataFrame
    parts: int
    pairs: int


#: Rows of two numbers in an Arrow batch.
NUMBER_ROWS = 10_000


def both_lists(ends: DataFrame) -> Lists:
    """The distinct pairs of ``ends`` (src, dst), taken both ways, by their first one; written once.

    Each pair is dealt to both ends as it is, so that what is equal meets where the lists are made: edges are told apart,
    turned round and grouped in one shuffle.
    """
    spark = ends.sparkSession
    parts = parts_for(2 * ends.count(), spark.sparkContext.defaultParallelism)
    with store.batch_rows(spark, NUMBER_ROWS):
        rows = meet(dealt(ends.select(*(F.col(c).cast("long").alias(c) for c in ("src", "dst"))), parts, turned=True), parts)
        rows = store.written(rows.mapInArrow(partial(_lists, parts=parts), LISTS), "lists")
    return Lists(rows, parts, rows.agg(F.sum("pairs")).first()[0] or 0)


def _lists(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    key, value = sorted_part(batches)
    new = np.ones(len(key), bool)
    new[1:] = (key[1:] != key[:-1]) | (value[1:] != value[:-1])
    key, value = key[new], value[new]
    d = np.diff(np.append(np.flatnonzero(np.diff(key, prepend=key[:1] - 1)), len(key)))
    d = np.repeat(d, d)
    for a in range(0, len(key), SHARE):
        k, x, own = (c[a : a + SHARE] for c in (key, value, d))
        both = joined(k, x)
        data = [k, x] if both is None else [both, None]
        binary = [pa.array([c if c is None else c.tobytes()], pa.binary()) for c in (*data, own.astype(np.int32))]
        numbers = [pa.array(part_of(k[:1], parts), pa.int32()), pa.array([0], pa.int32())]
        yield pa.RecordBatch.from_arrays([*numbers, *binary, pa.array([len(k)], pa.int64())], names=[c.split()[0] for c in LISTS.split(", ")])
    trim()


def list_degrees(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    """(neighbour, the vertex's degree), dealt, of rows of ``LISTS``."""
    dealer = Dealer(parts)
    for batch in batches:
        for i in range(batch.num_rows):
            _, near = _both([_pairs(batch, i)])
            yield from dealer.add(near, np.frombuffer(batch.column(4)[i].as_buffer(), np.int32))
    yield from dealer.rest()
    trim()
