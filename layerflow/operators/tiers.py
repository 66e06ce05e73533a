"""Replay of a layer's two-tier store, and the bounded combiner that works by the same rules inside a push layer.

State is kept in flat arrays and changes a chunk at a time.  Rules: within a chunk its destinations are pinned; if they are more than the slots, the chunk is taken in slices of that
many by position; victims are the policy's lowest, ties by position; completed vertices free their slots at the end of
their slice; an eviction or reload moves one state.  A shard is one independent store; several divide the slots.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from layerflow import store
from layerflow.functions.columns import value_columns
from layerflow.operators import arrays
from layerflow.operators.policies import POLICIES

CHUNK_SCHEMA = "shard int, chunk long, kind string, vid long, dests int, reloads int, evictions int, finished int, parked int, resident int"


#: Steps, pending counts and ids fit in 31 bits of a key each.
_FAR = (1 << 31) - 1


class TierStore:
    """Pending counts and residency of one shard in flat arrays, a chunk at a time.

    Vertices are small numbers; a victim is the resident with the smallest key (rank, vertex) that isn't in the chunk.
    The smallest keys, up to a bound, lie sorted in a front, the latest of them in a short list of their own, so that a
    chunk never copies the front.  A key that changes is added anew and its old entry is told by not being the vertex's
    key any more; only a front used up looks at all residents, for the next ones.
    """

    #: Keys that a new front takes: one in 32 residents, within these limits.
    FRONT = (1 << 12, 1 << 17)
    #: Latest keys that are kept apart from the front.
    LATEST = 1 << 12

    def __init__(self, slots: int, policy: str, seed: int = 0):
        if slots < 1:
            raise ValueError("at least one slot")
        if policy not in POLICIES:
            raise ValueError(f"no such policy: {policy}; there are {', '.join(POLICIES)}")
        self.slots, self.policy = slots, policy
        self.rng = np.random.default_rng(seed)
        self.step = self.n_resident = self.n_parked = 0
        self.pending = np.zeros(0, np.int64)
        self.key = np.zeros(0, np.int64)
        self.reloads = np.zeros(0, np.int32)
        self.resident, self.seen, self.pinned = (np.zeros(0, bool) for _ in range(3))
        self.front, self.at, self.bound, self.width = np.zeros(0, np.int64), 0, -1, self.FRONT[0]
        self.latest = np.zeros(0, np.int64)

    def _room(self, n: int) -> None:
        if n > len(self.key):
            size = max(n, 2 * len(self.key), 1024)
            for name in ("pending", "key", "reloads", "resident", "seen", "pinned"):
                old = getattr(self, name)
                new = np.full(size, -1, np.int64) if name == "pending" else np.zeros(size, old.dtype)
                new[: len(old)] = old
                setattr(self, name, new)

    def _rank(self, v: np.ndarray, fresh: np.ndarray, left: np.ndarray, next_use: np.ndarray) -> np.ndarray:
        """Sets the keys that change and returns whose."""
        if self.policy in ("fifo", "random"):
            v = fresh
        if self.policy == "fewest":
            rank = left
        elif self.policy == "most":
            rank = _FAR - left
        elif self.policy == "farthest":
            rank = _FAR - np.minimum(next_use, _FAR)
        elif self.policy == "random":
            rank = self.rng.integers(0, _FAR, len(fresh))
        else:
            rank = np.full(len(v), self.step)
        self.key[v] = (rank.astype(np.int64) << 31) | v
        return v

    def _live(self, keys: np.ndarray) -> np.ndarray:
        """Which of sorted keys are residents' own, each once."""
        v = keys & _FAR
        live = self.resident[v] & (self.key[v] == keys)
        live[1:] &= keys[1:] != keys[:-1]
        return live

    def _refill(self, n: int) -> None:
        keys = self.key[np.flatnonzero(self.resident)]
        keys = keys[keys > self.bound]
        self.width = max(self.FRONT[0], min(self.FRONT[1], len(keys) >> 5))
        take = max(n, self.width)
        if len(keys) > take:
            keys = np.partition(keys, take - 1)[:take]
            self.front = np.sort(keys)
            self.bound = int(self.front[-1])
        else:
            self.front, self.bound = np.sort(keys), np.iinfo(np.int64).max
        self.at = 0

    def _insert(self, keys: np.ndarray) -> None:
        keys = keys[keys <= self.bound]
        if not len(keys):
            return
        self.latest = np.concatenate([self.latest, keys])
        self.latest.sort()
        if len(self.latest) > self.LATEST:
            front = self.front[self.at :]
            self.front, self.at = np.insert(front, np.searchsorted(front, self.latest), self.latest), 0
            self.latest = self.latest[:0]
            if len(self.front) > 4 * self.width:
                self.front = self.front[self._live(self.front)]
                if len(self.front) > 2 * self.width:
                    self.front = self.front[: 2 * self.width]
                    self.bound = int(self.front[-1])

    def _evict(self, n: int, pinned: np.ndarray) -> None:
        """Takes out the n residents with the smallest keys outside of ``pinned``."""
        self.pinned[pinned] = True
        kept = []
        while n:
            if self.at == len(self.front) and not len(self.latest):
                self._refill(n + len(pinned))
            old = self.front[self.at : self.at + 2 * n + 64]
            # beyond the last one looked at, the front may hold keys before the latest
            near = len(self.latest) if self.at + len(old) == len(self.front) else int(np.searchsorted(self.latest, old[-1], "right"))
            keys = old
            if near:
                keys = np.concatenate([old, self.latest[:near]])
                keys.sort()
            v, live = keys & _FAR, self._live(keys)
            held = self.pinned[v]
            found = np.flatnonzero(live & ~held)[:n]
            end = int(found[-1]) + 1 if len(found) == n else len(keys)
            self.resident[v[found]] = False
            kept.append(keys[:end][(live & held)[:end]])
            self.at += int(np.searchsorted(old, keys[end - 1], "right"))
            if near:
                self.latest = self.latest[int(np.searchsorted(self.latest[:near], keys[end - 1], "right")) :]
            n -= len(found)
        self.pinned[pinned] = False
        back = np.concatenate(kept)
        if len(back):
            self.latest = np.concatenate([back, self.latest])
            self.latest.sort()

    def take(self, v: np.ndarray, left: np.ndarray, seen: np.ndarray, next_use: np.ndarray | None = None) -> tuple[int, int, int]:
        """Takes a chunk's vertices, in order, with the messages they still wait for and whether they had any before.

        Returns reloads, evictions and finished ones.
        """
        self._room(int(v.max()) + 1 if len(v) else 0)
        back = out = done = 0
        for a in range(0, len(v), self.slots):
            part, wait = v[a : a + self.slots], left[a : a + self.slots]
            new = ~self.resident[part]
            fresh = part[new]
            over = self.n_resident + len(fresh) - self.slots
            if over > 0:
                self._evict(over, part)
                self.n_resident -= over
                self.n_parked += over
                out += over
            again = part[new & seen[a : a + self.slots]]
            if len(again):
                self.reloads[again] += 1
                self.n_parked -= len(again)
                back += len(again)
            self.resident[part] = wait != 0
            finished = len(part) - int(np.count_nonzero(wait))
            self.n_resident += len(fresh) - finished
            done += finished
            changed = self._rank(part, fresh, np.maximum(wait, 0), None if next_use is None else next_use[a : a + self.slots])
            self._insert(self.key[changed[self.resident[changed]]])
            self.step += 1
        return back, out, done

    def chunk(self, v: np.ndarray, messages: np.ndarray, d_in: np.ndarray, next_use: np.ndarray) -> tuple[int, int, int]:
        """``take`` of vertices whose pending counts are kept here.  d_in 0: never finishes."""
        self._room(int(v.max()) + 1 if len(v) else 0)
        left, seen = self.pending[v], self.seen[v]
        left = np.where(left < 0, d_in, left) - messages
        self.pending[v], self.seen[v] = np.where(left, left, -1), left != 0
        return self.take(v, left, seen, next_use)


def _chunks(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[list[np.ndarray]]:
    """The columns of each run of rows with equal first ``keys`` columns, over batch borders."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        cols = [np.asarray(c) for c in batch.columns]
        if not len(cols[0]):
            continue
        change = np.zeros(len(cols[0]), bool)
        for c in cols[:keys]:
            change[1:] |= c[1:] != c[:-1]
        if held and any(h[-1] != c[0] for h, c in zip(held[-1], cols[:keys])):
            yield [np.concatenate(x) for x in zip(*held)]
            held = []
        cuts = [0, *np.flatnonzero(change).tolist(), len(change)]
        for a, b in zip(cuts, cuts[1:]):
            if a:
                yield [np.concatenate(x) for x in zip(*held)]
                held = []
            held.append([c[a:b] for c in cols])
    if held:
        yield [np.concatenate(x) for x in zip(*held)]


@dataclass
class Replay:
    chunks: DataFrame  # shard, chunk, dests, reloads, evictions, finished, parked, resident
    reloads: DataFrame  # vid, reloads
    state_bytes: int

    def summary(self) -> DataFrame:
        c = self.chunks.agg(F.sum("evictions").alias("evictions"), F.sum("reloads").alias("reloads"), F.sum("finished").alias("finished"), F.max("resident").alias("most_resident"), F.max("parked").alias("most_parked"), F.avg(F.col("reloads") / F.col("dests")).alias("reload_share"))
        return c.withColumn("reload_bytes", F.col("reloads") * self.state_bytes).withColumn("evicted_bytes", F.col("evictions") * self.state_bytes)

    def reload_cdf(self) -> DataFrame:
        """(reloads, vertices, cumulative): unique reloaded vertices by how often."""
        n = self.reloads.groupBy("reloads").agg(F.count("*").alias("vertices"))
        return n.withColumn("cumulative", F.sum("vertices").over(Window.orderBy("reloads")))

    def parked_series(self) -> DataFrame:
        return self.chunks.groupBy("chunk").agg(F.sum("parked").alias("parked"))


def replay_tiers(trace: DataFrame, slots: int, policy: str = "fewest", seed: int = 0, shards: int = 1, state_bytes: int = 1, key: str = "dpos") -> Replay:
    """Replays a message trace (chunk, dst, cnt, d_in, dpos).

    One shard is one machine's store, so its trace passes one task; P shards are P machines with slots/P each, dealt by
    position, and as many tasks.
    """
    if policy not in POLICIES or slots < 1:
        TierStore(slots, policy)  # says what is wrong
    far = policy == "farthest"
    store.text_batches(trace.sparkSession)
    if "left" not in trace.columns:
        w = Window.partitionBy("dst").orderBy("chunk")
        trace = trace.withColumns({"left": F.col("d_in") - F.sum("cnt").over(w), "nxt": F.lead("chunk").over(w)})
    size = trace.agg(F.count("*").alias("n"), F.max("chunk").alias("last")).first()
    width = _width(size["n"], size["last"] or 0)
    k, cols = F.col(key), ["shard", "chunk", "k", "dst", "left", "seen"] + ["nxt"] * far
    t = trace.select(F.pmod(k, F.lit(shards)).cast("int").alias("shard"), "chunk", F.call_function("div", k, F.lit(shards)).alias("k"), "dst", F.col("left").cast("int").alias("left"), (F.col("left") + F.col("cnt") != F.col("d_in")).alias("seen"), F.coalesce("nxt", F.lit(_FAR)).cast("int").alias("nxt")).select(cols)
    # packing and sorting are shared by all tasks: a store's task gets the arrays of its chunks, not their rows
    return replay_packed(_pack(t.mapInArrow(partial(_shares, width=width), SHARES_SCHEMA), width), slots, policy, seed, shards, state_bytes)


def _width(n: int, last: int) -> int:
    """Chunks of a block, for n rows in chunks up to the last."""
    return min(_FAR, max(1, BLOCK * (last + 1) // max(1, n)))


def _pack(shares: DataFrame, width: int) -> DataFrame:
    return shares.repartition("shard", "block").sortWithinPartitions("shard", "block").mapInArrow(partial(_packed, width=width), PACKED_SCHEMA)


def packed_runs(edges: DataFrame | None, positions: DataFrame, rows: int, far: bool = False, shards: int = 1, lists: arrays.Lists | None = None) -> DataFrame:
    """The chunks of ``progress.message_runs`` as arrays for ``replay_packed``, written once; ``far`` adds next chunks.

    Edges, or ``lists`` instead of them, meet their sources' positions, then messages their destinations, dealt as arrays;
    no trace of rows is made.
    """
    if rows < 1:
        raise ValueError("a chunk has at least one row")
    spark = positions.sparkSession
    store.text_batches(spark)
    n, last = lists.pairs if lists else edges.count(), (positions.agg(F.max("pos")).first()[0] or 0) // rows
    parts, width = lists.parts if lists else arrays.parts_for(n, spark.sparkContext.defaultParallelism), _width(n, last)
    ends = lists.rows.select("part", "side", "k", "x") if lists else arrays.dealt(edges.select("src", "dst"), parts)
    ends = ends.unionByName(arrays.dealt(positions.select(F.col("vid").cast("long").alias("vid"), F.col("pos").cast("long").alias("pos")), parts, 1))
    sent = arrays.meet(ends, parts).mapInArrow(partial(_sent, rows=rows, parts=parts), arrays.DEALT)
    shares = arrays.meet(sent, parts).mapInArrow(partial(_run_shares, width=width, far=far, shards=shards), SHARES_SCHEMA)
    return store.written(_pack(shares, width), "packed")


def packed_peak(packed: DataFrame) -> int:
    """``progress.trace_peak`` of packed chunks."""
    from layerflow.operators.progress import _peak

    moves = packed.select("chunk", "opened", "closed").mapInArrow(_moves, "chunk long, opened long, closed long")
    return _peak(moves.groupBy("chunk").agg(F.sum(F.col("opened") - F.col("closed")).alias("net"), F.sum("closed").alias("closed")))


def _moves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(batch.num_rows):
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(c[i].as_buffer(), np.int64)) for c in batch.columns], names=batch.schema.names)


def _sent(batches: Iterator[pa.RecordBatch], rows: int, parts: int) -> Iterator[pa.RecordBatch]:
    """(destination, chunk) of a part's edges (side 0) with a placed source, and (vertex, -1 - position) of its vertices (side 1)."""
    (src, dst), (vid, pos) = arrays.sides(batches, 2)
    order = np.argsort(vid)
    vid, pos = vid[order], pos[order]
    dealer = arrays.Dealer(parts)
    yield from dealer.add(vid, -1 - pos)
    for a in range(0, len(src) if len(vid) else 0, arrays.SHARE):
        at = np.minimum(np.searchsorted(vid, src[a : a + arrays.SHARE]), len(vid) - 1)
        known = vid[at] == src[a : a + arrays.SHARE]
        yield from dealer.add(dst[a : a + arrays.SHARE][known], pos[at[known]] // rows)
    yield from dealer.rest()
    arrays.trim()


def _run_shares(batches: Iterator[pa.RecordBatch], width: int, far: bool, shards: int) -> Iterator[pa.RecordBatch]:
    """Shares, as of ``_shares``, of a part's messages and positions."""
    from layerflow.operators.progress import _run_rows

    runs = _run_rows(*arrays.sorted_part(batches))
    for a in range(0, runs.num_rows, SHARE):
        chunk, dst, cnt, d_in, pos, left = (np.asarray(runs.column(i).slice(a, SHARE)) for i in range(6))
        nxt = [np.asarray(runs.column(6).slice(a, SHARE).fill_null(_FAR)).astype(np.int32)] if far else []
        yield _share(width, (pos % shards).astype(np.int32), chunk, pos // shards, dst, left.astype(np.int32), left + cnt != d_in, *nxt)
    arrays.trim()


def replay_packed(packed: DataFrame, slots: int, policy: str = "fewest", seed: int = 0, shards: int = 1, state_bytes: int = 1) -> Replay:
    """Replays packed chunks, made for the same shards (and with next chunks for ``farthest``)."""
    if policy not in POLICIES or slots < 1:
        TierStore(slots, policy)  # says what is wrong
    own = max(1, slots // shards)
    t = packed.drop("opened", "closed").repartition(shards, "shard").sortWithinPartitions("shard", "block")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, shard, rows = None, None, []
        names = np.zeros(0, np.int64)

        def pack(cols: list) -> pa.RecordBatch:
            kinds = [pa.int32(), pa.int64(), pa.string(), pa.int64(), *[pa.int32()] * 6]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=[x.split()[0] for x in CHUNK_SCHEMA.split(", ")])

        def leave() -> Iterator[pa.RecordBatch]:
            if rows:
                yield pack(list(zip(*rows)))
                rows.clear()
            again = np.flatnonzero(state.reloads) if state else np.zeros(0, np.int64)
            for a in range(0, len(again), 1 << 16):
                v = again[a : a + (1 << 16)]
                none = [None] * len(v)
                yield pack([np.full(len(v), shard), none, ["vertex"] * len(v), names[v], none, state.reloads[v], none, none, none, none])

        for s, chunks, ends, v, left, seen, dst, nxt in _unpacked(batches):
            if s != shard:
                yield from leave()
                state, shard, names = TierStore(own, policy, seed), s, np.zeros(0, np.int64)
            first = v[~seen]
            room = int(first.max()) + 1 if len(first) else 0
            if len(names) < room:
                names = np.concatenate([names, np.zeros(max(room, 2 * len(names)) - len(names), np.int64)])
            names[first] = dst
            for c, a, b in zip(chunks, [0, *ends], ends):
                back, out, done = state.take(v[a:b], left[a:b], seen[a:b], None if nxt is None else nxt[a:b])
                rows.append((shard, c, "chunk", None, b - a, back, out, done, state.n_parked, state.n_resident))
            if len(rows) >= 4096:
                yield pack(list(zip(*rows)))
                rows.clear()
        yield from leave()
        state = names = None
        arrays.trim()

    with store.batch_rows(packed.sparkSession, BLOCKS):
        out = store.written(t.mapInArrow(work, CHUNK_SCHEMA), "replay")
    chunks = out.where("kind = 'chunk'").drop("kind", "vid")
    return Replay(chunks, out.where("kind = 'vertex'").select("vid", "reloads"), state_bytes)


#: Rows of a share of the trace that one task packs, and about as many as a block of chunks has.
SHARE, BLOCK = 1 << 20, 1 << 17
#: Blocks in an Arrow batch.
BLOCKS = 8
SHARES_SCHEMA = "shard int, block long, at binary, wait binary, dst binary, nxt binary"
PACKED_SCHEMA = "shard int, block long, chunk binary, ends binary, v binary, wait binary, dst binary, nxt binary, opened binary, closed binary"


def _shares(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    """Rows (shard, chunk, k, dst, left, seen[, nxt]) as one row of arrays for each block of ``width`` chunks.

    ``at`` holds the chunk within the block and the vertex; ``wait`` what is left, less than 0 (-1 - left) for a vertex's
    first messages; ``dst`` the names of those alone.
    """
    held, size = [], 0
    pack = lambda: _share(width, *(np.asarray(c) for c in pa.Table.from_batches(held).columns))
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            size += batch.num_rows
            if size >= SHARE:
                yield pack()
                held, size = [], 0
    if held:
        yield pack()


def _share(width: int, shard, chunk, k, dst, left, seen, *nxt) -> pa.RecordBatch:
    block = chunk // width
    # few blocks fit in 16 bits, whose sort takes one pass over each byte
    place = (block - block.min()) * (int(shard.max()) + 1) + shard
    order = np.argsort(place.astype(np.uint16) if place.max() < 1 << 16 else place, kind="stable")
    shard, block = shard[order], block[order]
    at, wait, seen = (((chunk % width) << 31) | k)[order], np.where(seen, left, -1 - left).astype(np.int32)[order], seen[order]
    dst = dst[order][~seen]
    cuts = np.flatnonzero(np.diff(block, prepend=block[0] - 1) | np.diff(shard, prepend=shard[0]))
    names = np.concatenate([[0], np.cumsum(~seen)])
    ends = np.append(cuts[1:], len(at))
    pieces = list(zip(cuts.tolist(), ends.tolist()))
    data = [[x[a:b].tobytes() for a, b in pieces] for x in (at, wait)]
    data.append([dst[a:b].tobytes() for a, b in zip(names[cuts].tolist(), names[ends].tolist())])
    nxt = nxt[0][order] if nxt else None
    data.append([None] * len(pieces) if nxt is None else [nxt[a:b].tobytes() for a, b in pieces])
    return _row(SHARES_SCHEMA, pa.array(shard[cuts], pa.int32()), pa.array(block[cuts], pa.int64()), *(pa.array(x, pa.binary()) for x in data))


def _row(schema: str, *cols: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(list(cols), names=[x.split()[0] for x in schema.split(", ")])


def _packed(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    """One row of arrays for each block whose shares come together: its chunks, where each ends, and its vertices in order."""

    def pack(shard: int, block: int, shares: list[list]) -> pa.RecordBatch:
        at, wait, dst, *nxt = (np.concatenate([np.frombuffer(x.as_buffer(), kind) for x in c]) for c, kind in zip(zip(*shares), (np.int64, np.int32, np.int64, np.int32)) if c[0].is_valid)
        order = np.argsort(at)
        names = np.full(len(at), -1, np.int64)
        names[wait < 0] = dst
        at, wait, names = at[order], wait[order], names[order]
        dst = names[wait < 0]
        chunk = at >> 31
        cuts = np.flatnonzero(np.diff(chunk, prepend=-1))
        before, ended = (np.concatenate([[0], np.cumsum(x)]) for x in (wait < 0, (wait == 0) | (wait == -1)))
        ends = np.append(cuts[1:], len(at))
        nxt = nxt[0][order] if nxt else None
        data = [chunk[cuts] + block * width, ends, (at & _FAR).astype(np.int32), wait, dst, nxt, before[ends] - before[cuts], ended[ends] - ended[cuts]]
        return _row(PACKED_SCHEMA, pa.array([shard], pa.int32()), pa.array([block], pa.int64()), *(pa.array([None if x is None else x.tobytes()], pa.binary()) for x in data))

    now, held = None, []
    for batch in batches:
        for i, key in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())):
            if key != now and held:
                yield pack(*now, held)
                held = []
            now = key
            held.append([batch.column(j)[i] for j in range(2, 6)])
    if held:
        yield pack(*now, held)


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """(shard, chunks, where each ends, v, left, seen, names of those not seen, nxt or nothing) of each block."""
    kinds = (np.int64, np.int64, np.int32, np.int32, np.int64, np.int32)
    for batch in batches:
        for i, shard in enumerate(batch.column(0).to_pylist()):
            chunk, ends, v, wait, dst, nxt = (np.frombuffer(x.as_buffer(), kind) if x.is_valid else None for x, kind in zip((batch.column(j)[i] for j in range(2, 8)), kinds))
            seen = wait >= 0
            yield shard, chunk.tolist(), ends.tolist(), v.astype(np.int64), np.where(seen, wait, -1 - wait).astype(np.int64), seen, dst, None if nxt is None else nxt.astype(np.int64)


#: Sums of a chunk that are made at once where they pass the store.
PIECE = 1 << 13


class PartialSums:
    """At most ``slots`` partial sums of a task, by vertex, in flat arrays; what is evicted or complete is handed out."""

    def __init__(self, slots: int, policy: str, width: int, kind=np.int64):
        self.slots, self.policy = slots, policy
        self.ids = np.zeros(0, np.int64)
        self.sums = np.zeros((0, width), kind)
        self.count, self.left, self.rank = (np.zeros(0, np.int64) for _ in range(3))
        self.step = 0
        self.rng = np.random.default_rng(0)

    def add(self, dst: np.ndarray, values: np.ndarray, local: np.ndarray, at: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Messages of one chunk, with how many each destination gets in all from this task; yields (dst, count, sums).

        ``values`` has a row a message, or a row a source and ``at`` says which one a message carries: messages are then
        made a piece at a time, however many a chunk sends.
        """
        order = np.argsort(dst, kind="stable")
        ids = dst[order]
        first = np.flatnonzero(np.diff(ids, prepend=ids[:1] - 1))
        ids = ids[first]
        if not len(ids):
            return
        ends = np.append(first[1:], len(dst))
        count, local, row = ends - first, local[order[first]], order if at is None else at[order]

        def sums(a: int, b: int) -> np.ndarray:
            piece = values[row[first[a] : ends[b - 1]]]
            return piece if len(piece) == b - a else np.add.reduceat(piece, first[a:b] - first[a], axis=0)

        whole = len(ids) // self.slots
        for i, a in enumerate(range(0, len(ids), self.slots)):
            b = min(a + self.slots, len(ids))
            if i == 1 and whole > 2:
                # a slice of as many as there are slots leaves nothing else in the store: all but the last pass it at once
                b = (whole - 1) * self.slots
                yield self._take(np.arange(len(self.ids)))
                for c in range(a, b, PIECE):
                    d = min(b, c + PIECE)
                    yield ids[c:d], count[c:d], sums(c, d)
                self.step += whole - 2
                if self.policy == "random":
                    self.rng.integers(0, _FAR, b - a)
            elif not 1 < i < whole - 1:
                yield from self._slice(ids[a:b], sums(a, b), count[a:b], local[a:b])

    def _slice(self, ids, sums, count, local):
        self.step += 1
        at = np.searchsorted(self.ids, ids)
        known = np.zeros(len(ids), bool)
        near = at < len(self.ids)
        known[near] = self.ids[at[near]] == ids[near]
        old = at[known]
        self.sums[old] += sums[known]
        self.count[old] += count[known]
        self.left[old] -= count[known]
        pinned = np.zeros(len(self.ids), bool)
        pinned[old] = True
        fresh = ~known
        over = len(self.ids) + int(fresh.sum()) - self.slots
        if over > 0:
            free = np.flatnonzero(~pinned)
            gone = free[np.lexsort((self.ids[free], self.rank[free]))[:over]]
            yield self._take(gone)
        place = np.searchsorted(self.ids, ids[fresh])
        left = local[fresh] - count[fresh]
        self.ids, self.sums = np.insert(self.ids, place, ids[fresh]), np.insert(self.sums, place, sums[fresh], axis=0)
        self.count, self.left = np.insert(self.count, place, count[fresh]), np.insert(self.left, place, left)
        self.rank = np.insert(self.rank, place, self.rng.integers(0, _FAR, len(place)) if self.policy == "random" else self.step)
        mine = np.searchsorted(self.ids, ids)
        if self.policy in ("fewest", "most"):
            self.rank[mine] = self.left[mine] if self.policy == "fewest" else -self.left[mine]
        elif self.policy in ("lru", "farthest"):  # without a look ahead, the least recent is taken for the farthest
            self.rank[mine] = self.step
        done = np.flatnonzero(self.left <= 0)
        if len(done):
            yield self._take(done)

    def _take(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        out = self.ids[at], self.count[at], self.sums[at]
        keep = np.ones(len(self.ids), bool)
        keep[at] = False
        self.ids, self.sums, self.count, self.left, self.rank = self.ids[keep], self.sums[keep], self.count[keep], self.left[keep], self.rank[keep]
        return out

    def rest(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self._take(np.arange(len(self.ids)))


class HandedOn:
    """Partial sums that have left a task's store, added up by destination until the task ends.

    Destinations of a task are ``block``, ``block`` + ``blocks``, ...: ``rows`` of them, whose sums are held.
    """

    def __init__(self, rows: int, block: int, blocks: int, width: int, kind=np.int64):
        self.block, self.blocks = block, blocks
        self.sums = np.zeros((rows, width), kind)
        self.count, self.parts = np.zeros(rows, np.int64), np.zeros(rows, np.int64)

    def add(self, ids: np.ndarray, count: np.ndarray, sums: np.ndarray) -> None:
        at = ids // self.blocks
        self.sums[at] += sums
        self.count[at] += count
        self.parts[at] += 1

    def rest(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(dst, count, how many partial sums, sums), a piece at a time."""
        found = np.flatnonzero(self.parts)
        for a in range(0, len(found), PIECE):
            at = found[a : a + PIECE]
            yield at * self.blocks + self.block, self.count[at], self.parts[at], self.sums[at]


def push_combine_bounded(edges: DataFrame, h: DataFrame, vertices: DataFrame, slots: int, policy: str = "fewest", parts: int = 8, agg: str = "sum", chunk_rows: int = 1024) -> DataFrame:
    """A push layer's sum or mean (rounded down) with at most ``slots`` partial sums a task.

    Messages come in chunks of sources within ranges of sources; a task knows from counts made beforehand how many each
    destination will get from its range.  A full store emits a victim's partial sum to the shuffle; a destination
    whose local messages are all in leaves at once.  The final sum by destination completes them: what is evicted
    changes the shuffle's size, never the result.  One tile.
    """
    from layerflow.operators.aggregate import _finish

    cols = value_columns(h)
    chunk = F.call_function("div", F.col("src"), F.lit(chunk_rows))
    ranged = edges.select("src", "dst", F.pmod(F.xxhash64(chunk), F.lit(parts)).cast("int").alias("part"), chunk.alias("chunk"))
    local = ranged.groupBy("part", "dst").agg(F.count("*").alias("local"))
    m = ranged.join(local, ["part", "dst"]).join(h, F.col("src") == F.col("vid")).select("part", "chunk", "dst", "local", *cols)
    m = m.repartition(parts, "part").sortWithinPartitions("part", "chunk")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, part = PartialSums(slots, policy, len(cols)), None
        pack = lambda v, n, x: pa.RecordBatch.from_arrays([pa.array(v), pa.array(n), *(pa.array(np.ascontiguousarray(x[:, j])) for j in range(len(cols)))], names=["dst", "n", *cols])
        for p, _, dst, left, *values in _chunks(batches, 2):
            if p[0] != part and part is not None:
                yield pack(*sums.rest())
                sums = PartialSums(slots, policy, len(cols))
            part = p[0]
            for out in sums.add(dst, np.column_stack(values), left):
                yield pack(*out)
        yield pack(*sums.rest())

    partial = m.mapInArrow(work, "dst long, n long, " + ", ".join(f"{c} long" for c in cols))
    total = partial.groupBy("dst", F.lit(0).alias("tile")).agg(*[F.sum(c).alias(c) for c in cols], F.sum("n").alias("n_recv"))
    return _finish(total, vertices, h, edges, cols, agg, True, 1)


def cache_replay(accesses: DataFrame, capacity: int, policy: str = "farthest", sets: int = 1) -> DataFrame:
    """(batch, hits, misses) of a cache of ``capacity`` items over accesses (batch, item), Belady's or LRU.

    A batch's items are held together; a batch of more than the capacity passes in slices by item.  One set is one
    machine's cache in one task; more sets (by item) are a set-associative cache, each with its share and task.
    """
    w = Window.partitionBy("item").orderBy("batch")
    t = accesses.select("batch", "item").distinct().withColumn("nxt", F.coalesce(F.lead("batch").over(w), F.lit(2**40)))
    t = t.select(F.pmod("item", F.lit(sets)).cast("int").alias("s"), "batch", F.call_function("div", F.col("item"), F.lit(sets)).alias("item"), "nxt")
    t = t.repartition(sets, "s").sortWithinPartitions("s", "batch", "item")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, own, rows = None, None, []
        for s, batch, item, nxt in _chunks(batches, 2):
            if s[0] != own:
                state, own = TierStore(max(1, capacity // sets), policy), s[0]
            state._room(int(item.max()) + 1)
            hits = misses = 0
            for a in range(0, len(item), state.slots):
                part = item[a : a + state.slots]
                held = int(state.resident[part].sum())
                hits, misses = hits + held, misses + len(part) - held
                # pending counts never reach 0: items stay until they are evicted
                state.chunk(part, np.ones(len(part), np.int64), np.full(len(part), _FAR), nxt[a : a + state.slots])
            rows.append((int(batch[0]), hits, misses))
            if len(rows) >= 4096:
                yield _counts(rows)
                rows = []
        yield _counts(rows)

    found = t.mapInArrow(work, "batch long, hits long, misses long")
    return found if sets == 1 else found.groupBy("batch").agg(F.sum("hits").alias("hits"), F.sum("misses").alias("misses"))


def _counts(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [[], [], []]
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["batch", "hits", "misses"])


def page_trace(edges: DataFrame, batch: int, rows_per_block: int) -> DataFrame:
    """(batch, item): blocks of source rows that batches of destinations touch."""
    div = lambda c, n: F.call_function("div", F.col(c), F.lit(n))
    return edges.select(div("dst", batch).alias("batch"), div("src", rows_per_block).alias("item")).distinct()


def page_cache_replay(edges: DataFrame, batch: int, rows_per_block: int, blocks: int) -> DataFrame:
    """Hits and misses of a page cache with least-recent replacement under pulling."""
    return cache_replay(page_trace(edges, batch, rows_per_block), blocks, "lru")
