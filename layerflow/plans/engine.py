"""One run of the push engine over stored layers.

The graph is relabelled by the vertex order; its out-lists, and each layer's rows, are stored by ranges of new ids.  A task
reads a range chunk by chunk: rows and out-lists of the same vertices, in the same order.  Each chunk's messages are summed
by destination and merged into a resident store of bounded size; a full store gives partial sums up to the shuffle by the
eviction policy, a destination that this range owes nothing more leaves at once.  The shuffle completes the sums.  The
finisher gathers complete vertices in buffers and applies the layer's dense part to one buffer while the next one fills;
its rows become the next layer's spills.  Layers are separate jobs: what is lost with an executor is work on one layer.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layerflow import store
from layerflow.functions.columns import value_columns
from layerflow.operators import arrays, orders, storage
from layerflow.operators.layers import TILE, Layer
from layerflow.operators.policies import POLICIES
from layerflow.operators.tiers import HandedOn, PartialSums
from layerflow.plans.layerwise import RunReport
from layerflow.sources.graphs import Graph

ORDERS: dict[str, Callable[[Graph], DataFrame]] = {
    "original": lambda g: orders.order_original(g.vertices),
    "random": lambda g: orders.order_random(g.vertices),
    "yield": lambda g: orders.order_yield(g.edges, g.vertices),
    "degree": lambda g: orders.order_degree(g.edges, g.vertices),
    "rcm": lambda g: orders.order_rcm(g.edges, g.vertices),
}


@contextmanager
def stage(spark: SparkSession, report: RunReport, layer: int, name: str) -> Iterator[None]:
    """Times a stage and names its jobs; a stage that fails marks the run as not finished."""
    began = time.time()
    spark.sparkContext.setJobGroup(f"{report.engine}-{report.graph}-{layer}", f"{name}, layer {layer} of {report.graph}")
    try:
        yield
    except Exception:
        report.status = f"did not finish: {name}, layer {layer}"
        raise
    finally:
        report.stages.append({"layer": layer, "stage": name, "seconds": time.time() - began})
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        spark.sparkContext.setJobDescription(None)


#: Rows of sources whose lists a task makes into a batch.
LIST_ROWS = 1 << 12


def write_topology(g: Graph, path: str, n: int, n_ranges: int, positions: DataFrame | None = None, lists: arrays.Lists | None = None, blocks: int = 1) -> None:
    """Out-lists of each vertex by range, in order; beside each neighbour, how many messages it gets from the range in all.

    Edges (or ``lists`` instead of them) are dealt as arrays: to their sources' ``positions``, which become their ids, to
    their destinations, where messages are counted, and to the range.  A list is cut by the neighbours' ids modulo
    ``blocks``, so a vertex has up to so many rows.
    """
    spark = g.vertices.sparkSession
    pairs = lists.pairs if lists else g.edges.count()
    parts = lists.parts if lists else arrays.parts_for(pairs, spark.sparkContext.defaultParallelism)
    width, pieces = max(1, -(-n // n_ranges)), max(1, -(-pairs // (n_ranges * arrays.PART)))
    with store.batch_rows(spark, arrays.NUMBER_ROWS):
        if positions is None:
            ends = arrays.dealt(g.edges.select("dst", "src"), parts)
        else:
            placed = lambda: arrays.dealt(positions.select(F.col("vid").cast("long").alias("vid"), F.col("pos").cast("long").alias("pos")), parts, 1)
            ends = lists.rows.select("part", "side", "k", "x") if lists else arrays.dealt(g.edges.select("src", "dst"), parts)
            ends = arrays.meet(ends.unionByName(placed()), parts).mapInArrow(partial(_moved, parts=parts), arrays.DEALT).unionByName(placed())
        kind = "int" if n < 1 << 31 else "long"
        counted = arrays.meet(ends, parts).mapInArrow(partial(_counted, moved=positions is not None, width=width, pieces=pieces, kind=kind), "part int, src binary, dst binary, local binary")
        out = counted.repartitionById(n_ranges * pieces, "part").mapInArrow(partial(_out_lists, width=width, blocks=blocks, kind=kind), f"vid long, dst array<{kind}>, local array<{kind}>, block int, range_id int")
        out.write.partitionBy("range_id").parquet(path)


_KINDS = {"int": np.int32, "long": np.int64}


def _met(key: np.ndarray, vid: np.ndarray, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which pairs of a part have a vertex by that key, and its position; as often as there is one."""
    order = np.argsort(vid, kind="stable")
    vid, pos = vid[order], pos[order]
    lo = np.searchsorted(vid, key)
    if not len(vid) or (vid[1:] != vid[:-1]).all():
        known = np.flatnonzero(vid[np.minimum(lo, len(vid) - 1)] == key) if len(vid) else np.zeros(0, np.int64)
        return known, pos[lo[known]]
    n = np.searchsorted(vid, key, "right") - lo
    return np.repeat(np.arange(len(key)), n), pos[np.repeat(lo + n - np.cumsum(n), n) + np.arange(n.sum())]


def _moved(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    """(destination, position of the source) of a part's edges (side 0) by its vertices' positions (side 1)."""
    (src, dst), (vid, pos) = arrays.sides(batches, 2)
    dealer = arrays.Dealer(parts)
    at, pos = _met(src, vid, pos)
    yield from dealer.add(dst[at], pos)
    yield from dealer.rest()
    arrays.trim()


def _counted(batches: Iterator[pa.RecordBatch], moved: bool, width: int, pieces: int, kind: str) -> Iterator[pa.RecordBatch]:
    """Edges of a part's destinations, counted by the source's range, as shares of the ``pieces`` of each range."""
    (dst, src), (vid, pos) = arrays.sides(batches, 2)
    if moved:
        at, dst = _met(dst, vid, pos)
        src = src[at]
    dst, src = arrays.sorted_pairs(dst, src)
    where = src // width
    first = np.flatnonzero(np.diff(dst, prepend=dst[:1] - 1) | np.diff(where, prepend=where[:1]))
    local = np.diff(np.append(first, len(dst)))
    local = np.repeat(local, local)
    for a in range(0, len(dst), arrays.SHARE):
        s, d, c, r = (x[a : a + arrays.SHARE] for x in (src, dst, local, where))
        part = r * pieces + (s - r * width) * pieces // width
        order = np.argsort(part.astype(np.uint16) if 0 <= part.min() and part.max() < 1 << 16 else part, kind="stable")
        part = part[order]
        cuts = np.flatnonzero(np.diff(part, prepend=part[:1] - 1))
        ends = list(zip(cuts.tolist(), np.append(cuts[1:], len(part)).tolist()))
        data = [x[order].astype(_KINDS[kind]) for x in (s, d, c)]
        yield pa.RecordBatch.from_arrays([pa.array(part[cuts], pa.int32()), *(pa.array([x[i:j].tobytes() for i, j in ends], pa.binary()) for x in data)], names=["part", "src", "dst", "local"])
    arrays.trim()


def _out_lists(batches: Iterator[pa.RecordBatch], width: int, blocks: int, kind: str) -> Iterator[pa.RecordBatch]:
    """Rows of ``write_topology`` of a task's shares."""
    held: list[list[np.ndarray]] = [[], [], []]
    for batch in batches:
        for j, own in enumerate(held, 1):
            own.extend(np.frombuffer(x.as_buffer(), _KINDS[kind]) for x in batch.column(j))
    if not held[0]:
        return
    src, dst, local = (np.concatenate(own) for own in held)
    held.clear()
    order = np.lexsort((dst, src) if blocks == 1 else (dst, dst % blocks, src))
    src, dst, local = src[order], dst[order], local[order]
    block = dst % blocks
    cuts = np.append(np.flatnonzero(np.diff(src, prepend=src[:1] - 1) | np.diff(block, prepend=block[:1])), len(src))
    for a in range(0, len(cuts) - 1, LIST_ROWS):
        at = cuts[a : a + LIST_ROWS + 1]
        vid, own, piece = src[at[:-1]].astype(np.int64), block[at[:-1]], slice(at[0], at[-1])
        lists = [pa.ListArray.from_arrays(pa.array(at - at[0], pa.int32()), pa.array(x[piece])) for x in (dst, local)]
        yield pa.RecordBatch.from_arrays([pa.array(vid), *lists, pa.array(own, pa.int32()), pa.array(vid // width, pa.int32())], names=["vid", "dst", "local", "block", "range_id"])
    arrays.trim()


def iter_chunks(spark: SparkSession, topology: str, layer: str, chunk_rows: int) -> DataFrame:
    """(range_id, block, chunk, vid, tile, dst, local, c0..): topology and rows of the same vertices, in the same order."""
    rows = spark.read.parquet(layer).drop("spill")
    lists = spark.read.parquet(topology)
    both = rows.join(lists, ["range_id", "vid"]).withColumn("chunk", F.call_function("div", F.col("vid"), F.lit(chunk_rows)))
    return both.select("range_id", "block", "chunk", "vid", "tile", "dst", "local", *value_columns(rows))


#: Partial sums that a task hands on together, at least.
PACK = 1 << 13
#: Bytes of handed-on sums that a task adds up before the shuffle, and blocks of destinations at most.
HELD, BLOCKS = 160 << 20, 64


def blocks_for(n: int, width: int) -> int:
    """Blocks of destinations whose sums, of one tile, a task can hold."""
    return min(BLOCKS, max(1, -(-n * min(TILE, width) * 8 // HELD)))


def _sources(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[tuple]:
    """(key.., values of the sources, and their messages: dst, local, which source) of each chunk, over batch borders."""
    held: list[tuple] = []

    def chunk() -> tuple:
        key = held[0][0]
        size, dst, local, values = (np.concatenate(x) for x in list(zip(*held))[1:])
        held.clear()
        return key, values, dst, local, np.repeat(np.arange(len(size)), size)

    for b in batches:
        if not b.num_rows:
            continue
        cols = [np.asarray(b.column(j)) for j in range(keys)]
        lists = [b.column(j) for j in (keys, keys + 1)]
        ends = np.asarray(lists[0].offsets)
        dst, local = (np.asarray(x.values) for x in lists)
        values = np.column_stack([np.asarray(c) for c in b.columns[keys + 2 :]])
        change = np.zeros(b.num_rows, bool)
        for c in cols:
            change[1:] |= c[1:] != c[:-1]
        cuts = [0, *np.flatnonzero(change).tolist(), b.num_rows]
        for i, j in zip(cuts, cuts[1:]):
            key = tuple(int(c[i]) for c in cols)
            if held and held[0][0] != key:
                yield chunk()
            piece = slice(ends[i], ends[j])
            held.append((key, np.diff(ends[i : j + 1]), dst[piece], local[piece], values[i:j]))
    if held:
        yield chunk()


def combine(chunks: DataFrame, n_ranges: int, slots: int, policy: str, tiles: int = 1, n: int = 0, blocks: int = 1) -> DataFrame:
    """(dst, tile, n, parts, c0..): partial sums that leave the tasks' resident stores, a task for each range, tile and block.

    Of ``n`` destinations, those of a block that have left the store are added up in the task, if ``HELD`` bytes hold
    them; ``parts`` says how many partial sums that were.
    """
    cols = value_columns(chunks)
    kind = chunks.schema[cols[0]].dataType.simpleString()
    task = (F.col("range_id") * tiles + F.col("tile") % tiles) * blocks + F.col("block")
    dealt = chunks.repartitionById(n_ranges * tiles * blocks, task.cast("int")).sortWithinPartitions("range_id", "tile", "block", "chunk", "vid")
    dealt = dealt.select("range_id", "tile", "block", "chunk", "dst", "local", *cols)
    rows = -(-n // blocks)
    whole = 0 < rows * len(cols) * 8 <= HELD

    def rows_of(tile: int, v: np.ndarray, n: np.ndarray, parts: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(v, pa.int64()), pa.array(np.full(len(v), tile, np.int32)), pa.array(n), pa.array(parts), *(pa.array(np.ascontiguousarray(x[:, j])) for j in range(len(cols)))], names=["dst", "tile", "n", "parts", *cols])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        sums, key, left = None, None, None

        def take(out) -> None:
            held.append(out) if left is None else left.add(*out)

        def pack(least: int) -> Iterator[pa.RecordBatch]:
            if held and sum(len(f[0]) for f in held) >= least:
                v, n, x = (np.concatenate(c) for c in zip(*held))
                held.clear()
                yield rows_of(key[1], v, n, np.ones(len(v), np.int64), x)

        def leave() -> Iterator[pa.RecordBatch]:
            if sums is not None:
                take(sums.rest())
                yield from pack(1)
                if left is not None:
                    for v, n, parts, x in left.rest():
                        yield rows_of(key[1], v, n, parts, x)

        for own, values, dst, local, at in _sources(batches, 4):
            if key != own[:3]:
                yield from leave()
                sums, key = PartialSums(slots, policy, len(cols), values.dtype), own[:3]
                left = HandedOn(rows, own[2], blocks, len(cols), values.dtype) if whole else None
            for out in sums.add(dst, values, local, at):
                take(out)
            yield from pack(PACK)
        yield from leave()
        sums = left = None
        arrays.trim()

    return dealt.mapInArrow(work, f"dst long, tile int, n long, parts long, {', '.join(f'{c} {kind}' for c in cols)}")


class Finisher:
    """Applies a layer's dense part to buffers of complete vertices; a buffer is worked on while the next one fills.

    Rows come as (vid, n, x: array of the aggregate, own: array of the own row).
    """

    def __init__(self, layer: Layer, exact: bool, buffer_rows: int = 4096):
        if buffer_rows < 1:
            raise ValueError("a buffer has at least one row")
        self.layer, self.exact, self.buffer_rows = layer, exact, buffer_rows

    def apply(self, vid: np.ndarray, n: np.ndarray, x: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.layer.agg == "mean":
            n = np.maximum(n, 1)[:, None]
            x = x // n if self.exact else x / n
        return vid, self.layer.apply_numpy(x, own)

    def __call__(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = np.int64 if self.exact else np.float64
        matrix = lambda c, rows: np.asarray(c.flatten()).astype(kind, copy=False).reshape(rows, -1)
        with ThreadPoolExecutor(1) as thread:
            running = None
            for vid, n, x, own in self._buffers(batches):
                started = thread.submit(self.apply, np.asarray(vid), np.asarray(n), matrix(x, len(vid)), matrix(own, len(vid)))
                if running is not None:
                    yield from self._rows(*running.result())
                running = started
            if running is not None:
                yield from self._rows(*running.result())

    def _buffers(self, batches: Iterator[pa.RecordBatch]) -> Iterator[list[pa.Array]]:
        held, size = [], 0
        for batch in batches:
            while batch.num_rows:
                part = batch.slice(0, self.buffer_rows - size)
                batch = batch.slice(part.num_rows)
                held.append(part)
                size += part.num_rows
                if size == self.buffer_rows:
                    yield pa.Table.from_batches(held).combine_chunks().to_batches()[0].columns
                    held, size = [], 0
        if held:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0].columns

    def _rows(self, vid: np.ndarray, y: np.ndarray) -> Iterator[pa.RecordBatch]:
        """Tiles of the finished rows."""
        width = min(TILE, y.shape[1])
        for t in range(-(-y.shape[1] // TILE)):
            z = np.zeros((len(y), width), y.dtype)
            piece = y[:, t * TILE : (t + 1) * TILE]
            z[:, : piece.shape[1]] = piece
            yield pa.RecordBatch.from_arrays([pa.array(vid), pa.array(np.full(len(y), t, np.int32)), *(pa.array(np.ascontiguousarray(z[:, j])) for j in range(width))], names=["vid", "tile", *(f"c{j}" for j in range(width))])


def _whole(rows: DataFrame, key: list[str], width: int, name: str, more: list | None = None) -> DataFrame:
    """Tiles of a vertex as one array of ``width`` components."""
    cols = value_columns(rows)
    tiles = F.sort_array(F.collect_list(F.struct("tile", F.array(*cols).alias("v"))))
    return rows.groupBy(*key).agg(F.slice(F.flatten(F.transform(tiles, lambda t: t["v"])), 1, width).alias(name), *(more or []))


def finish_layer(sums: DataFrame, own: DataFrame, layer: Layer, width: int, out: int, exact: bool, buffer_rows: int) -> DataFrame:
    """(vid, tile, c0..) of all vertices from completed sums and own rows; vertices without messages have the zero sum."""
    kind = "long" if exact else "double"
    x = _whole(sums, ["dst"], width, "x", [F.max("n").alias("n")]).withColumnRenamed("dst", "vid")
    both = _whole(own, ["vid"], width, "own").join(x, "vid", "left")
    zero = F.array_repeat(F.lit(0).cast(kind), width)
    both = both.select("vid", F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.coalesce("x", zero).cast(f"array<{kind}>").alias("x"), F.col("own").cast(f"array<{kind}>").alias("own"))
    return both.mapInArrow(Finisher(layer, exact, buffer_rows), f"vid long, tile int, {', '.join(f'c{j} {kind}' for j in range(min(TILE, out)))}")


#: Spills of a file.
IN_FILE = 64


def run_engine(
    g: Graph, layers: list[Layer], order: str | DataFrame = "yield", slots: int = 1 << 20, policy: str = "fewest", exact: bool = True,
    n_ranges: int = 8, chunk_rows: int = 1024, spill_rows: int = 1 << 16, buffer_rows: int = 4096,
) -> tuple[DataFrame, RunReport]:
    """(vid, tile, c0..) of all vertices under their own ids, and what the run took, stage by stage.

    ``slots``: partial sums a task holds (``progress.slots_for`` makes them from a budget).  Layers aggregate by sum or
    mean; every vertex needs a feature row.  Rows wider than a tile are combined tile by tile.
    """
    if policy not in POLICIES or slots < 1:
        raise ValueError("at least one slot and a known policy")
    if any(x.agg not in ("sum", "mean") for x in layers):
        raise ValueError("the stored engine aggregates by sum or mean; see infer_layerwise for the others")
    spark, report = g.edges.sparkSession, RunReport("push", g.name)
    with stage(spark, report, 0, "order"):
        lists = None
        if g.ends is not None:  # written first: they are counted, then dealt
            ends = store.written(g.ends, "ends")
            lists = arrays.both_lists(ends)
            store.discard(ends)
        if order == "yield" and lists:
            order = orders.order_yield(None, g.vertices, lists=lists)
        pos = store.written((ORDERS[order](g) if isinstance(order, str) else order).select("vid", "pos"), "pos")
        n = pos.count()
    with stage(spark, report, 0, "layout"):
        topology, blocks = store.new_path(spark, "topology"), blocks_for(n, max([g.d, *(x.weights[-1].shape[1] for x in layers[:-1] if x.weights)]))
        write_topology(g, topology, n, n_ranges, pos, lists, blocks)
        if lists:
            store.discard(lists.rows)
        path = storage.write_layer(spark, orders.relabel_rows(g.features, pos), 0, n, n_ranges, spill_rows, IN_FILE)
    width = g.d
    for i, layer in enumerate(layers, 1):
        began = time.time()
        rows = spark.read.parquet(path).drop("range_id", "spill")
        with stage(spark, report, i, "gather and combine"):
            left = combine(iter_chunks(spark, topology, path, chunk_rows), n_ranges, slots, policy, -(-width // TILE), n, blocks)
            cols = value_columns(left)
            sums = left.groupBy("dst", "tile").agg(*[F.sum(c).alias(c) for c in cols], F.sum("n").alias("n"), F.sum("parts").alias("parts"))
            sums = store.written(sums, f"sums{i}")
            report.messages.append(sums.agg(F.sum("parts")).first()[0] or 0)
        with stage(spark, report, i, "finish"):
            out = layer.weights[-1].shape[1] if layer.weights else width
            before, path = path, storage.write_layer(spark, finish_layer(sums, rows, layer, width, out, exact, buffer_rows), i, n, n_ranges, spill_rows, IN_FILE)
            store.delete(spark, before)
            store.discard(sums)
        width = out
        report.seconds.append(time.time() - began)
    store.delete(spark, topology)
    back = spark.read.parquet(path).drop("range_id", "spill").withColumnRenamed("vid", "pos").join(pos, "pos")
    return back.select("vid", "tile", *value_columns(back)), report


def pull_baseline(g: Graph, layers: list[Layer], order: str | DataFrame = "rcm", batch_edges: int = 4096, exact: bool = True) -> tuple[DataFrame, RunReport]:
    """The pull baseline: vertices in a bandwidth-reducing order, batches of destinations with about ``batch_edges``
    in-edges, each of which ships its sources' whole rows to one place; layers are written.

    ``report.messages`` holds the rows shipped, layer by layer.
    """
    from layerflow.operators.aggregate import pull_aggregate
    from layerflow.operators.progress import dynamic_batches

    spark, report = g.edges.sparkSession, RunReport("pull", g.name)
    with stage(spark, report, 0, "order"):
        pos = store.written((ORDERS[order](g) if isinstance(order, str) else order).select("vid", "pos"), "pos")
    with stage(spark, report, 0, "layout"):
        edges = store.written(orders.relabel_edges(g.edges, pos), "edges")
        vertices = store.written(orders.relabel_rows(g.vertices, pos), "vertices")
        h = store.written(orders.relabel_rows(g.features, pos), "features")
        batches = dynamic_batches(edges, vertices.select("vid", F.col("vid").alias("pos")), batch_edges)
        edges = store.written(edges.join(batches.select(F.col("vid").alias("dst"), "batch"), "dst"), "batched")
    width = g.d
    for i, layer in enumerate(layers, 1):
        began = time.time()
        with stage(spark, report, i, "gather and compute"):
            x = pull_aggregate(edges, h, vertices, layer.agg, exact, max(1, -(-width // TILE)), by="batch").drop("n_recv")
            h = store.written(layer.apply(x, h), f"layer{i}")
            report.messages.append(edges.count() * max(1, -(-width // TILE)))
        width = layer.weights[-1].shape[1] if layer.weights else width
        report.seconds.append(time.time() - began)
    back = h.withColumnRenamed("vid", "pos").join(pos, "pos")
    return back.select("vid", "tile", *value_columns(back)), report


def modelled_reads(g: Graph, pos: DataFrame, d: int, itemsize: int, batch_edges: int, rows_per_block: int, cache_blocks: int) -> tuple[int, int]:
    """Bytes a layer reads: pushing (each row once and the topology) and pulling by dynamic batches through a page cache."""
    from layerflow.operators.progress import dynamic_batches, push_read_bytes
    from layerflow.operators.tiers import cache_replay

    edges = orders.relabel_edges(g.edges, pos)
    n, m = pos.count(), g.edges.count()
    batches = dynamic_batches(edges, pos.select(F.col("pos").alias("vid"), "pos"), batch_edges)
    touched = edges.join(batches.select(F.col("vid").alias("dst"), "batch"), "dst").select("batch", F.call_function("div", F.col("src"), F.lit(rows_per_block)).alias("item"))
    missed = cache_replay(touched, cache_blocks, "lru").agg(F.sum("misses")).first()[0] or 0
    return push_read_bytes(n, m, d, itemsize), missed * rows_per_block * d * itemsize + 8 * (n + m)

