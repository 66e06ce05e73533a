"""How a layer progresses under an order: spans, partial sums open at a time, completion, chunks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from layerflow import store
from layerflow.operators.orders import UNIT
from layerflow.operators.positions import running_sum

_MOST, _WIDE = (1 << 63) - 1, "decimal(38,0)"


def chunk_rows(chunk_bytes: int, d: int, itemsize: int) -> int:
    """Rows of a chunk: edges don't count."""
    return max(1, chunk_bytes // (d * itemsize))


def slots_for(budget_bytes: int, width: int, itemsize: int) -> int:
    """Partial sums that a budget holds."""
    return budget_bytes // (width * itemsize)


def orchestrator_bytes(v: int) -> int:
    """In-degree, out-degree and pending count of four bytes each, and one of state, a vertex."""
    return v * 13


def assign_chunks(positions: DataFrame, rows: int) -> DataFrame:
    if rows < 1:
        raise ValueError("a chunk has at least one row")
    return positions.withColumn("chunk", F.call_function("div", F.col("pos"), F.lit(rows)))


def arrivals(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """Edges with the position of their source: (at, dst)."""
    return edges.join(positions.select(F.col("vid").alias("src"), F.col("pos").alias("at")).hint("shuffle_hash"), "src").select("at", "dst")


def vertex_span(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """(vid, first, last, span) of vertices with in-edges."""
    e = arrivals(edges, positions).groupBy("dst").agg(F.min("at").alias("first"), F.max("at").alias("last"))
    return e.select(F.col("dst").alias("vid"), "first", "last", (F.col("last") - F.col("first")).alias("span"))


def span_summary(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """Mean and exact percentiles of spans."""
    s = vertex_span(edges, positions)
    return s.agg(F.count("*").alias("n"), F.sum("span").alias("total"), *[F.expr(f"percentile_disc({p}) within group (order by span)").alias(f"p{int(p * 100)}") for p in (0.5, 0.9, 0.99)])


def chunk_events(edges: DataFrame, positions: DataFrame, rows: int) -> DataFrame:
    """(chunk, opened, closed): destinations that first and last receive in each chunk."""
    s = vertex_span(edges, positions)
    div = lambda c: F.call_function("div", F.col(c), F.lit(rows))
    opened = s.groupBy(div("first").alias("chunk")).agg(F.count("*").alias("opened"))
    closed = s.groupBy(div("last").alias("chunk")).agg(F.count("*").alias("closed"))
    chunks = positions.select(div("pos").alias("chunk")).distinct()
    out = chunks.join(opened, "chunk", "left").join(closed, "chunk", "left")
    return out.select("chunk", F.coalesce("opened", F.lit(0)).cast("long").alias("opened"), F.coalesce("closed", F.lit(0)).cast("long").alias("closed"))


def active_series(edges: DataFrame, positions: DataFrame, rows: int) -> DataFrame:
    """(chunk, during, after): open partial sums while and after each chunk."""
    ev = chunk_events(edges, positions, rows).withColumn("net", F.col("opened") - F.col("closed"))
    return running_sum(ev, "chunk", "net", "after").select("chunk", (F.col("after") + F.col("closed")).alias("during"), "after")


def finished_per_chunk(edges: DataFrame, positions: DataFrame, rows: int) -> DataFrame:
    return chunk_events(edges, positions, rows).select("chunk", F.col("closed").alias("finished"))


def active_peak(edges: DataFrame, positions: DataFrame, rows: int) -> DataFrame:
    """The largest number of partial sums open at a time: slots with which nothing is evicted."""
    return active_series(edges, positions, rows).agg(F.max("during").alias("peak"))


def trace_peak(trace: DataFrame) -> int:
    """``active_peak`` of a message trace's chunks; 0 without messages."""
    if "nxt" in trace.columns:
        ev = trace.groupBy("chunk").agg(F.sum((F.col("left") + F.col("cnt") == F.col("d_in")).cast("long")).alias("opened"), F.sum(F.col("nxt").isNull().cast("long")).alias("closed"))
        return _peak(ev.select("chunk", (F.col("opened") - F.col("closed")).alias("net"), "closed"))
    s = trace.groupBy("dst").agg(F.min("chunk").alias("first"), F.max("chunk").alias("last"))
    moves = s.select(F.explode(F.array(F.struct(F.col("first").alias("chunk"), F.lit(1).alias("opened"), F.lit(0).alias("closed")), F.struct(F.col("last").alias("chunk"), F.lit(0).alias("opened"), F.lit(1).alias("closed")))).alias("m"))
    ev = moves.groupBy("m.chunk").agg(F.sum(F.col("m.opened") - F.col("m.closed")).alias("net"), F.sum("m.closed").alias("closed"))
    return _peak(ev)


def _peak(ev: DataFrame) -> int:
    return running_sum(ev, "chunk", "net", "after").agg(F.max(F.col("after") + F.col("closed"))).first()[0] or 0


def recommend_slots(edges: DataFrame, positions: DataFrame, rows: int, tolerance: float = 0.0, cap: int | None = None) -> int:
    """Slots that leave at most a share ``tolerance`` of the peak without one, within a cap."""
    peak = active_peak(edges, positions, rows).first()["peak"] or 0
    wanted = int(-(-peak * (1 - tolerance) // 1))
    return min(wanted, cap) if cap else wanted


def completion_curve(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """(pos, done): what all destinations have received after each source, each counting 1 in the end, in 2**-40.

    ``done`` is a long as long as the last of it fits (2**23 destinations), else a decimal without fraction.
    """
    degrees = lambda: edges.groupBy("dst").agg(F.count("*").alias("d"))
    d_in, kind, unit = degrees(), "long", F.call_function("div", F.lit(UNIT), F.col("d"))
    if positions.count() * UNIT > _MOST:
        edges = store.written(edges.select("src", "dst"), "edges")
        d_in = store.written(degrees(), "degrees")
        if (d_in.agg(F.sum((unit * F.col("d")).cast(_WIDE))).first()[0] or 0) > _MOST:
            kind = _WIDE
    gain = edges.join(d_in, "dst").groupBy("src").agg(F.sum(unit.cast(kind)).alias("g"))
    steps = positions.select(F.col("vid").alias("src"), "pos").join(gain, "src", "left").select("pos", F.coalesce("g", F.lit(0)).cast(kind).alias("g"))
    return running_sum(steps, "pos", "g", "done").select("pos", "done")


def message_trace(edges: DataFrame, positions: DataFrame, rows: int, self_message: bool = False) -> DataFrame:
    """(chunk, dst, cnt, d_in, dpos): messages of each chunk by destination."""
    return message_runs(edges, positions, rows, self_message).select("chunk", "dst", "cnt", "d_in", "dpos")


RUNS_SCHEMA = "chunk long, dst long, cnt long, d_in long, dpos long, left long, nxt long"


def message_runs(edges: DataFrame, positions: DataFrame, rows: int, self_message: bool = False) -> DataFrame:
    """The message trace, with what is left for the destination after each chunk and its next chunk, null after the last.

    Positions travel among the messages of their vertex, first of them, so a destination's rows come together once.
    """
    if rows < 1:
        raise ValueError("a chunk has at least one row")
    if self_message:
        edges = edges.select("src", "dst").unionByName(positions.select(F.col("vid").alias("src"), F.col("vid").alias("dst")))
    e = arrivals(edges, positions).select("dst", F.call_function("div", F.col("at"), F.lit(rows)).alias("x"))
    both = e.unionByName(positions.select(F.col("vid").alias("dst"), (-1 - F.col("pos")).alias("x")))
    return both.repartition("dst").sortWithinPartitions("dst", "x").mapInArrow(_runs, RUNS_SCHEMA)


def _runs(batches: Iterator[pa.RecordBatch], rows: int = 1 << 16) -> Iterator[pa.RecordBatch]:
    """Trace rows from sorted (dst, x): x is a message's chunk, or -1 - position in the destination's first row."""
    held, size = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        dst, x = (np.asarray(c) for c in batch.columns)
        held.append((dst, x))
        size += len(dst)
        if size >= rows and dst[-1] != held[0][0][0]:
            dst, x = (np.concatenate(c) for c in zip(*held))
            end = int(np.searchsorted(dst, dst[-1]))
            yield _run_rows(dst[:end], x[:end])
            held, size = [(dst[end:], x[end:])], len(dst) - end
    if held:
        yield _run_rows(*(np.concatenate(c) for c in zip(*held)))


def _run_rows(dst: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
    placed = x < 0
    vid, pos = dst[placed], -1 - x[placed]
    known = np.zeros(len(dst), bool)
    if len(vid):
        at = np.searchsorted(vid, dst)
        known = ~placed & (vid[np.minimum(at, len(vid) - 1)] == dst)
    dst, chunk = dst[known], x[known]
    start = np.ones(len(dst), bool)
    start[1:] = (dst[1:] != dst[:-1]) | (chunk[1:] != chunk[:-1])
    start = np.flatnonzero(start)
    cnt, dst, chunk = np.diff(np.append(start, len(dst))), dst[start], chunk[start]
    first = np.flatnonzero(np.diff(dst, prepend=dst[:1] - 1))
    group = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(dst))))
    seen = np.cumsum(cnt)
    before = (seen - cnt)[first]
    d_in = (np.append(before[1:], seen[-1:]) - before)[group]
    nxt = np.append(chunk[1:], chunk[:1])
    last = np.zeros(len(dst), bool)
    last[np.append(first[1:], len(dst))[: len(first)] - 1] = True
    cols = [chunk, dst, cnt, d_in, pos[np.searchsorted(vid, dst)], d_in - (seen - before[group])]
    return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols), pa.array(nxt, pa.int64(), mask=last)], names=[c.split()[0] for c in RUNS_SCHEMA.split(", ")])


def state_census(edges: DataFrame, positions: DataFrame, rows: int, at_chunk: int) -> DataFrame:
    """Vertices with in-edges by state after a chunk, all slots being enough: not started, resident, completed."""
    s = vertex_span(edges, positions)
    first, last = (F.call_function("div", F.col(c), F.lit(rows)) for c in ("first", "last"))
    state = F.when(first > at_chunk, "not started").when(last > at_chunk, "resident").otherwise("completed")
    return s.groupBy(state.alias("state")).agg(F.count("*").alias("n"))


def illegal_transitions(log: DataFrame) -> DataFrame:
    """Rows of a state log (vid, step, state) that follow a state they must not follow."""
    w = Window.partitionBy("vid").orderBy("step")
    before = F.coalesce(F.lag("state").over(w), F.lit("not started"))
    legal = F.array(*[F.lit(x) for x in ("not started>resident", "resident>parked", "resident>completed", "parked>resident")])
    return log.withColumn("move", F.concat_ws(">", before, F.col("state"))).where(~F.array_contains(legal, F.col("move")))


# -- modelled reads ---------------------------------------------------------------------------


def push_read_bytes(n_vertices: int, n_edges: int, d: int, itemsize: int) -> int:
    """Every source row once, and the topology."""
    return n_vertices * d * itemsize + 8 * (n_vertices + n_edges)


def pull_read_blocks(edges: DataFrame, batch: int, rows_per_block: int) -> DataFrame:
    """(batch, blocks): distinct blocks of source rows that each batch of destinations reads."""
    div = lambda c, n: F.call_function("div", F.col(c), F.lit(n))
    return edges.select(div("dst", batch).alias("batch"), div("src", rows_per_block).alias("b")).groupBy("batch").agg(F.count_distinct("b").alias("blocks"))


def read_amplification(edges: DataFrame, n_vertices: int, batch: int, rows_per_block: int) -> DataFrame:
    """Blocks read by pulling over blocks that hold all rows, in thousandths."""
    once = -(-n_vertices // rows_per_block)
    total = pull_read_blocks(edges, batch, rows_per_block).agg(F.coalesce(F.sum("blocks"), F.lit(0)).alias("blocks"))
    return total.select("blocks", F.lit(once).cast("long").alias("once"), F.call_function("div", F.col("blocks") * 1000, F.lit(once)).alias("per_mille"))


def neighbor_cache(edges: DataFrame, vertices: DataFrame, budget: int) -> DataFrame:
    """Vertices whose in-neighbour lists a cache of ``budget`` ids holds, the most popular first."""
    from layerflow.operators.aggregate import degrees
    from layerflow.operators.positions import dense_positions

    ranked = dense_positions(degrees(edges, vertices), [F.desc("d_out"), F.col("vid")], "rank")
    return running_sum(ranked, "rank", "d_in", "used").where(F.col("used") <= budget).select("vid", "rank", "used")


def dynamic_batches(edges: DataFrame, positions: DataFrame, budget: int) -> DataFrame:
    """(vid, batch): consecutive destinations with about ``budget`` in-edges a batch."""
    d = edges.groupBy("dst").agg(F.count("*").alias("n"))
    rows = positions.select(F.col("vid"), "pos").join(d.withColumnRenamed("dst", "vid"), "vid", "left").select("vid", "pos", F.coalesce("n", F.lit(0)).cast("long").alias("n"))
    return running_sum(rows, "pos", "n", "seen").select("vid", F.call_function("div", F.col("seen") - F.col("n"), F.lit(budget)).alias("batch"))
