"""Vertex orders: who is processed when.

Every order is (vid, pos) with pos dense from 0.  Yield order puts first the vertices whose messages finish most: the
score of a vertex is the sum over its out-edges of 1 / in-degree of the destination, divided by its out-degree; the
exact form counts in units of 2**-40, so that engines agree.  Vertices without out-edges score 0 and come last.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layerflow import store
from layerflow.operators import arrays
from layerflow.operators.aggregate import degrees
from layerflow.operators.positions import dense_positions

UNIT = 1 << 40


def order_original(vertices: DataFrame) -> DataFrame:
    return dense_positions(vertices.select("vid"), [F.col("vid")])


def order_random(vertices: DataFrame, seed: int = 0) -> DataFrame:
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("vid").cast("string")))
    return dense_positions(vertices.select("vid", key.alias("_k")), [F.col("_k"), F.col("vid")]).select("vid", "pos")


def yield_scores(edges: DataFrame, vertices: DataFrame, cost: str = "out_degree", exact: bool = True) -> DataFrame:
    """(vid, score).  cost "none" leaves out the division by out-degree."""
    # dealt before they are summed: ends are too many for sums before the shuffle to pay; count and join take one deal,
    # which is why the count is of src
    edges = edges.select("src", "dst").repartition("dst")
    d_in = edges.groupBy("dst").agg(F.count("src").alias("d"))
    gain = F.call_function("div", F.lit(UNIT), F.col("d")) if exact else 1.0 / F.col("d")
    gains = edges.join(d_in.select("dst", gain.alias("g")).hint("shuffle_hash"), "dst").select("src", "g").repartition("src")
    sums = gains.groupBy("src").agg(F.sum("g").alias("s"), F.count("*").alias("n"))
    score = F.col("s") if cost == "none" else F.call_function("div", F.col("s"), F.col("n")) if exact else F.col("s") / F.col("n")
    scored = sums.select(F.col("src").alias("vid"), score.alias("score"))
    return vertices.select("vid").join(scored, "vid", "left").select("vid", F.coalesce("score", F.lit(0).cast("long") if exact else F.lit(0.0)).alias("score"))


def dealt_scores(edges: DataFrame | None, vertices: DataFrame, pairs: int, cost: str = "out_degree", lists: arrays.Lists | None = None) -> DataFrame:
    """The exact ``yield_scores`` of about ``pairs`` edges dealt as arrays, or of ``lists``; written once."""
    if lists:
        parts, gains = lists.parts, lists.rows.mapInArrow(partial(arrays.list_degrees, parts=lists.parts), arrays.DEALT)
    else:
        parts = arrays.parts_for(pairs, vertices.sparkSession.sparkContext.defaultParallelism)
        gains = arrays.meet(arrays.dealt(edges.select("dst", "src"), parts), parts).mapInArrow(partial(_gains, parts=parts), arrays.DEALT)
    with store.batch_rows(vertices.sparkSession, arrays.NUMBER_ROWS):
        met = arrays.meet(gains.unionByName(arrays.dealt(vertices.select("vid", F.lit(0).cast("long").alias("none")), parts, 1)), parts)
        return store.written(met.mapInArrow(partial(_scores, cost=cost), "vid long, score long"), "scores")


def _gains(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    """(source, the destination's in-degree) of a part's edges, all of each destination's."""
    ((dst, src),) = arrays.sides(batches)
    order = np.argsort(dst)
    dst, src = dst[order], src[order]
    d = np.diff(np.append(np.flatnonzero(np.diff(dst, prepend=dst[:1] - 1)), len(dst)))
    dealer = arrays.Dealer(parts)
    yield from dealer.add(src, np.repeat(d, d))
    yield from dealer.rest()
    arrays.trim()


def _scores(batches: Iterator[pa.RecordBatch], cost: str) -> Iterator[pa.RecordBatch]:
    """(vid, score) of a part's vertices (side 1) from their edges' destinations' in-degrees (side 0)."""
    (src, d), (vid, _) = arrays.sides(batches, 2)
    src, d = arrays.sorted_pairs(src, d)
    first = np.flatnonzero(np.diff(src, prepend=src[:1] - 1))
    score = np.zeros(len(vid), np.int64)
    if len(first):
        sums, src = np.add.reduceat(UNIT // d, first), src[first]
        if cost != "none":
            sums //= np.diff(np.append(first, len(d)))
        at = np.minimum(np.searchsorted(src, vid), len(src) - 1)
        score = np.where(src[at] == vid, sums[at], 0)
    yield pa.RecordBatch.from_arrays([pa.array(vid), pa.array(score)], names=["vid", "score"])
    arrays.trim()


def order_yield(edges: DataFrame | None, vertices: DataFrame, cost: str = "out_degree", exact: bool = True, pairs: int | None = None, lists: arrays.Lists | None = None) -> DataFrame:
    """(vid, score, pos); with the number of edges, ``pairs``, or with ``lists`` instead of edges by ``dealt_scores``."""
    scores = dealt_scores(edges, vertices, pairs, cost, lists) if exact and (pairs or lists) else yield_scores(edges, vertices, cost, exact)
    return dense_positions(scores, [F.desc("score"), F.col("vid")]).select("vid", "score", "pos")


def order_degree(edges: DataFrame, vertices: DataFrame, by: str = "in") -> DataFrame:
    """Fewest in-edges first, or most out-edges first."""
    key = F.col("d_in") if by == "in" else F.desc("d_out")
    return dense_positions(degrees(edges, vertices), [key, F.col("vid")]).select("vid", "pos")


def components(both: DataFrame, max_rounds: int = 100) -> DataFrame:
    """(vid, comp) of vertices with edges, comp being the smallest id of the component; ``both`` has each edge both ways.

    Each round hooks every vertex to its smallest neighbour, then contracts the edges to the hooks; what is left of a
    path shrinks by a factor a round, so rounds grow with the logarithm of the diameter.
    """
    edges, labels = both.select("src", "dst").where("src != dst"), None
    for _ in range(max_rounds):
        hook = store.written(edges.groupBy("src").agg(F.least(F.col("src"), F.min("dst")).alias("to")), "hooks")
        step = hook.select(F.col("src").alias("comp"), "to")
        labels = hook.select(F.col("src").alias("vid"), F.col("to").alias("comp")) if labels is None else store.written(labels.join(step, "comp", "left").select("vid", F.coalesce("to", "comp").alias("comp")), "labels")
        near, far = hook.select("src", F.col("to").alias("_s")), hook.select(F.col("src").alias("dst"), F.col("to").alias("_d"))
        edges = edges.join(near, "src").join(far, "dst").select(F.col("_s").alias("src"), F.col("_d").alias("dst")).where("src != dst").distinct()
        edges = store.written(edges, "contracted")
        if not edges.limit(1).count():
            break
    return labels


def order_rcm(edges: DataFrame, vertices: DataFrame, max_levels: int = 10_000) -> DataFrame:
    """Reverse breadth-first order from a vertex of lowest degree in each component, neighbours by parent and degree.

    All components, found by contraction first, advance together, a level a step.  Steps are written, so that plans stay
    short; their number is the largest eccentricity of a root, which suits the baseline's graphs.
    """
    both = store.written(edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).where("src != dst").distinct(), "both")
    d = both.groupBy("src").agg(F.count("*").alias("deg"))
    info = vertices.select("vid").distinct().join(d.withColumnRenamed("src", "vid"), "vid", "left").select("vid", F.coalesce("deg", F.lit(0).cast("long")).alias("deg"))
    comp = info.join(components(both, max_levels), "vid", "left").select("vid", "deg", F.coalesce("comp", "vid").alias("comp"))
    comp = store.written(comp, "comp")
    roots = comp.groupBy("comp").agg(F.min(F.struct("deg", "vid")).alias("r")).select("comp", F.col("r.vid").alias("vid"), F.col("r.deg").alias("deg"))
    level = store.written(roots.select("vid", "comp", "deg", F.lit(0).alias("level"), F.lit(0).cast("long").alias("rank")), "level")
    done, before = [level], level
    for n in range(1, max_levels):
        near = both.join(level.select(F.col("vid").alias("src"), "rank"), "src").groupBy("dst").agg(F.min("rank").alias("parent")).withColumnRenamed("dst", "vid")
        # a neighbour of a level is in it, in the one before or in the next
        fresh = near.join(before.select("vid").unionByName(level.select("vid")), "vid", "left_anti").join(comp, "vid")
        before, level = level, dense_positions(fresh, [F.col("parent"), F.col("deg"), F.col("vid")], "rank").select("vid", "comp", "deg", F.lit(n).alias("level"), "rank")
        level = store.written(level, "level")
        if not level.limit(1).count():
            break
        done.append(level)
        if len(done) > 32:  # keeps the plan of the union short
            done = [store.written(reduce(DataFrame.unionByName, done), "done")]
    return dense_positions(reduce(DataFrame.unionByName, done), [F.desc("comp"), F.desc("level"), F.desc("rank"), F.col("vid")]).select("vid", "pos")


def order_greedy_small(edges: list[tuple[int, int]], n: int) -> list[int]:
    """The ideal that the yield order approximates, for small graphs: re-scores after every step.

    Takes the vertex with the largest gain less the number of partial sums it would newly open.
    """
    out: dict[int, list[int]] = {v: [] for v in range(n)}
    d_in = [0] * n
    for u, v in edges:
        out[u].append(v)
        d_in[v] += 1
    left, opened, order, todo = d_in.copy(), set(), [], set(range(n))
    while todo:

        def worth(u: int) -> tuple[float, int]:
            gain = sum(1 / left[v] for v in out[u])
            return (gain - sum(v not in opened for v in out[u]) / max(1, len(out[u])), -u)

        u = max(todo, key=worth)
        todo.remove(u)
        order.append(u)
        for v in out[u]:
            left[v] -= 1
            opened.add(v)
    return order


def relabel_edges(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """Edges under new ids."""
    p = positions.select("vid", "pos")
    return edges.join(p.withColumnRenamed("vid", "src").withColumnRenamed("pos", "_s"), "src").join(p.withColumnRenamed("vid", "dst").withColumnRenamed("pos", "_d"), "dst").select(F.col("_s").alias("src"), F.col("_d").alias("dst"))


def relabel_rows(rows: DataFrame, positions: DataFrame) -> DataFrame:
    """Rows keyed by vid under new ids."""
    return rows.join(positions.select("vid", F.col("pos").alias("_p")), "vid").select(F.col("_p").alias("vid"), *[c for c in rows.columns if c != "vid"])
