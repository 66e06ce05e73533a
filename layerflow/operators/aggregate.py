"""One layer's neighbourhood aggregation, pushed from sources or pulled by destinations.

Push: source rows are read once and joined to their out-edges; partial sums form per destination before the shuffle and
are completed after it.  Pull: every edge ships its source's whole row to the destination's partition and only there is
it aggregated.  Both give equal results; their shuffles differ by the share of edges that meet within a map task.

Special cases: a vertex without in-edges has the zero row (also for max and min); a source without a feature row counts
as a zero row but keeps its edge; self-loops are ordinary edges.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from layerflow.functions.columns import floor_div, value_columns

AGGREGATORS = ("sum", "mean", "mean_in_message", "max", "min", "std", "both", "count")


def degrees(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """(vid, d_in, d_out) of every vertex."""
    ends = edges.select(F.col("dst").alias("vid"), F.lit(1).alias("i"), F.lit(0).alias("o")).unionByName(edges.select(F.col("src").alias("vid"), F.lit(0).alias("i"), F.lit(1).alias("o")))
    counts = ends.groupBy("vid").agg(F.sum("i").alias("d_in"), F.sum("o").alias("d_out"))
    return vertices.select("vid").join(counts, "vid", "left").select("vid", F.coalesce("d_in", F.lit(0)).alias("d_in"), F.coalesce("d_out", F.lit(0)).alias("d_out"))


def coefficients(edges: DataFrame, norm: str) -> DataFrame:
    """Edges with the factor of their message: 1/d_in of the destination, or 1/sqrt(d_out(src) d_in(dst))."""
    d_in = edges.groupBy("dst").agg(F.count("*").alias("d_in"))
    out = edges.join(d_in, "dst")
    if norm == "dst":
        return out.select("src", "dst", (1.0 / F.col("d_in")).alias("w"))
    d_out = edges.groupBy("src").agg(F.count("*").alias("d_out"))
    return out.join(d_out, "src").select("src", "dst", (1.0 / F.sqrt(F.col("d_out") * F.col("d_in"))).alias("w"))


def add_self_loops(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionByName(vertices.select(F.col("vid").alias("src"), F.col("vid").alias("dst"))).distinct()


def make_messages(edges: DataFrame, h: DataFrame, agg: str = "mean_in_message") -> DataFrame:
    """(dst, tile, c0..): a message for each edge, normalised where the aggregator does so in the message."""
    return _messages(edges, h, agg)[0]


def _messages(edges: DataFrame, h: DataFrame, agg: str, by: str | None = None) -> tuple[DataFrame, list[str]]:
    """Source rows on their out-edges."""
    cols = value_columns(h)
    if agg in ("mean_in_message", "both") and "w" not in edges.columns:
        edges = coefficients(edges, "dst" if agg == "mean_in_message" else "both")
    keep = ["src", "dst", *([by] if by else []), *(["w"] if "w" in edges.columns else [])]
    weight = F.col("w") if "w" in edges.columns else None
    out = edges.select(*keep).join(h, F.col("src") == F.col("vid"))
    values = [F.col(c) if weight is None else (F.col(c) * weight) for c in cols]
    return out.select(*([by] if by else []), "dst", "tile", *[v.alias(c) for v, c in zip(values, cols)]), cols


def _combined(cols: list[str], agg: str) -> list[Column]:
    if agg in ("sum", "mean", "mean_in_message", "both"):
        return [F.sum(c).alias(c) for c in cols]
    if agg in ("max", "min"):
        return [getattr(F, agg)(c).alias(c) for c in cols]
    if agg == "std":
        return [F.stddev_pop(c).alias(c) for c in cols]
    if agg == "count":
        return [F.count(c).alias(c) for c in cols]
    raise ValueError(f"no such aggregator: {agg}; there are {', '.join(AGGREGATORS)}")


def _finish(sums: DataFrame, vertices: DataFrame, h: DataFrame, edges: DataFrame, cols: list[str], agg: str, exact: bool, tiles: int) -> DataFrame:
    """Adds vertices without messages; divides for the mean at the end."""
    zero = F.lit(0).cast(h.schema[cols[0]].dataType if agg not in ("std", "both", "mean_in_message", "count") else ("long" if agg == "count" else "double"))
    every = vertices.select("vid", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))).alias("tile"))
    out = every.join(sums.withColumnRenamed("dst", "vid"), ["vid", "tile"], "left")
    n = F.coalesce(F.col("n_recv"), F.lit(0))
    values = []
    for c in cols:
        v = F.coalesce(F.col(c), zero)
        if agg == "mean":
            v = F.when(n > 0, floor_div(F.col(c), n) if exact else F.col(c) / n).otherwise(zero if exact else F.lit(0.0))
        values.append(v.alias(c))
    return out.select("vid", "tile", *values, n.alias("n_recv"))


def push_aggregate(edges: DataFrame, h: DataFrame, vertices: DataFrame, agg: str = "mean", exact: bool = True, tiles: int = 1) -> DataFrame:
    """(vid, tile, c0.., n_recv) of every vertex.  ``exact``: integer values, and means rounded down."""
    messages, cols = _messages(edges, h, agg)
    sums = messages.groupBy("dst", "tile").agg(*_combined(cols, agg), F.count("*").alias("n_recv"))
    return _finish(sums, vertices, h, edges, cols, agg, exact, tiles)


def pull_aggregate(edges: DataFrame, h: DataFrame, vertices: DataFrame, agg: str = "mean", exact: bool = True, tiles: int = 1, by: str | None = None) -> DataFrame:
    """The same from full rows shipped along every edge: no combining before the shuffle.

    ``by``: a column of the edges that all in-edges of a destination share, such as its batch; rows are dealt by it.
    """
    messages, cols = _messages(edges, h, agg, by)
    dealt = ["dst", "tile"] if by is None else [by, "dst", "tile"]
    sums = messages.repartition(*([by] if by else dealt)).groupBy(*dealt).agg(*_combined(cols, agg), F.count("*").alias("n_recv"))
    sums = sums.drop(by) if by else sums
    return _finish(sums, vertices, h, edges, cols, agg, exact, tiles)


def attention_aggregate(edges: DataFrame, h: DataFrame, vertices: DataFrame, left: list[float], right: list[float], slope: float = 0.2) -> DataFrame:
    """Softmax-weighted sums; an edge scores leaky(left . h(src) + right . h(dst)).  Two passes: largest score, then weights.

    Floats; one tile.  Scores only travel with edges, source rows once, in the second pass.
    """
    cols = value_columns(h)
    dot = lambda w: sum((F.col(c) * float(x) for c, x in zip(cols, w)), F.lit(0.0))
    score = h.select("vid", dot(left).alias("l"), dot(right).alias("r"))
    e = edges.select("src", "dst").join(score.select(F.col("vid").alias("src"), "l"), "src").join(score.select(F.col("vid").alias("dst"), "r"), "dst")
    raw = F.col("l") + F.col("r")
    e = e.select("src", "dst", F.when(raw > 0, raw).otherwise(raw * slope).alias("s"))
    top = e.groupBy("dst").agg(F.max("s").alias("top"))
    e = e.join(top, "dst").select("src", "dst", F.exp(F.col("s") - F.col("top")).alias("w"))
    sums = e.join(h, F.col("src") == F.col("vid")).groupBy("dst").agg(F.sum("w").alias("_w"), *[F.sum(F.col(c) * F.col("w")).alias(c) for c in cols], F.count("*").alias("n_recv"))
    out = vertices.select("vid").join(sums.withColumnRenamed("dst", "vid"), "vid", "left")
    return out.select("vid", F.lit(0).alias("tile"), *[F.coalesce(F.col(c) / F.col("_w"), F.lit(0.0)).alias(c) for c in cols], F.coalesce("n_recv", F.lit(0)).alias("n_recv"))


def combine_factor(edges: DataFrame, positions: DataFrame, parts: int, n_vertices: int) -> DataFrame:
    """Edges over distinct (map part, destination): how much combining before the shuffle shrinks it."""
    width = -(-n_vertices // parts)
    e = edges.join(positions.select(F.col("vid").alias("src"), "pos"), "src").select(F.call_function("div", F.col("pos"), F.lit(width)).alias("part"), "dst")
    return e.agg(F.count("*").alias("edges"), F.count_distinct("part", "dst").alias("messages"))
