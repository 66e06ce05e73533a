"""Neighbourhood sampling, masks, frontiers and partition-local edges: what approximate or partial runs use."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from layerflow import store


def sample_neighbors(edges: DataFrame, fanout: int, seed: int = 0) -> DataFrame:
    """At most ``fanout`` in-edges of each vertex, by a hash of seed and edge."""
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("src").cast("string"), F.col("dst").cast("string")))
    rank = F.row_number().over(Window.partitionBy("dst").orderBy(key, "src"))
    return edges.select("src", "dst").withColumn("_r", rank).where(F.col("_r") <= fanout).drop("_r")


def mask_edges(edges: DataFrame, enabled: Column) -> DataFrame:
    """Edges with a flag; a masked run keeps those where it holds."""
    return edges.withColumn("enabled", F.coalesce(enabled, F.lit(False)))


def masked(edges: DataFrame) -> DataFrame:
    return edges.where("enabled").select("src", "dst")


def partition_local(edges: DataFrame, n_vertices: int, parts: int) -> DataFrame:
    """Edges within ranges of ids; those between ranges are dropped, which changes results."""
    width = -(-n_vertices // parts)
    part = lambda c: F.call_function("div", F.col(c), F.lit(width))
    return edges.where(part("src") == part("dst"))


def frontier(edges: DataFrame, targets: DataFrame, hops: int) -> DataFrame:
    """(vid, hop): vertices first reached after 0.. hops against the edges.

    A hop's vertices are written: the next hop and all later exclusions read them, none computes them again.
    """
    seen = store.written(targets.select("vid").distinct().withColumn("hop", F.lit(0)), "hop")
    last = seen
    for hop in range(1, hops + 1):
        near = edges.join(last.select(F.col("vid").alias("dst")), "dst", "left_semi").select(F.col("src").alias("vid")).distinct()
        last = store.written(near.join(seen, "vid", "left_anti").withColumn("hop", F.lit(hop)), "hop")
        seen = seen.unionByName(last)
    return seen


def khop_subgraph(edges: DataFrame, targets: DataFrame, hops: int) -> DataFrame:
    """Edges that the targets' ``hops`` layers need."""
    inner = frontier(edges, targets, hops - 1).select(F.col("vid").alias("dst")) if hops > 1 else targets.select(F.col("vid").alias("dst"))
    return edges.join(inner.distinct(), "dst", "left_semi")


def touched_share(edges: DataFrame, vertices: DataFrame, every: int, hops: int, fanout: int | None = None, seed: int = 0) -> DataFrame:
    """(seeds, touched, vertices) for the seeds vid % every = 0."""
    e = sample_neighbors(edges, fanout, seed) if fanout else edges
    seeds = vertices.where(F.col("vid") % every == 0)
    f = frontier(e, seeds, hops)
    return f.agg(F.count_if(F.col("hop") == 0).alias("seeds"), F.count("*").alias("touched")).join(vertices.agg(F.count("*").alias("vertices")))


def frontier_redundancy(edges: DataFrame, vertices: DataFrame, batch: int, hops: int) -> DataFrame:
    """(batch, hop, n): vertices that each batch of targets computes at each hop; over all, work against V."""
    b = F.call_function("div", F.col("vid"), F.lit(batch))
    last = vertices.select(b.alias("batch"), "vid")
    levels = last.withColumn("hop", F.lit(0))
    for hop in range(1, hops + 1):
        last = last.select("batch", F.col("vid").alias("dst")).join(edges, "dst").select("batch", F.col("src").alias("vid")).distinct()
        levels = levels.unionByName(last.withColumn("hop", F.lit(hop)))
    return levels.groupBy("batch", "hop").agg(F.count("*").alias("n"))


def subgraph_bytes(edges: DataFrame, targets: DataFrame, hops: int, d: int, itemsize: int) -> DataFrame:
    """Ids and rows that a stored computation graph of the targets takes."""
    e = khop_subgraph(edges, targets, hops).agg(F.count("*").alias("edges"))
    v = frontier(edges, targets, hops).agg(F.count("*").alias("rows"))
    return e.join(v).withColumn("bytes", F.col("edges") * 16 + F.col("rows") * d * itemsize)
