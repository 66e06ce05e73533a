"""Vertex-wise inference in batches, and the superbatch baseline with its caches."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layerflow import store
from layerflow.operators.layers import Layer
from layerflow.operators.progress import neighbor_cache
from layerflow.operators.sampling import frontier, sample_neighbors
from layerflow.operators.tiers import cache_replay
from layerflow.plans.layerwise import infer_layerwise
from layerflow.sources.graphs import Graph


def infer_targets(g: Graph, layers: list[Layer], targets: DataFrame, fanout: int | None = None, seed: int = 0, exact: bool = True) -> DataFrame:
    """Rows of the targets only: their in-neighbourhood of as many hops as there are layers is cut out and run."""
    edges = sample_neighbors(g.edges, fanout, seed) if fanout else g.edges
    # the cut-out is written: each layer and hop reads it, none computes it again
    reached = store.written(frontier(edges, targets, len(layers)), "reached")
    need = reached.select("vid")
    inner = reached.where(F.col("hop") < len(layers)).select(F.col("vid").alias("dst"))
    cut = store.written(edges.join(inner, "dst", "left_semi").select("src", "dst"), "cut")
    part = replace(g, vertices=g.vertices.join(need, "vid", "left_semi"), edges=cut, features=g.features.join(need, "vid", "left_semi"))
    out, _ = infer_layerwise(part, layers, exact=exact)
    return out.join(targets.select("vid").distinct(), "vid", "left_semi")


def infer_vertexwise(g: Graph, layers: list[Layer], n_vertices: int, batch: int, fanout: int | None = None, seed: int = 0) -> DataFrame:
    """All vertices, batch by batch of ids, each batch on its own: what batches share is computed again."""
    out = None
    for lo in range(0, n_vertices, batch):
        rows = store.written(infer_targets(g, layers, g.vertices.where((F.col("vid") >= lo) & (F.col("vid") < lo + batch)), fanout, seed), "batch")
        out = rows if out is None else out.unionByName(rows)
    return out


@dataclass
class SuperbatchReport:
    superbatch: int
    edges: int  # of the stored computation graphs
    cached_edges: int  # of them, those whose lists the neighbour cache holds
    rows: int  # that its batches compute, over all layers
    hits: int
    misses: int


def superbatch_baseline(g: Graph, layers: list[Layer], n_vertices: int, batch: int, superbatch: int, feature_rows: int, neighbor_ids: int, fanout: int | None = None, seed: int = 0) -> tuple[DataFrame, list[SuperbatchReport]]:
    """Superbatches of batches: adjacency of popular vertices is cached, computation graphs of all batches are written,
    then the batches' feature accesses go through a cache that evicts what is used latest, and each batch computes its
    own graph.

    A vertex that several batches need is computed by each: vertices are numbered by batch and id, so that one run over
    the batches' graphs side by side repeats that work.
    """
    cached = store.written(neighbor_cache(g.edges, g.vertices, neighbor_ids).select(F.col("vid").alias("dst"), F.lit(True).alias("cached")), "cached")
    edges = sample_neighbors(g.edges, fanout, seed) if fanout else g.edges
    number = lambda c: F.col("batch") * n_vertices + F.col(c)
    reports, out = [], None
    for n, lo in enumerate(range(0, n_vertices, batch * superbatch)):
        targets = g.vertices.where((F.col("vid") >= lo) & (F.col("vid") < lo + batch * superbatch)).select(F.call_function("div", F.col("vid"), F.lit(batch)).alias("batch"), "vid")
        last = seen = targets
        graph = None
        for _ in layers:
            e = last.select("batch", F.col("vid").alias("dst")).join(edges, "dst").select("batch", "src", "dst")
            graph = e if graph is None else graph.unionByName(e)
            last = e.select("batch", F.col("src").alias("vid")).distinct()
            seen = seen.unionByName(last)
        graph = store.written(graph.distinct(), "graphs")
        need = store.written(seen.distinct(), "need")
        counts = cache_replay(need.select("batch", F.col("vid").alias("item")), feature_rows).agg(F.sum("hits").alias("h"), F.sum("misses").alias("m")).first()
        sizes = graph.join(cached, "dst", "left").agg(F.count("*").alias("e"), F.count("cached").alias("c")).first()
        reports.append(SuperbatchReport(n, sizes["e"], sizes["c"], need.count() * len(layers), counts["h"] or 0, counts["m"] or 0))
        apart = replace(
            g,
            vertices=need.select(number("vid").alias("vid"), F.lit("copy").alias("kind")),
            edges=graph.select(number("src").alias("src"), number("dst").alias("dst")),
            features=need.join(g.features, "vid").withColumn("vid", number("vid")).drop("batch"),
        )
        rows, _ = infer_layerwise(apart, layers)
        wanted = targets.select(number("vid").alias("_n"), F.col("vid").alias("_v"))
        rows = store.written(rows.join(wanted, F.col("vid") == F.col("_n")).drop("vid", "_n").withColumnRenamed("_v", "vid").select(*rows.columns), "superbatch")
        store.discard(graph, need)
        out = rows if out is None else out.unionByName(rows)
    return out, reports


def refresh_incremental(g: Graph, layers: list[Layer], old: DataFrame, changed: DataFrame) -> DataFrame:
    """Results after the features of ``changed`` vertices changed: only what their out-edges reach is run again."""
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    affected = store.written(frontier(back, changed, len(layers)).select("vid").distinct(), "affected")
    fresh = infer_targets(g, layers, affected)
    return old.join(affected, "vid", "left_anti").unionByName(fresh)
