"""Graphs built on the given tables: vertices (vid, kind), edges (src, dst), features (vid, tile, c0..).

Ids are dense: each kind of vertex follows the one before it.  Edges are distinct; a null endpoint drops its edge.
Features are integers, so that sums don't depend on the order of rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from layerflow import store
from layerflow.operators.positions import dense_positions
from layerflow.sources.tables import row_count, table

TILE = 64
FIXED_POINT = 65536
NEIGHBOURS = 5


@dataclass(frozen=True)
class Graph:
    name: str
    vertices: DataFrame
    edges: DataFrame
    features: DataFrame | None
    d: int = 8
    ends: DataFrame | None = None  # (src, dst) of edges that go both ways, not yet told apart

    def with_edges(self, edges: DataFrame) -> Graph:
        return replace(self, edges=edges, ends=None)


def clean_edges(edges: DataFrame, dedup: bool = True) -> DataFrame:
    """Edges without null endpoints, each once unless multiplicities are asked for."""
    edges = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src is not null and dst is not null")
    return edges.distinct() if dedup else edges


def both_ways(edges: DataFrame) -> DataFrame:
    """``clean_edges`` of edges and their reverses: of two ends one edge is told apart, then turned round."""
    ends = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src is not null and dst is not null")
    ends = ends.select(F.least("src", "dst").alias("lo"), F.greatest("src", "dst").alias("hi")).distinct()
    return ends.select(F.expr("explode(if(lo = hi, array(struct(lo AS src, hi AS dst)), array(struct(lo AS src, hi AS dst), struct(hi AS src, lo AS dst)))) AS e")).select("e.src", "e.dst")


def base_features(rows: DataFrame) -> DataFrame:
    """Eight integers from (vid, kind number k, amount a), a a non-negative integer."""
    v, k, a = F.col("vid"), F.col("k"), F.col("a")
    cols = [k + 1, a % 1000, F.call_function("div", a, F.lit(1000)) % 100, v % 97, (v * 31 + 7) % 101, (v * 17 + 3) % 89, (a * 7 + v) % 113, F.lit(50)]
    return rows.select("vid", F.lit(0).alias("tile"), *[c.cast("long").alias(f"c{i}") for i, c in enumerate(cols)])


def widen_features(features: DataFrame, d: int) -> DataFrame:
    """Features of width d from the eight of each vertex: component i mixes base column i mod 8 with the id."""
    base = [f"c{i}" for i in range(8)]

    def component(i: int) -> Column:
        return F.col(base[i]) if i < 8 else ((F.col(base[i % 8]) * (1 + i // 8) + F.col("vid") * 31 + i * 17) % 127)

    if d <= TILE:
        return features.select("vid", "tile", *[component(i).alias(f"c{i}") for i in range(d)])
    tiles = [F.struct(F.lit(t).alias("tile"), *[(component(t * TILE + j) if t * TILE + j < d else F.lit(0).cast("long")).alias(f"c{j}") for j in range(TILE)]) for t in range(-(-d // TILE))]
    return features.select("vid", F.explode(F.array(*tiles)).alias("t")).select("vid", "t.*")


def _amount(c: str) -> Column:
    return F.floor(F.abs(F.coalesce(F.col(c), F.lit(0.0)))).cast("long")


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers, orders, parts and suppliers; edges along keys and back."""
    t = lambda n: table(spark, sf_dir, n)
    nc, no, np = (row_count(spark, sf_dir, n) for n in ("customer", "orders", "part"))
    at = {"customer": 0, "orders": nc, "part": nc + no, "supplier": nc + no + np}
    cols = {"customer": ("c_custkey", "c_acctbal"), "orders": ("o_orderkey", "o_totalprice"), "part": ("p_partkey", "p_retailprice"), "supplier": ("s_suppkey", "s_acctbal")}
    rows = None
    for i, (name, (key, amount)) in enumerate(cols.items()):
        part = t(name).select((F.col(key) + at[name]).alias("vid"), F.lit(name).alias("kind"), F.lit(i).alias("k"), _amount(amount).alias("a"))
        rows = part if rows is None else rows.unionByName(part)
    line = t("lineitem").select((F.col("l_orderkey") + at["orders"]).alias("o"), (F.col("l_partkey") + at["part"]).alias("p"), (F.col("l_suppkey") + at["supplier"]).alias("s"))
    edges = t("orders").select(F.col("o_custkey").alias("src"), (F.col("o_orderkey") + at["orders"]).alias("dst"))
    edges = edges.unionByName(line.select(F.col("o").alias("src"), F.col("p").alias("dst"))).unionByName(line.select(F.col("p").alias("src"), F.col("s").alias("dst")))
    return Graph("trade", rows.select("vid", "kind"), both_ways(edges), base_features(rows), ends=edges)


def embgraph(spark: SparkSession, sf_dir: str) -> Graph:
    """Embeddings with their 64 components; sparse edges derived from returned first lines."""
    e = table(spark, sf_dir, "embeddings")
    n = row_count(spark, sf_dir, "embeddings")
    line = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_linenumber = 1")
    edges = line.select((F.col("l_partkey") % n).alias("src"), ((F.col("l_orderkey") * 31 + F.col("l_suppkey")) % n).alias("dst"))
    q = [F.floor(F.coalesce(F.element_at("embedding", i + 1).cast("double"), F.lit(0.0)) * FIXED_POINT).cast("long").alias(f"c{i}") for i in range(TILE)]
    return Graph("embgraph", e.select(F.col("vec_id").alias("vid"), F.lit("vector").alias("kind")), clean_edges(edges), e.select(F.col("vec_id").alias("vid"), F.lit(0).alias("tile"), *q), TILE)


def _nearest(batches: Iterator[pd.DataFrame], ids: np.ndarray, vectors: np.ndarray, k: int) -> Iterator[pd.DataFrame]:
    """Of each query (ids, vectors) and each batch of rows (dst, b) the k largest inner products: src, dst, s."""
    for batch in batches:
        if batch.empty:
            continue
        dst, rows = batch["dst"].to_numpy(), np.stack(batch["b"].to_numpy())
        # doubles hold these sums exactly up to 2^53, and multiply much faster
        exact = float(np.abs(rows).max()) * float(np.abs(vectors).max()) * vectors.shape[1] < 2**53
        kind = np.float64 if exact else np.int64
        rows = rows.astype(kind)
        for at in range(0, len(ids), 1024):
            products = (vectors[at : at + 1024].astype(kind) @ rows.T).astype(np.int64)
            for src, s in zip(ids[at : at + 1024], products):
                s[dst == src] = np.iinfo(np.int64).min
                least = np.partition(s, len(s) - k)[len(s) - k] if len(s) > k else s.min()
                near = np.flatnonzero((s >= least) & (dst != src))
                near = near[np.lexsort((dst[near], -s[near]))[:k]]
                yield pd.DataFrame({"src": src, "dst": dst[near], "s": s[near]})


#: Queries of one pass over all rows: 64 numbers of 8 bytes each, so 8 MB broadcast.
QUERY_BLOCK = 1 << 14


def knn(spark: SparkSession, sf_dir: str, k: int = NEIGHBOURS) -> Graph:
    """Each vector's k nearest by fixed-point inner product, by brute force.

    Blocks of vectors, of fixed size, are broadcast over all rows in turn; each batch of rows gives its k nearest.  The
    work is quadratic, as for any exact answer; the dealt nearest-neighbour operator is the way for large tables.
    """
    g = embgraph(spark, sf_dir)
    rows = store.written(g.features.select(F.col("vid").alias("dst"), F.array(*[f"c{i}" for i in range(TILE)]).alias("b")), "vectors")
    bounds = rows.agg(F.min("dst"), F.max("dst")).first()
    found = spark.createDataFrame([], "src long, dst long, s long")
    for lo in range(bounds[0], bounds[1] + 1, QUERY_BLOCK) if bounds[0] is not None else ():
        block = rows.where((F.col("dst") >= lo) & (F.col("dst") < lo + QUERY_BLOCK)).toPandas()
        if len(block):
            held = spark.sparkContext.broadcast((block["dst"].to_numpy(), np.stack(block["b"].to_numpy())))
            found = found.unionByName(rows.mapInPandas(lambda batches, held=held: _nearest(batches, *held.value, k), "src long, dst long, s long"))
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))
    return Graph("knn", g.vertices, found.withColumn("r", rank).where(F.col("r") <= k).select("src", "dst"), g.features, TILE)


def copurchase(spark: SparkSession, sf_dir: str) -> Graph:
    """Parts bought in one order."""
    p = table(spark, sf_dir, "part")
    pairs = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = pairs.select("l_orderkey", F.col("l_partkey").alias("dst"))
    edges = pairs.select("l_orderkey", F.col("l_partkey").alias("src")).join(other, "l_orderkey").where("src < dst")
    rows = p.select(F.col("p_partkey").alias("vid"), F.col("p_size").cast("long").alias("k"), _amount("p_retailprice").alias("a"))
    return Graph("copurchase", p.select(F.col("p_partkey").alias("vid"), F.lit("part").alias("kind")), both_ways(edges.select("src", "dst")), base_features(rows), ends=edges.select("src", "dst"))


def session(spark: SparkSession, sf_dir: str) -> Graph:
    """Each event to its user's next one."""
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    edges = e.select(F.col("event_id").alias("src"), F.lead("event_id").over(w).alias("dst"))
    rows = e.select(F.col("event_id").alias("vid"), F.hour("ts").cast("long").alias("k"), _amount("value").alias("a"))
    return Graph("session", e.select(F.col("event_id").alias("vid"), F.col("event_type").alias("kind")), clean_edges(edges), base_features(rows))


def _numbered(names: DataFrame, start: int) -> DataFrame:
    """(name, vid) of the distinct names in order, from ``start`` on."""
    return dense_positions(names.select("name").where("name is not null").distinct(), [F.col("name")]).select("name", (F.col("pos") + start).alias("vid"))


def links(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages and what their hyperlinks name."""
    pages = table(spark, sf_dir, "pages")
    n = row_count(spark, sf_dir, "pages")
    found = pages.select(F.col("page_id").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("name"))
    targets = _numbered(found, n)
    edges = found.join(targets, "name").select("src", F.col("vid").alias("dst"))
    vertices = pages.select(F.col("page_id").alias("vid"), F.lit("page").alias("kind")).unionByName(targets.select("vid", F.lit("target").alias("kind")))
    rows = pages.select(F.col("page_id").alias("vid"), F.lit(0).alias("k"), F.length("html").cast("long").alias("a")).unionByName(targets.select("vid", F.lit(1).alias("k"), F.length("name").cast("long").alias("a")))
    return Graph("links", vertices, clean_edges(edges), base_features(rows))


def hubs(spark: SparkSession, sf_dir: str) -> Graph:
    """Documents to a vertex of their language and one of their source: a few vertices with very many in-edges."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars")
    n = row_count(spark, sf_dir, "documents")
    langs = _numbered(docs.select(F.col("lang").alias("name")), n)
    n_langs = docs.select("lang").where("lang is not null").distinct().count()
    sources = _numbered(docs.select(F.col("source").alias("name")), n + n_langs)
    edges = docs.join(F.broadcast(langs), docs["lang"] == langs["name"]).select(F.col("doc_id").alias("src"), F.col("vid").alias("dst"))
    edges = edges.unionByName(docs.join(sources, docs["source"] == sources["name"]).select(F.col("doc_id").alias("src"), F.col("vid").alias("dst")))
    kinds = docs.select(F.col("doc_id").alias("vid"), F.lit("document").alias("kind")).unionByName(langs.select("vid", F.lit("language").alias("kind"))).unionByName(sources.select("vid", F.lit("source").alias("kind")))
    rows = docs.select(F.col("doc_id").alias("vid"), F.lit(0).alias("k"), F.col("n_chars").alias("a")).unionByName(langs.unionByName(sources).select("vid", F.lit(1).alias("k"), F.lit(0).cast("long").alias("a")))
    return Graph("hubs", kinds, clean_edges(edges), base_features(rows))


def turns(spark: SparkSession, sf_dir: str) -> Graph:
    """Turns of conversations in a row."""
    c = dense_positions(table(spark, sf_dir, "conversations"), [F.col("conv_id"), F.col("turn")])
    w = Window.partitionBy("conv_id").orderBy("turn")
    edges = c.select(F.col("pos").alias("src"), F.lead("pos").over(w).alias("dst"))
    rows = c.select(F.col("pos").alias("vid"), F.col("turn").alias("k"), F.length("text").cast("long").alias("a"))
    return Graph("turns", c.select(F.col("pos").alias("vid"), F.col("role").alias("kind")), clean_edges(edges), base_features(rows))


def geo(spark: SparkSession, sf_dir: str, with_items: bool = False) -> Graph:
    """Customers and suppliers to nations to regions; with_items adds benchmark items, which have no edges."""
    t = lambda n: table(spark, sf_dir, n)
    nr, nn, nc, ns = (row_count(spark, sf_dir, n) for n in ("region", "nation", "customer", "supplier"))
    parts = [("region", "r_regionkey", 0), ("nation", "n_nationkey", nr), ("customer", "c_custkey", nr + nn), ("supplier", "s_suppkey", nr + nn + nc)]
    if with_items:
        parts.append(("benchmark", "item_id", nr + nn + nc + ns))
    rows = None
    for i, (name, key, at) in enumerate(parts):
        part = t(name).select((F.col(key).cast("long") + at).alias("vid"), F.lit(name).alias("kind"), F.lit(i).alias("k"), F.col(key).cast("long").alias("a"))
        rows = part if rows is None else rows.unionByName(part)
    edges = t("nation").select((F.col("n_nationkey") + nr).alias("src"), F.col("n_regionkey").alias("dst"))
    edges = edges.unionByName(t("customer").select((F.col("c_custkey") + nr + nn).alias("src"), (F.col("c_nationkey") + nr).alias("dst")))
    edges = edges.unionByName(t("supplier").select((F.col("s_suppkey") + nr + nn + nc).alias("src"), (F.col("s_nationkey") + nr).alias("dst")))
    return Graph("isolated" if with_items else "geo", rows.select("vid", "kind"), clean_edges(edges), base_features(rows))


def isolated(spark: SparkSession, sf_dir: str) -> Graph:
    return geo(spark, sf_dir, True)


GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {g.__name__: g for g in (trade, embgraph, knn, copurchase, session, links, hubs, turns, geo, isolated)}
