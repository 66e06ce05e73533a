"""Approximate nearest neighbours with a hash-prefix forest.

Each tree gives every vector a long string of bits (signs of projections on random directions of the tree) and keeps
the strings in a sorted array.  A query descends in each tree to the longest prefix it shares with any entry, then all
trees ascend together, one bit at a time, until the entries under the query's prefixes are enough distinct candidates.
Candidates are scored on the original vectors; nothing else is.

Vectors are written once, dealt over shards of bounded size by the first bits of a routing string: one more such string
for all shards, so that vectors of one direction lie together.  Each shard has a forest of its own.  Queries come in
blocks of a bounded number of bytes, which are broadcast: a block passes over the written shards without a shuffle, and
only the shards' best are shuffled, to be merged.  A query visits the shards in order of the margin by which its own bits
would have to change, until they hold the share ``reach`` of all rows.  Equal vectors are indexed once, with their
``k + 1`` smallest ids: no query can return more of them, so this loses nothing.

Candidates are asked for as a share of the shard and some for each neighbour.  On isotropic vectors, whose nearest
neighbours are hardly nearer than others, a recall of 0.9 needs a large share of nearly all shards, which is what the
defaults are for; on clustered ones the forest's long prefixes and the routing find more with less (set ``share`` and
``reach`` lower and measure).

Defined results: vectors that are null, zero or hold null or non-finite components take no part, neither as query nor
as candidate; only vectors of the query's length are candidates; rows equal in id and vector count once, and a query's
own id is never its neighbour; with fewer candidates than k all are returned.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from layerflow.llm import store

SHARD_ROWS = 16_384
#: Candidates of a shard for each neighbour asked for, beside the share of its rows.
PER_NEIGHBOUR = 8
#: Bytes of a block of queries.
QUERY_BYTES = 32 << 20


class Forest:
    """Sorted arrays of ``bits``-long hash strings, one a tree."""

    def __init__(self, vectors: np.ndarray, trees: int, bits: int, seed: int):
        self.bits = bits
        rng = np.random.default_rng(seed)
        self.planes = [rng.standard_normal((vectors.shape[1], bits)).astype(np.float32) for _ in range(trees)]
        self.order, self.keys = [], []
        for plane in self.planes:
            keys = self._strings(vectors, plane)
            order = np.argsort(keys, kind="stable")
            self.order.append(order)
            self.keys.append(keys[order])
        self.rows = len(vectors)

    def _strings(self, vectors: np.ndarray, plane: np.ndarray) -> np.ndarray:
        signs = (vectors @ plane) > 0
        return signs.astype(np.uint64) @ (np.uint64(1) << np.arange(self.bits - 1, -1, -1, dtype=np.uint64))

    def ranges(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of every depth, tree and query: the entries that share that many leading bits."""
        low = np.zeros((self.bits + 1, len(self.keys), len(queries)), np.int32)
        high = np.zeros_like(low)
        for t, (plane, keys) in enumerate(zip(self.planes, self.keys)):
            q = self._strings(queries, plane)
            for depth in range(self.bits + 1):
                free = np.uint64(self.bits - depth)
                first = (q >> free) << free
                low[depth, t] = np.searchsorted(keys, first)
                high[depth, t] = np.searchsorted(keys, first | ((np.uint64(1) << free) - np.uint64(1)), "right")
        return low, high

    def candidates(self, low: np.ndarray, high: np.ndarray, q: int, wanted: int) -> np.ndarray:
        """Ascends from the longest prefixes until ``wanted`` distinct entries (or all) are found."""
        wanted = min(wanted, self.rows)
        total = (high[:, :, q] - low[:, :, q]).sum(axis=1, dtype=np.int64)  # grows as depth falls
        depth = int(np.flatnonzero(total >= wanted)[-1])
        while True:
            seen = np.zeros(self.rows, bool)
            for order, a, b in zip(self.order, low[depth, :, q].tolist(), high[depth, :, q].tolist()):
                seen[order[a:b]] = True
            found = np.flatnonzero(seen)
            if len(found) >= wanted or depth == 0:
                return found
            depth -= 1


def search_shard(rows: np.ndarray, ids: list[list[int]], queries: np.ndarray, query_ids: np.ndarray, k: int, trees: int, bits: int, share: float, seed: int) -> pd.DataFrame:
    """The k best of one shard for each query."""
    single = rows.astype(np.float32)
    forest = Forest(single, trees, bits, seed)
    keep = 2 * k + 24
    out: list[tuple[int, int, float]] = []
    for a in range(0, len(queries), 512):
        block = queries[a : a + 512]
        low, high = forest.ranges(block.astype(np.float32))
        for i, (q, own) in enumerate(zip(block, query_ids[a : a + 512].tolist())):
            found = forest.candidates(low, high, i, PER_NEIGHBOUR * k + math.ceil(share * len(rows)))
            if len(found) > keep:  # single precision first, with room for its error
                rough = single[found] @ q.astype(np.float32)
                edge = np.partition(rough, len(rough) - keep)[len(rough) - keep]
                found = found[rough >= edge - 1e-4 * (1 + abs(float(edge)))]
            exact = rows[found] @ q
            best = sorted((-s, v) for s, r in zip(exact.tolist(), found.tolist()) for v in ids[r] if v != own)[:k]
            out += [(own, v, -s) for s, v in best]
    return pd.DataFrame(out, columns=["query_id", "vec_id", "score"])


class Router:
    """Shards by the first ``bits`` signs of one more string, ``parts`` hashed parts to each prefix."""

    def __init__(self, dim: int, bits: int, seed: int):
        self.bits = bits
        self.plane = np.random.default_rng([seed, dim, 1]).standard_normal((dim, bits))
        self.prefixes = (np.arange(1 << bits)[:, None] >> np.arange(bits - 1, -1, -1)) & 1 == 1

    def of(self, vectors: np.ndarray) -> np.ndarray:
        return ((vectors @ self.plane) > 0) @ (1 << np.arange(self.bits - 1, -1, -1))

    def visits(self, queries: np.ndarray, rows: np.ndarray, reach: float) -> np.ndarray:
        """Whether each query visits each prefix: cheapest first, until they hold the share ``reach`` of the rows."""
        lean = queries @ self.plane
        cost = np.where(self.prefixes[None] == (lean > 0)[:, None], 0.0, np.abs(lean)[:, None]).sum(axis=2)
        order = np.argsort(cost, axis=1, kind="stable")
        before = np.cumsum(rows[order], axis=1) - rows[order]
        out = np.zeros(cost.shape, bool)
        np.put_along_axis(out, order, before < reach * rows.sum(), axis=1)
        return out


def usable(vector: str) -> F.Column:
    """Holds for vectors of finite numbers, not all zero."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.col(vector).isNotNull() & ~F.coalesce(bad, F.lit(True)) & F.exists(vector, lambda x: x != 0)


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vector: str = "embedding", trees: int = 64, bits: int = 16, share: float = 0.4, reach: float = 1.0, seed: int = 7, shard_rows: int = SHARD_ROWS, query_bytes: int = QUERY_BYTES) -> DataFrame:
    """The k nearest of ``vectors`` for each of ``queries`` by inner product: query_id, rank, vec_id, score."""
    norm = lambda df: df.select(F.col(id_col).cast("long").alias("i"), F.col(vector).cast("array<double>").alias("v")).where("i is not null").where(usable("v")).distinct()
    base, asked = norm(vectors), store.written(norm(queries), "queries")
    few = base.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("i"))).where(F.col("r") <= k + 1)
    points = store.written(few.groupBy("v").agg(F.sort_array(F.collect_list("i")).alias("ids")), "points")
    depth = max(0, min(10, math.ceil(math.log2(max(1, points.count()) / shard_rows))))

    def route(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            batch["dim"] = batch["v"].map(len).astype("int32")
            batch["prefix"] = np.zeros(len(batch), np.int32)
            for dim, part in batch.groupby("dim"):
                batch.loc[part.index, "prefix"] = Router(dim, depth, seed).of(np.stack(part["v"].to_list())).astype(np.int32)
            yield batch[["dim", "prefix", "v", "ids"]]

    routed = points.mapInPandas(route, "dim int, prefix int, v array<double>, ids array<long>")
    # one row a prefix and length of vectors, of which there are 2 ** 10 and few
    sizes = {(r.dim, r.prefix): r.n for r in routed.groupBy("dim", "prefix").agg(F.count("*").alias("n")).collect()}
    counts = {d: np.array([sizes.get((d, p), 0) for p in range(1 << depth)]) for d in {d for d, _ in sizes}}
    parts = [(d, p, math.ceil(n / (2 * shard_rows))) for (d, p), n in sizes.items()]  # a prefix of too many rows has several
    shards_of = base.sparkSession.createDataFrame(parts, "dim int, prefix int, parts int")
    keys = ["dim", "prefix", "part"]
    split = routed.join(F.broadcast(shards_of), ["dim", "prefix"]).withColumn("part", F.pmod(F.xxhash64("v"), F.col("parts")).cast("int")).drop("parts")
    shards = store.written(split.repartition(max(1, sum(n for *_, n in parts)), *keys).sortWithinPartitions(*keys, F.element_at("ids", 1)), "shards")
    store.discard(points)
    total = asked.agg(F.sum(F.size("v") * 8 + 8)).first()[0] or 0
    blocks = max(1, math.ceil(total / query_bytes))
    found = None
    for b in range(blocks):
        rows = asked.where(F.pmod(F.xxhash64("i"), F.lit(blocks)) == b).toPandas()
        by_dim = {d: (x["i"].to_numpy(), np.stack(x["v"].to_list()).astype(np.float64)) for d, x in rows.groupby(rows["v"].map(len))} if len(rows) else {}
        sent = shards.sparkSession.sparkContext.broadcast(by_dim)
        best = store.written(shards.mapInPandas(_search(sent, counts, depth, k, trees, bits, share, reach, seed), "query_id long, vec_id long, score double"), "best")
        sent.destroy()
        found = best if found is None else found.unionByName(best)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _search(sent, counts: dict[int, np.ndarray], depth: int, k: int, trees: int, bits: int, share: float, reach: float, seed: int):
    """Searches each run of rows of one shard, in the order they are stored, for the queries that visit it."""

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        dim, prefix = int(rows["dim"].iloc[0]), int(rows["prefix"].iloc[0])
        ids, queries = sent.value.get(dim, (np.zeros(0, np.int64), np.zeros((0, dim))))
        if len(ids):
            at = np.concatenate([np.flatnonzero(Router(dim, depth, seed).visits(queries[a : a + 1024], counts[dim], reach)[:, prefix]) + a for a in range(0, len(ids), 1024)])
            ids, queries = ids[at], queries[at]
        return search_shard(np.stack(rows["v"].to_list()).astype(np.float64), [list(map(int, x)) for x in rows["ids"]], queries, ids, k, trees, bits, share, seed)

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        shard = None
        for batch in batches:
            for key, part in batch.groupby(["dim", "prefix", "part"], sort=False):
                if held and key != shard:
                    yield one(pd.concat(held, ignore_index=True))
                    held = []
                shard = key
                held.append(part)
        if held:
            yield one(pd.concat(held, ignore_index=True))

    return work
