"""Layer-wise inference over a whole graph, its in-memory reference and the choice of projection side."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layerflow import store
from layerflow.functions.columns import value_columns
from layerflow.functions.weights import make_weights
from layerflow.operators.aggregate import attention_aggregate, pull_aggregate, push_aggregate
from layerflow.operators.layers import TILE, GatConv, GinConv, GraphConv, Layer, Propagate, SageConv, finish, linear, sgc  # noqa: F401
from layerflow.sources.graphs import Graph


@dataclass
class RunReport:
    """What a run took, layer by layer."""

    engine: str
    graph: str
    seconds: list[float] = field(default_factory=list)  # of layers that were run; a lazy plan has none
    status: str = "done"
    stages: list[dict] = field(default_factory=list)  # layer, stage and seconds
    messages: list[int] = field(default_factory=list)  # rows shuffled, layer by layer

    def rows(self) -> list[dict]:
        return [{"graph": self.graph, "engine": self.engine, "layer": i + 1, "seconds": s, "status": self.status} for i, s in enumerate(self.seconds)]


def model(kind: str, d: int, hidden: int = 8, classes: int = 4, weights: str = "lattice", shift: int | None = 4, layers: int = 2) -> list[Layer]:
    """Named models of ``layers`` layers: graphconv, sage, gin, sgc, gat."""
    widths = [d, *[hidden] * (layers - 1), classes]
    out: list[Layer] = []  # hidden is 128 in the experiments; small widths keep checks by SQL cheap
    for n in range(layers):
        a, b, last = widths[n], widths[n + 1], n == layers - 1
        more = {"act": "identity" if last else "relu", "shift": None if last else shift}
        w = lambda i, x=a, y=b, n=n: make_weights(3 * n + i, x, y, weights)
        if kind == "graphconv":
            out.append(GraphConv([w(0)], **more))
        elif kind == "sage":
            out.append(SageConv([w(0), w(1)], **more))
        elif kind == "gin":
            out.append(GinConv([w(0, a, hidden), w(1, hidden, b)], **more))
        elif kind == "gat":
            rng = np.random.default_rng(n)
            out.append(GatConv([make_weights(n, a, b, "glorot")], [rng.normal(size=b).tolist()], [rng.normal(size=b).tolist()], act=more["act"]))
        elif kind != "sgc":
            raise ValueError(f"no such model: {kind}")
    return sgc(layers, make_weights(0, d, classes, weights)) if kind == "sgc" else out


def projection_side(layer: Layer, d_in: int, d_out: int) -> str:
    """Whether to map rows before or after they are aggregated: the narrower side, where the order doesn't matter."""
    return "before" if isinstance(layer, GraphConv) and layer.agg in ("sum", "mean", "both", "mean_in_message") and d_out < d_in else "after"


def run_layer(g: Graph, h: DataFrame, layer: Layer, engine: str = "push", exact: bool = True, side: str = "after", width: int = 0) -> DataFrame:
    tiles = max(1, -(-(width or g.d) // TILE))
    if layer.agg == "attention":
        return _attention(g, h, layer)
    aggregate = {"push": push_aggregate, "pull": pull_aggregate}[engine]
    if side == "before":  # exact only for sums: a mean rounded down doesn't commute with the map
        mapped = linear(h, layer.weights[0])
        x = aggregate(g.edges, mapped, g.vertices, layer.agg, exact, max(1, -(-layer.weights[0].shape[1] // TILE))).drop("n_recv")
        return finish(x, layer.act, layer.shift)
    x = aggregate(g.edges, h, g.vertices, layer.agg, exact, tiles).drop("n_recv")
    return layer.apply(x, h)


def _attention(g: Graph, h: DataFrame, layer: GatConv) -> DataFrame:
    heads = []
    for w, left, right in zip(layer.weights, layer.left, layer.right):
        z = linear(h.select("vid", "tile", *[F.col(c).cast("double").alias(c) for c in value_columns(h)]), w)
        heads.append(attention_aggregate(g.edges, z, g.vertices, left, right, layer.slope).drop("n_recv"))
    out, width = heads[0], len(value_columns(heads[0]))
    for k, x in enumerate(heads[1:], 1):
        cols = value_columns(x)
        out = out.join(x.select("vid", *[F.col(c).alias(f"c{k * width + i}") for i, c in enumerate(cols)]), "vid")
    return finish(out, layer.act, None)


def infer_layerwise(g: Graph, layers: list[Layer], engine: str = "push", exact: bool = True, materialize: bool = False, side: str = "after") -> tuple[DataFrame, RunReport]:
    """(vid, tile, c0..) of all vertices after all layers.

    ``materialize`` writes each layer's rows to the shared folder before the next reads them: no layer is computed
    twice, and a lost executor costs one layer's tasks.  Without it the layers stay one lazy plan.
    """
    h, report, width = g.features, RunReport(engine, g.name), g.d
    for n, layer in enumerate(layers):
        began = time.time()
        choice = projection_side(layer, width, layer.weights[0].shape[1]) if side == "auto" and layer.weights else "after" if side == "auto" else side
        h = run_layer(g, h, layer, engine, exact, choice, width)
        width = sum(w.shape[1] for w in layer.weights) if layer.agg == "attention" else layer.weights[-1].shape[1] if layer.weights else width
        if materialize:
            context = h.sparkSession.sparkContext
            context.setJobDescription(f"{engine} layer {n + 1} of {g.name}")
            h = store.written(h, f"layer{n + 1}")
            context.setJobDescription(None)
            report.seconds.append(time.time() - began)
    if not materialize:
        report.status = "planned"
    return h, report


def reference_numpy(g: Graph, layers: list[Layer], exact: bool = True) -> dict[int, np.ndarray]:
    """The exact result of a small graph in driver memory; for tests."""
    feats = g.features.toPandas()
    cols = [c for c in feats.columns if c.startswith("c")]
    vids = sorted(r.vid for r in g.vertices.select("vid").distinct().collect())
    at = {v: i for i, v in enumerate(vids)}
    n_tiles = int(feats["tile"].max()) + 1 if len(feats) else 1
    h = np.zeros((len(vids), n_tiles * len(cols)), np.int64 if exact else np.float64)
    for row in feats.itertuples(index=False):
        if row.vid in at:
            h[at[row.vid], row.tile * len(cols) : (row.tile + 1) * len(cols)] = row[2:]
    edges = np.array([(at[r.src], at[r.dst]) for r in g.edges.collect()], np.int64).reshape(-1, 2)
    src, dst = edges.T
    d_in = np.bincount(dst, minlength=len(vids))
    d_out = np.bincount(src, minlength=len(vids))
    for layer in layers:
        x = np.zeros_like(h)
        if layer.agg in ("sum", "mean", "mean_in_message"):
            np.add.at(x, dst, h[src])
            if layer.agg != "sum":
                n = np.maximum(d_in, 1)[:, None]
                x = x // n if exact else x / n
        elif layer.agg == "both":
            np.add.at(x, dst, h[src] / np.sqrt(d_out[src] * d_in[dst])[:, None])
        elif layer.agg in ("max", "min"):
            x = np.full(h.shape, -np.inf if layer.agg == "max" else np.inf)
            (np.maximum if layer.agg == "max" else np.minimum).at(x, dst, h[src])
            x[d_in == 0] = 0
            x = x.astype(h.dtype)
        elif layer.agg == "attention":
            parts = []
            for w, left, right in zip(layer.weights, layer.left, layer.right):
                z = h @ w
                s = (z @ np.array(left))[src] + (z @ np.array(right))[dst]
                s = np.where(s > 0, s, layer.slope * s)
                top = np.full(len(vids), -np.inf)
                np.maximum.at(top, dst, s)
                e = np.exp(s - top[dst])
                total, y = np.zeros(len(vids)), np.zeros_like(z, dtype=float)
                np.add.at(total, dst, e)
                np.add.at(y, dst, z[src] * e[:, None])
                parts.append(y / np.where(total > 0, total, 1)[:, None])
            h = layer._end(np.concatenate(parts, 1))
            continue
        h = layer.apply_numpy(x, h)
    return {v: h[i] for v, i in at.items()}
