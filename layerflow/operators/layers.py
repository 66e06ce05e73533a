"""Layer types: what a vertex makes of its own row and of its neighbourhood's aggregate.

The dense map is applied row by row with the weights sent once: as column expressions while the matrix is small, which
keeps the layer in one generated stage, else as NumPy products over Arrow batches; the tiles of a wide row are mapped
apart and their results summed, since the map is linear.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from layerflow.functions.columns import value_columns

TILE = 64
#: Matrices with more entries than this are multiplied in NumPy.
EXPRESSION_ENTRIES = 256
ACTIVATIONS = ("identity", "relu", "sigmoid", "tanh", "leaky")


def activate(x: Column, name: str) -> Column:
    if name == "identity":
        return x
    if name == "relu":
        return F.greatest(x, x * 0)
    if name == "sigmoid":
        return 1.0 / (1.0 + F.exp(-x))
    if name == "tanh":
        return F.tanh(x)
    if name == "leaky":
        return F.when(x > 0, x).otherwise(x * 0.01)
    raise ValueError(f"no such activation: {name}")


def _np_activate(x: np.ndarray, name: str) -> np.ndarray:
    return {"identity": lambda: x, "relu": lambda: np.maximum(x, 0), "sigmoid": lambda: 1 / (1 + np.exp(-x)), "tanh": lambda: np.tanh(x), "leaky": lambda: np.where(x > 0, x, 0.01 * x)}[name]()


def linear(x: DataFrame, w: np.ndarray, bias: np.ndarray | None = None) -> DataFrame:
    """(vid, tile, c0..) of x W + b."""
    cols, tiles = value_columns(x), -(-w.shape[0] // TILE)
    b = np.zeros(w.shape[1], w.dtype) if bias is None else bias
    if tiles == 1 and w.size <= EXPRESSION_ENTRIES and w.shape[1] <= TILE:
        whole = np.issubdtype(w.dtype, np.integer)
        lit = lambda v: F.lit(int(v) if whole else float(v))
        out = [sum((F.col(c) * lit(v) for c, v in zip(cols, w[:, j]) if v != 0), lit(b[j])) for j in range(w.shape[1])]
        return x.select("vid", F.lit(0).alias("tile"), *[o.cast("long" if whole else "double").alias(f"c{j}") for j, o in enumerate(out)])
    sent = x.sparkSession.sparkContext.broadcast((w, b))
    whole = np.issubdtype(w.dtype, np.integer)
    width = min(TILE, w.shape[1])
    out_tiles = -(-w.shape[1] // TILE)
    kind = "long" if whole else "double"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, b = sent.value
        for batch in batches:
            vid, tile = (np.asarray(batch.column(i)) for i in (0, 1))
            rows = np.column_stack([np.asarray(c) for c in batch.columns[2:]])
            for t in np.unique(tile).tolist():
                at = tile == t
                part = w[t * TILE : t * TILE + rows.shape[1]]
                y = rows[at][:, : len(part)] @ part + (b if t == 0 else 0)
                for o in range(out_tiles):
                    z = np.zeros((len(y), width), y.dtype)
                    piece = y[:, o * TILE : (o + 1) * TILE]
                    z[:, : piece.shape[1]] = piece
                    yield pa.RecordBatch.from_arrays([pa.array(vid[at]), pa.array(np.full(len(y), o, np.int32)), *(pa.array(np.ascontiguousarray(z[:, j])) for j in range(width))], names=["vid", "tile", *(f"c{j}" for j in range(width))])

    y = x.select("vid", "tile", *cols).mapInArrow(work, "vid long, tile int, " + ", ".join(f"c{j} {kind}" for j in range(width)))
    return y.groupBy("vid", "tile").agg(*[F.sum(f"c{j}").alias(f"c{j}") for j in range(width)]) if tiles > 1 else y


def finish(y: DataFrame, act: str, shift: int | None) -> DataFrame:
    """Activation, and for integers division by 2**shift, rounded down."""
    cols = value_columns(y)
    out = []
    for c in cols:
        v = activate(F.col(c), act)
        if shift:
            v = F.floor(v / F.lit(float(1 << shift)))
        out.append(v.cast(y.schema[c].dataType).alias(c))
    return y.select("vid", "tile", *out)


@dataclass
class Layer:
    """Weights, activation and the aggregator a layer asks for."""

    weights: list[np.ndarray]
    agg: str = "mean"
    act: str = "relu"
    shift: int | None = None
    bias: list[np.ndarray] = field(default_factory=list)
    own: bool = False  # needs the vertex's own row

    def aggregates(self) -> str:
        return self.agg

    def slot_width(self, d: int) -> int:
        return d

    def apply(self, x: DataFrame, own: DataFrame | None) -> DataFrame:
        raise NotImplementedError

    def apply_numpy(self, x: np.ndarray, own: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def _end(self, y: np.ndarray, act: str | None = None) -> np.ndarray:
        y = _np_activate(y, act or self.act)
        return np.floor(y / (1 << self.shift)).astype(y.dtype) if self.shift else y


class GraphConv(Layer):
    """A linear map of the aggregate."""

    def apply(self, x, own):
        return finish(linear(x, self.weights[0], self.bias[0] if self.bias else None), self.act, self.shift)

    def apply_numpy(self, x, own):
        return self._end(x @ self.weights[0] + (self.bias[0] if self.bias else 0))


class SageConv(Layer):
    """A linear map of own row and aggregate side by side: weights for the one, then for the other."""

    def __init__(self, weights, **more):
        super().__init__(weights, own=True, **more)

    def slot_width(self, d):
        return 2 * d

    def apply(self, x, own):
        a, b = linear(own, self.weights[0]), linear(x, self.weights[1])
        cols = value_columns(a)
        both = a.join(b.select("vid", "tile", *[F.col(c).alias(f"_{c}") for c in cols]), ["vid", "tile"])
        return finish(both.select("vid", "tile", *[(F.col(c) + F.col(f"_{c}")).alias(c) for c in cols]), self.act, self.shift)

    def apply_numpy(self, x, own):
        return self._end(own @ self.weights[0] + x @ self.weights[1])


class GinConv(Layer):
    """Two maps with a relu between of (1 + eps) own row + sum."""

    def __init__(self, weights, eps: int | float = 0, **more):
        super().__init__(weights, own=True, **({"agg": "sum"} | more))
        self.eps = eps

    def apply(self, x, own):
        cols = value_columns(x)
        both = own.join(x.select("vid", "tile", *[F.col(c).alias(f"_{c}") for c in cols]), ["vid", "tile"])
        mixed = both.select("vid", "tile", *[(F.col(c) * (1 + self.eps) + F.col(f"_{c}")).alias(c) for c in cols])
        return finish(linear(finish(linear(mixed, self.weights[0]), "relu", self.shift), self.weights[1]), self.act, self.shift)

    def apply_numpy(self, x, own):
        return self._end(self._end((own * (1 + self.eps) + x) @ self.weights[0], "relu") @ self.weights[1])


class GatConv(Layer):
    """One or more attention heads over linearly mapped rows, side by side; floats."""

    def __init__(self, weights, left: list[list[float]], right: list[list[float]], slope: float = 0.2, **more):
        super().__init__(weights, agg="attention", **more)
        self.left, self.right, self.slope = left, right, slope

    def slot_width(self, d):
        return sum(w.shape[1] + 2 for w in self.weights)


class Propagate(Layer):
    """An aggregate passed on as it is: all steps but the last of a simplified convolution."""

    def __init__(self, agg: str = "mean"):
        super().__init__([], agg=agg, act="identity")

    def apply(self, x, own):
        return x.drop("n_recv")

    def apply_numpy(self, x, own):
        return x


class MessageLayer(Layer):
    """Any aggregator with any update of frames: update(aggregate, own rows) -> (vid, tile, c0..)."""

    def __init__(self, agg: str, update, act: str = "identity", own: bool = False):
        super().__init__([], agg=agg, act=act, own=own)
        self.update = update

    def apply(self, x, own):
        return finish(self.update(x, own), self.act, None)


def sgc(k: int, w: np.ndarray, **more) -> list[Layer]:
    """k mean propagations and one map."""
    return [*(Propagate() for _ in range(k - 1)), GraphConv([w], **({"act": "identity"} | more))]


def relu_log_softmax(y: DataFrame) -> DataFrame:
    """log softmax over the components of one-tile rows."""
    cols = value_columns(y)
    top = F.greatest(*[F.col(c) for c in cols]) if len(cols) > 1 else F.col(cols[0])
    total = F.log(sum((F.exp(F.col(c) - F.col("_m")) for c in cols), F.lit(0.0)))
    return y.withColumn("_m", top).select("vid", "tile", *[(F.col(c) - F.col("_m") - total).alias(c) for c in cols])


def argmax(y: DataFrame, name: str = "label") -> DataFrame:
    """(vid, label): the component with the largest value, the first of several."""
    cols = value_columns(y)
    values = F.array(*[F.col(c) for c in cols])
    return y.select("vid", (F.array_position(values, F.array_max(values)) - 1).cast("int").alias(name))
