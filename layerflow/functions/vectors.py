"""Vector functions over Arrow batches and table functions, and their registration for SQL."""

from __future__ import annotations

from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def _dot(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.dot(np.asarray(x, np.float64), np.asarray(y, np.float64))) if x is not None and y is not None else None for x, y in zip(a, b)])


def _add(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([np.asarray(x, np.float64) + np.asarray(y, np.float64) for x, y in zip(a, b)])


def _scale(a: pd.Series, s: pd.Series) -> pd.Series:
    return pd.Series([np.asarray(x, np.float64) * y for x, y in zip(a, s)])


def _normalise(a: pd.Series) -> pd.Series:
    return pd.Series([np.asarray(x, np.float64) / (np.linalg.norm(np.asarray(x, np.float64)) or 1.0) for x in a])


def _pack_half(a: pd.Series) -> pd.Series:
    return pd.Series([None if x is None else np.asarray(x, np.float16).tobytes() for x in a])


def _unpack_half(a: pd.Series) -> pd.Series:
    return pd.Series([None if x is None else np.frombuffer(x, np.float16).astype(np.float32) for x in a])


@cache
def _functions() -> dict:
    """The functions by name, made when a session is there to read their types."""
    return {
        "vec_dot": pandas_udf(_dot, "double", functionType=200),
        "vec_add": pandas_udf(_add, "array<double>", functionType=200),
        "vec_scale": pandas_udf(_scale, "array<double>", functionType=200),
        "vec_normalise": pandas_udf(_normalise, "array<double>", functionType=200),
        "pack_half": pandas_udf(_pack_half, "binary", functionType=200),
        "unpack_half": pandas_udf(_unpack_half, "array<float>", functionType=200),
    }


def vec_dot(a, b):
    return _functions()["vec_dot"](a, b)


def vec_add(a, b):
    return _functions()["vec_add"](a, b)


def vec_scale(a, s):
    return _functions()["vec_scale"](a, s)


def vec_normalise(a):
    return _functions()["vec_normalise"](a)


def pack_half(a):
    """Vectors as two bytes a component, for storage only: Spark has no type for them."""
    return _functions()["pack_half"](a)


def unpack_half(a):
    return _functions()["unpack_half"](a)


def vec_matmul(weights: np.ndarray):
    """A column function that multiplies vectors by a matrix."""

    def f(a: pd.Series) -> pd.Series:
        return pd.Series(list(np.stack([np.asarray(x, np.float64) for x in a]) @ weights)) if len(a) else pd.Series([], dtype=object)

    return pandas_udf(f, "array<double>", functionType=200)


def vec_sum(rows: DataFrame, by: str, vector: str, d: int) -> DataFrame:
    """Element-wise sums by key from built-in sums of the components, so that they combine before the shuffle."""
    sums = rows.groupBy(by).agg(*[F.sum(F.element_at(vector, i + 1)).alias(f"_{i}") for i in range(d)])
    return sums.select(by, F.array(*[F.col(f"_{i}") for i in range(d)]).alias(vector))


class _CountUp:
    def eval(self, n: int):
        for k in range(n + 1):
            yield (k,)


class _ExplodeAdjacency:
    def eval(self, vid: int, nbrs: list):
        for n in nbrs or []:
            yield vid, n


def register(spark: SparkSession) -> None:
    """Makes the functions known to SQL."""
    for name, f in _functions().items():
        spark.udf.register(name, f)
    spark.udtf.register("count_up", udtf(_CountUp, returnType="k: int"))
    spark.udtf.register("explode_adjacency", udtf(_ExplodeAdjacency, returnType="src: long, dst: long"))


def register_graph(spark: SparkSession, graph, layers: dict[int, DataFrame] | None = None) -> None:
    """Views v_edges, v_vertices, v_features and v_layer<n>."""
    graph.edges.createOrReplaceTempView("v_edges")
    graph.vertices.createOrReplaceTempView("v_vertices")
    if graph.features is not None:
        graph.features.createOrReplaceTempView("v_features")
    for n, df in (layers or {}).items():
        df.createOrReplaceTempView(f"v_layer{n}")
