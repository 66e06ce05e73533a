"""Accuracy measures between two sets of rows (vid, c0..)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layerflow.functions.columns import value_columns


def _paired(a: DataFrame, b: DataFrame) -> tuple[DataFrame, list[str]]:
    cols = value_columns(a)
    if cols != value_columns(b):
        raise ValueError("rows of different widths")
    both = a.select("vid", *cols).join(b.select("vid", *[F.col(c).alias(f"_{c}") for c in cols], F.lit(True).alias("_there")), "vid", "full")
    bad = both.where(F.col("_there").isNull() | F.col(cols[0]).isNull()).limit(1).count()
    if bad:
        raise ValueError("different vertices")
    return both, cols


def mean_max_abs_error(a: DataFrame, b: DataFrame) -> DataFrame:
    """Mean over vertices of the largest absolute difference of a component."""
    both, cols = _paired(a, b)
    diffs = [F.abs(F.col(c) - F.col(f"_{c}")) for c in cols]
    return both.agg(F.avg(F.greatest(*diffs) if len(cols) > 1 else diffs[0]).alias("error"))


def mean_avg_rel_error(a: DataFrame, b: DataFrame, eps: float = 1e-12) -> DataFrame:
    """Mean over vertices of the mean relative difference of components; b is the reference."""
    both, cols = _paired(a, b)
    rel = [F.abs(F.col(c) - F.col(f"_{c}")) / F.greatest(F.abs(F.col(f"_{c}")), F.lit(eps)) for c in cols]
    return both.agg(F.avg(sum(rel, F.lit(0.0)) / len(cols)).alias("error"))


def confusion(predicted: DataFrame, actual: DataFrame) -> DataFrame:
    """(label, predicted, n) of vertices with a label."""
    return actual.where("label is not null").join(predicted.select("vid", F.col("label").alias("predicted")), "vid").groupBy("label", "predicted").agg(F.count("*").alias("n"))


def class_accuracy(predicted: DataFrame, actual: DataFrame) -> DataFrame:
    return confusion(predicted, actual).agg(F.sum(F.when(F.col("label") == F.col("predicted"), F.col("n")).otherwise(0)).alias("right"), F.sum("n").alias("total"))


def label_agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """(same, total) of two labellings."""
    return a.join(b.select("vid", F.col("label").alias("_l")), "vid").agg(F.count_if(F.col("label") == F.col("_l")).alias("same"), F.count("*").alias("total"))


def differing_rows(a: DataFrame, b: DataFrame) -> int:
    """Rows that only one of two runs has: 0 for a deterministic engine."""
    return a.exceptAll(b.select(a.columns)).count() + b.select(a.columns).exceptAll(a).count()


def extrapolate(elapsed: float, done: float, total: float, cap: float = 6 * 3600.0) -> float:
    """Time of a run stopped at the cap, linear in the share of the layer it did."""
    return elapsed if done >= total or elapsed < cap else elapsed * total / done


def speedup_table(reports: DataFrame, base: str) -> DataFrame:
    """Seconds by (graph, model), one column an engine, and each engine's over the base's."""
    t = reports.groupBy("graph", "model").pivot("engine").agg(F.sum("seconds"))
    others = [c for c in t.columns if c not in ("graph", "model", base)]
    return t.select("*", *[(F.col(c) / F.col(base)).alias(f"{c}_over_{base}") for c in others])


def memory_plan(slots: int, width: int, itemsize: int, buffer_bytes: int, buffers: int, overhead: int, v: int) -> dict[str, int]:
    """What a run's memory is made of."""
    parts = {"slots": slots * width * itemsize, "buffers": buffer_bytes * buffers, "overhead": overhead, "vertex_state": v * 13}
    return parts | {"total": sum(parts.values())}
