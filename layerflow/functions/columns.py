"""Small column expressions that both engines compute alike."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def floor_div(a: Column, b: Column) -> Column:
    """Integer division rounded down, for integers and positive divisors."""
    return F.call_function("div", a - F.pmod(a, b), b)


def value_columns(df: DataFrame, prefix: str = "c") -> list[str]:
    """Names prefix0, prefix1, ... in order."""
    found = [c for c in df.columns if c.startswith(prefix) and c[len(prefix) :].isdigit()]
    return sorted(found, key=lambda c: int(c[len(prefix) :]))


def to_long_rows(df: DataFrame, prefix: str = "c", index: str = "i", value: str = "q") -> DataFrame:
    """(vid, i, q) rows of a tiled frame; column k of tile t is component 64 t + k."""
    cols = value_columns(df, prefix)
    tile = F.col("tile") * 64 if "tile" in df.columns else F.lit(0)
    parts = F.array(*[F.col(c) for c in cols])
    return df.select("vid", tile.alias("_b"), F.posexplode(parts).alias("_k", value)).select("vid", (F.col("_b") + F.col("_k")).cast("int").alias(index), value)
