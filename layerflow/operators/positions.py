"""Dense positions of sorted rows without a window over one partition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from layerflow import store


def dense_positions(df: DataFrame, order: list[Column], name: str = "pos") -> DataFrame:
    """Adds each row's rank (0, 1, ...) in a total order.

    Rows are dealt by range and sorted within partitions; only the partitions' row counts, as many numbers as there are
    partitions, come together before they are added to the row numbers within partitions.
    """
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order)
    ranged = store.written(ranged.withColumn("_at", F.monotonically_increasing_id()), "ranged")
    part = F.shiftright("_at", 33)
    sizes = {r["p"]: r["n"] for r in ranged.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()}
    starts, total = {}, 0
    for p in sorted(sizes):
        starts[p] = total
        total += sizes[p]
    spark = df.sparkSession
    offsets = spark.createDataFrame([(p, s) for p, s in starts.items()], "_p long, _s long") if starts else spark.createDataFrame([], "_p long, _s long")
    joined = ranged.withColumn("_p", part).join(F.broadcast(offsets), "_p")
    return joined.withColumn(name, F.col("_s") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).drop("_p", "_s", "_at")


def running_sum(df: DataFrame, order: str, value: str, name: str, width: int = 4096, levels: int = 3) -> DataFrame:
    """Adds the running sum of an integer column over a dense integer position; of decimals, as decimals.

    Blocks of ``width`` positions are summed apart, blocks' sums in the same way a level up; only one number a block of
    the last level, one for width to the power of ``levels`` - 1 positions, meets in one window.
    """
    from pyspark.sql import Window
    from pyspark.sql.types import DecimalType

    held = df.schema[value].dataType
    kind = held if isinstance(held, DecimalType) else "long"
    block = F.call_function("div", F.col(order), F.lit(width))
    rows = df.withColumn("_b", block)
    sums = rows.groupBy("_b").agg(F.sum(value).alias("_t"))
    if levels > 2:
        up = running_sum(sums.select(F.col("_b").alias("_up"), "_t"), "_up", "_t", "_sum", width, levels - 1)
        before = up.select(F.col("_up").alias("_b"), (F.col("_sum") - F.col("_t")).alias("_before"))
    else:
        before = sums.select("_b", (F.sum("_t").over(Window.orderBy("_b")) - F.col("_t")).alias("_before"))
    inner = F.sum(value).over(Window.partitionBy("_b").orderBy(order).rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("_in", inner).join(before, "_b").withColumn(name, (F.col("_in") + F.col("_before")).cast(kind)).drop("_b", "_in", "_before")
