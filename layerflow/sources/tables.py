"""The given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def row_count(spark: SparkSession, sf_dir: str, name: str) -> int:
    """Rows of a table, from the Parquet footers."""
    return table(spark, sf_dir, name).count()


def register(spark: SparkSession, sf_dir: str) -> None:
    """Views of all tables for SQL."""
    for name in NAMES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)
