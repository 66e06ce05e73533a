"""Sends this package to Python workers that can't import it."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

_sent: set[str] = set()


def _workers_import(spark: SparkSession) -> bool:
    def look(_):
        try:
            import layerflow  # noqa: F401

            yield True
        except ImportError:
            yield False

    return all(spark.sparkContext.parallelize([0], 1).mapPartitions(look).collect())


def ship(spark: SparkSession) -> None:
    """Once a session: if a worker can't import the package, adds it as a zip that Spark distributes."""
    app = spark.sparkContext.applicationId
    if app in _sent:
        return
    _sent.add(app)
    if _workers_import(spark):
        return
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    path = os.path.join(tempfile.mkdtemp(prefix="layerflow-"), "layerflow.zip")
    with zipfile.ZipFile(path, "w") as z:
        for folder, _, names in os.walk(os.path.join(root, "layerflow")):
            for n in names:
                if n.endswith(".py"):
                    z.write(os.path.join(folder, n), os.path.relpath(os.path.join(folder, n), root))
    spark.sparkContext.addPyFile(path)
