"""Tables written between the steps of an operator, in the folder that all executors share."""

from __future__ import annotations

import atexit
import contextlib
import gc
import itertools
import shutil
import tempfile
import time
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

_count = itertools.count()
_own: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where it is unset (tests on one machine), a folder of this process."""
    set_by_cluster = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if set_by_cluster:
        return set_by_cluster.rstrip("/")
    if not _own:
        folder = tempfile.mkdtemp(prefix="layerflow-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        _own.append("file://" + folder)
    return _own[0]


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex[:12]}-{next(_count)}"


def until_exit(spark: SparkSession, path: str) -> None:
    """Has a folder deleted when the application ends, if it still is there then."""
    where, files = _files(spark, path)
    files.deleteOnExit(where)


def read_text(spark: SparkSession, path: str) -> str:
    where, files = _files(spark, path)
    stream = files.open(where)
    try:
        return spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
    finally:
        stream.close()


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """Writes a small file at once: under another name first, then renamed."""
    where, files = _files(spark, path)
    aside = where.suffix(".new")
    stream = files.create(aside, True)
    stream.write(bytearray(text.encode()))
    stream.close()
    files.rename(aside, where)


def size(spark: SparkSession, path: str) -> int:
    """Bytes in a folder."""
    where, files = _files(spark, path)
    return files.getContentSummary(where).getLength()


def names(spark: SparkSession, path: str) -> list[str]:
    """Names in a folder; none if there is no such folder."""
    where, files = _files(spark, path)
    return sorted(x.getPath().getName() for x in files.listStatus(where)) if files.exists(where) else []


def _files(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where, where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def written(df: DataFrame, label: str) -> DataFrame:
    """``df`` written once and read back: later steps depend on files, not on lineage."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    until_exit(spark, path)
    release(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out._layerflow_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes the files of tables from ``written`` that nothing reads any more."""
    for df in tables:
        delete(df.sparkSession, df._layerflow_path)


#: Seconds between two collections at least.
PAUSE = 1.0
_released = 0.0


def release(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of finished steps, which it does when their plans are collected as garbage."""
    global _released
    if time.monotonic() - _released < PAUSE:
        return
    _released = time.monotonic()
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def delete(spark: SparkSession, path: str) -> None:
    where, files = _files(spark, path)
    files.delete(where, True)


#: Rows in an Arrow batch of whole texts: Spark's default of 10,000 is meant for rows of a few numbers.
TEXT_ROWS = 1000


def text_batches(spark: SparkSession) -> None:
    """Keeps what JVM and Python hold of a batch of texts small; leaves a smaller setting alone."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= TEXT_ROWS:
        spark.conf.set(name, str(TEXT_ROWS))


@contextlib.contextmanager
def batch_rows(spark: SparkSession, rows: int) -> Iterator[None]:
    """Rows in an Arrow batch of what is written within."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)
