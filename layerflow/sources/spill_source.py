"""A data source for spilled layers, ``layer_spill``: one input partition a range, id filters pushed to the files.

Files are read through the executors' file system in Python, so paths must be visible to them as files; where they are
not, ``read_spills`` falls back to Spark's own Parquet reader with the same pruning.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType


class RangePartition(InputPartition):
    def __init__(self, files: list[str]):
        super().__init__(files)
        self.files = files


class SpillReader(DataSourceReader):
    def __init__(self, path: str, schema: StructType):
        self.path, self.schema = path.removeprefix("file://"), schema
        self.lo, self.hi = None, None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Takes bounds on vid; Spark checks all filters again, so taking them loosely is safe."""
        for f in filters:
            if getattr(f, "attribute", None) == ("vid",):
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    self.lo = f.value if self.lo is None else max(self.lo, f.value)
                if isinstance(f, (LessThan, LessThanOrEqual, EqualTo)):
                    self.hi = f.value if self.hi is None else min(self.hi, f.value)
            yield f

    def partitions(self) -> list[RangePartition]:
        """Files by range, without those whose descriptor (the footer's id bounds) lies outside the filter."""
        import glob
        import os

        import pyarrow.parquet as pq

        out = []
        for folder in sorted(glob.glob(f"{self.path}/range_id=*")):
            files = []
            for f in sorted(glob.glob(f"{folder}/*.parquet")):
                meta = pq.ParquetFile(f).metadata
                at = meta.schema.names.index("vid")
                stats = [meta.row_group(i).column(at).statistics for i in range(meta.num_row_groups)]
                if any(s is None or not s.has_min_max or ((self.hi is None or s.min <= self.hi) and (self.lo is None or s.max >= self.lo)) for s in stats):
                    files.append(f)
            if files:
                out.append(RangePartition(files))
        return out or [RangePartition([])]

    def read(self, partition: RangePartition):
        import os

        import pyarrow.parquet as pq

        for f in partition.files:
            bounds = [("vid", ">=", self.lo)] * (self.lo is not None) + [("vid", "<=", self.hi)] * (self.hi is not None)
            t = pq.ParquetFile(f).read() if not bounds else pq.read_table(f, filters=bounds, partitioning=None)
            number = int(os.path.basename(os.path.dirname(f)).split("=")[1])
            import pyarrow as pa

            t = t.append_column("range_id", pa.array([number] * t.num_rows, pa.int32()))
            yield from t.select([x.name for x in self.schema.fields]).to_batches()


class LayerSpillSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "layer_spill"

    def schema(self) -> StructType:
        raise ValueError("give the schema of the spilled rows")

    def reader(self, schema: StructType) -> SpillReader:
        return SpillReader(self.options["path"], schema)


def read_spills(spark: SparkSession, path: str) -> DataFrame:
    """Rows of a spilled layer through the source where its files are visible, else through Spark's reader."""
    import os

    plain = spark.read.parquet(path)
    if not os.path.isdir(path.removeprefix("file://")):
        return plain
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(LayerSpillSource)
    return spark.read.format("layer_spill").schema(plain.schema).option("path", path).load()
