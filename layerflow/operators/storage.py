"""Topology and row storage: adjacency lists, id ranges, sorted spills with descriptors, chunks read by merging spills."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layerflow import store
from layerflow.operators.positions import dense_positions, running_sum


def adjacency(edges: DataFrame, vertices: DataFrame, by: str = "src", max_nbrs: int = 1 << 20) -> DataFrame:
    """(vid, segment, off, deg, nbrs): neighbours of each vertex in order, with offsets into all lists end to end.

    A vertex with more than ``max_nbrs`` neighbours has several segments, so no row grows with a hub's degree.
    """
    other = "dst" if by == "src" else "src"
    ranked = edges.select(F.col(by).alias("vid"), F.col(other).alias("n"))
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy("vid").orderBy("n")) - 1
    seg = ranked.withColumn("segment", F.call_function("div", rank.cast("long"), F.lit(max_nbrs)))
    lists = seg.groupBy("vid", "segment").agg(F.sort_array(F.collect_list("n")).alias("nbrs"))
    every = vertices.select("vid").join(lists, "vid", "left").select("vid", F.coalesce("segment", F.lit(0).cast("long")).alias("segment"), F.coalesce("nbrs", F.array().cast("array<bigint>")).alias("nbrs"))
    every = every.withColumn("deg", F.size("nbrs").cast("long"))
    at = offsets(every.select("vid", "segment", "deg"))
    return every.join(at, ["vid", "segment"]).select("vid", "segment", "off", "deg", "nbrs")


def offsets(degrees: DataFrame) -> DataFrame:
    """(vid, segment, off) from (vid, segment, deg), in order of vid and segment."""
    placed = dense_positions(degrees, [F.col("vid"), F.col("segment")], "_pos")
    return running_sum(placed, "_pos", "deg", "_end").select("vid", "segment", (F.col("_end") - F.col("deg")).alias("off"))


def degree_offsets(edges: DataFrame, vertices: DataFrame, by: str = "src") -> DataFrame:
    """(vid, deg, off): the offsets alone, without lists."""
    d = edges.groupBy(F.col(by).alias("vid")).agg(F.count("*").alias("deg"))
    rows = vertices.select("vid").join(d, "vid", "left").select("vid", F.lit(0).cast("long").alias("segment"), F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))
    return rows.join(offsets(rows), ["vid", "segment"]).select("vid", "deg", "off")


def explode_adjacency(lists: DataFrame, by: str = "src") -> DataFrame:
    """Edges of adjacency lists."""
    e = lists.select("vid", F.explode("nbrs").alias("n"))
    return e.select(F.col("vid").alias("src"), F.col("n").alias("dst")) if by == "src" else e.select(F.col("n").alias("src"), F.col("vid").alias("dst"))


def range_of(vid: str, n: int, n_ranges: int):
    """Range of an id: fixed widths, no sampling, so the same in every run."""
    return F.call_function("div", F.col(vid), F.lit(-(-n // n_ranges))).cast("int")


def write_spills(rows: DataFrame, path: str, n: int, n_ranges: int, spill_rows: int, order: str = "vid", in_file: int = 1) -> None:
    """Rows dealt by id range; within a range every ``spill_rows`` in order of arrival are sorted and make a file.

    Arrival is ``order``; a spill holds ids of one range only, so readers skip by range and by descriptor.  With
    ``in_file`` up to so many spills share a file, in pages of a spill's rows with their own bounds: opening files costs
    more than small spills do.
    """
    dealt = rows.withColumn("range_id", range_of("vid", n, n_ranges)).repartitionById(n_ranges, "range_id").sortWithinPartitions("range_id", order)
    spill = F.call_function("div", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)), F.lit(spill_rows))
    writer = dealt.withColumn("spill", spill).sortWithinPartitions("range_id", "spill", "vid").write.option("maxRecordsPerFile", spill_rows * in_file)
    if in_file > 1:
        writer = writer.option("parquet.page.row.count.limit", spill_rows)
    writer.partitionBy("range_id").mode("errorifexists").parquet(path)


def spill_manifest(spark: SparkSession, path: str) -> DataFrame:
    """(range_id, path, min_vid, max_vid, n_rows): one row a spill file, by smallest id."""
    rows = spark.read.parquet(path).select("range_id", "vid", F.input_file_name().alias("path"))
    return rows.groupBy("range_id", "path").agg(F.min("vid").alias("min_vid"), F.max("vid").alias("max_vid"), F.count("*").alias("n_rows")).orderBy("min_vid")


def overlapping_spills(manifest: DataFrame, lo: int, hi: int) -> DataFrame:
    """Spills with ids in [lo, hi)."""
    return manifest.where((F.col("min_vid") < hi) & (F.col("max_vid") >= lo))


def spill_overlap(manifest: DataFrame, chunks: DataFrame, n: int, n_ranges: int) -> DataFrame:
    """(chunk, range_id, min_vid, max_vid) of every chunk (chunk, lo, hi) and overlapping spill.

    A spill is of one range of ids, so chunks meet spills in a join by range.
    """
    by_range = chunks.withColumn("range_id", F.explode(F.sequence(range_of("lo", n, n_ranges), F.call_function("div", F.col("hi") - 1, F.lit(-(-n // n_ranges))).cast("int"))))
    return by_range.join(manifest, "range_id").where((F.col("min_vid") < F.col("hi")) & (F.col("max_vid") >= F.col("lo"))).select("chunk", "range_id", "min_vid", "max_vid")


def read_chunk(spark: SparkSession, path: str, lo: int, hi: int, n: int, n_ranges: int) -> DataFrame:
    """Rows of ids in [lo, hi) from all spills, merged by id.  Ranges prune directories, ids prune row groups."""
    width = -(-n // n_ranges)
    rows = spark.read.parquet(path).where((F.col("range_id") >= lo // width) & (F.col("range_id") <= (hi - 1) // width) & (F.col("vid") >= lo) & (F.col("vid") < hi))
    return rows.drop("range_id", "spill").sortWithinPartitions("vid")


def write_layer(spark: SparkSession, rows: DataFrame, layer: int, n: int, n_ranges: int = 8, spill_rows: int = 1 << 20, in_file: int = 1) -> str:
    path = store.new_path(spark, f"layer-{layer}")
    write_spills(rows, path, n, n_ranges, spill_rows, in_file=in_file)
    return path


def scan_only(spark: SparkSession, path: str) -> None:
    """Reads all rows and does nothing with them: the rate that storage sustains."""
    spark.read.parquet(path).write.format("noop").mode("overwrite").save()


def relayout_rows(rows: DataFrame, positions: DataFrame, path: str, n: int, n_ranges: int, spill_rows: int) -> None:
    """Rows under new ids in the same layout."""
    from layerflow.operators.orders import relabel_rows

    write_spills(relabel_rows(rows, positions), path, n, n_ranges, spill_rows)
