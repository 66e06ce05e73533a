import pandas as pd
import pytest
from pyspark.sql import functions as F

from layerflow.sources.graphs import GRAPHS
from layerflow.sources.tables import table
from layerflow.streaming import edges as st


@pytest.fixture(scope="module")
def parts(spark, sf_dir, tmp_path_factory):
    """Events in three files in order of time."""
    root = tmp_path_factory.mktemp("events")
    rows = table(spark, sf_dir, "events").orderBy("ts", "event_id").toPandas()
    step = len(rows) // 3 + 1
    for i in range(3):
        spark.createDataFrame(rows[i * step : (i + 1) * step], st.EVENTS).coalesce(1).write.mode("append").parquet(f"{root}/e")
    return f"{root}/e"


def test_session_edges_equal_batch(spark, sf_dir, parts):
    got = st.drain(st.session_edges(st.read_events(spark, parts, 99)), "edges_out")
    want = GRAPHS["session"](spark, sf_dir).edges
    assert got.select("src", "dst").exceptAll(want).count() == 0 and want.exceptAll(got.select("src", "dst")).count() == 0


def test_completed_sums(spark, tmp_path):
    m = spark.createDataFrame([(1, 2, 5), (1, 2, 7), (2, 2, 1)], "dst long, d_in int, value long")
    m.write.parquet(f"{tmp_path}/m")
    out = st.drain(st.completed_sums(spark.readStream.schema(m.schema).parquet(f"{tmp_path}/m")), "sums_out")
    assert [(r.dst, r.total, r.missing) for r in out.collect()] == [(1, 12, 0)]


def test_windows_and_duplicates(spark, sf_dir, parts):
    events = table(spark, sf_dir, "events")
    got = st.drain(st.windowed_counts(st.read_events(spark, parts, 99)), "windows_out", "complete")
    assert got.agg(F.sum("n")).first()[0] == events.count()
    assert st.drain(st.first_arrivals(st.read_events(spark, parts, 99)), "dedup_out").count() == events.select("event_id").distinct().count()


def test_stream_join(spark, parts):
    clicks, buys = (st.read_events(spark, parts, 99).where(F.col("event_type") == k) for k in ("click", "purchase"))
    batch = spark.read.schema(st.EVENTS).parquet(parts)
    a, b = batch.where("event_type = 'click'"), batch.where("event_type = 'purchase'")
    want = a.alias("l").join(b.alias("r"), F.expr("l.user_id = r.user_id AND r.ts >= l.ts AND r.ts <= l.ts + INTERVAL 1 hour")).count()
    assert st.drain(st.joined_pairs(clicks, buys, "1 hour"), "join_out").count() == want
