"""Queries against their SQL in DuckDB on the smallest tables."""

import duckdb
import pytest

from layerflow import catalog
from layerflow.sources.tables import NAMES

ORACLES = catalog.oracles()
#: One or two of each family; the driver compares all.
CHOSEN = [k for k in ORACLES if k.startswith(("graph_", "op_", "order_", "csr", "push_mean", "pull_mean", "layer_gin", "range_", "spill_", "read_chunk", "layer_spill"))]
CHOSEN += ["infer2_graphconv_trade", "infer2_sage_embgraph", "pull2_gin_copurchase", "w1_embgraph_sage_push", "w1_copurchase_graphconv_pull", "engine_order_random", "engine_chunks", "agg_symmetric", "agg_mean_in_message", "message_layer", "recommend_slots", "khop_subgraph", "active_series_yield", "completion_curve_yield", "span_percentiles_yield", "message_trace", "khop_frontier", "push_bounded_sum", "wide_layer_256", "neighbor_cache", "sampled_layer"]


def plain(v):
    return int(v) if isinstance(v, bool) else round(v, 9) if isinstance(v, float) else v


@pytest.mark.parametrize("name", sorted(set(CHOSEN)))
def test_query(spark, sf_dir, name):
    con = duckdb.connect()
    for t in NAMES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    df = catalog.queries()[name](spark, sf_dir)
    want = con.sql(ORACLES[name])
    assert sorted(df.columns) == sorted(want.columns)
    columns = sorted(df.columns)
    got = sorted((tuple(map(plain, r)) for r in df.select(columns).collect()), key=repr)
    assert got == sorted((tuple(map(plain, r)) for r in want.select(", ".join(f'"{c}"' for c in columns)).fetchall()), key=repr)


def test_catalog():
    assert set(ORACLES) <= set(catalog.queries())


def test_ranges_meet_every_event(spark, tmp_path):
    """More events than 20 ranges reach."""
    spark.range(30_000).selectExpr("id AS event_id").write.parquet(f"{tmp_path}/events.parquet")
    got = sorted(tuple(r) for r in catalog.queries()["op_join_range_all"](spark, str(tmp_path)).select("event_id", "lo").collect())
    assert got == [(i, lo) for i in range(30_000) for lo in range(0, 30_000, 700) if lo <= i < lo + 1000]


def test_vertexwise_covers_trade(spark, sf_dir):
    test_query(spark, sf_dir, "vertexwise_trade_all")


def test_arithmetic(spark, sf_dir):
    """The published figures, and the query reads the orders."""
    from layerflow.operators import errors, progress

    assert [progress.chunk_rows(8 << 20, d, b) for d, b in ((128, 4), (768, 2), (1024, 2))] == [16384, 5461, 4096]
    assert [progress.slots_for(g << 30, d, b) for g, d, b in ((50, 128, 4), (70, 768, 2), (80, 1024, 2))] == [104857600, 48933546, 41943040]
    assert errors.extrapolate(21600.0, 0.25, 1.0) == 86400
    test_query(spark, sf_dir, "arithmetic")
    assert catalog.queries()["arithmetic"](spark, sf_dir).inputFiles() == spark.read.parquet(f"{sf_dir}/orders.parquet").inputFiles()
