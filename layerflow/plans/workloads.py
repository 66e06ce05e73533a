"""The experiments, on the given graphs: each returns a small report.  Ratios and counters matter, not seconds."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layerflow import store
from layerflow.catalog import HIDDEN, ORDER, query, run_system, stored_order
from layerflow.functions.columns import value_columns
from layerflow.operators import arrays, errors, orders, progress, sampling, storage, tiers
from layerflow.plans import engine, layerwise
from layerflow.plans.measure import ProcessTrace, measured
from layerflow.sources.graphs import GRAPHS, widen_features

CHUNK = 64


def _report(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


@query("w1_costs")
def engines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three systems, layer by layer: seconds, rows shuffled (those computed, for superbatches) and modelled bytes read.

    All graphs with GraphConv, all models on ``copurchase``; two layers, 128 wide.
    """
    rows = []
    for name, kind in [(g, "graphconv") for g in ("embgraph", "copurchase", "trade")] + [("copurchase", "sage"), ("copurchase", "gin")]:
        g = GRAPHS[name](spark, sf_dir)
        n = g.vertices.count()
        push, pull = engine.modelled_reads(g, stored_order(spark, sf_dir, name, "rcm"), g.d, 4, 4096, 16, max(1, n // 16 // 5))
        for system, modelled in (("push", push), ("pull", pull)):
            report = run_system(spark, sf_dir, name, kind, system)[1]
            rows += [(name, kind, system, i + 1, s, m, modelled if i == 0 else None, report.status) for i, (s, m) in enumerate(zip(report.seconds, report.messages))]
        began = time.time()
        reports = run_system(spark, sf_dir, name, kind, "superbatch")[1]
        # its graphs and features: misses are rows read, edges are written and read again
        read = sum(16 * r.edges + r.misses * g.d * 4 for r in reports)
        rows.append((name, kind, "superbatch", 0, time.time() - began, sum(r.rows for r in reports), read, "done"))
    return _report(spark, rows, "graph string, model string, system string, layer int, seconds double, rows long, modelled_bytes long, status string")


@query("w1_widths")
def widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Push against pull, one layer, taking turns: what is shuffled and how long it takes as rows get wider."""
    rows = []
    for name in ("copurchase", "trade"):
        base = GRAPHS[name](spark, sf_dir)
        for d in (64, 256, 1024):
            g = replace(base, features=store.written(widen_features(base.features, d), "wide"), d=d)
            layer = layerwise.Propagate("sum")
            for again in range(2):
                for system in ("push", "pull") if again == 0 else ("pull", "push"):
                    c = measured(spark, lambda g=g, system=system, layer=layer: layerwise.run_layer(g, g.features, layer, system))
                    rows.append((name, d, system, again, c.seconds, c.shuffle_bytes, c.task_seconds))
            store.discard(g.features)
    return _report(spark, rows, "graph string, width int, system string, turn int, seconds double, shuffle_bytes long, task_seconds double")


@query("w2_accuracy")
def accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Floats against the in-memory reference of equal weights; GIN's sums grow large, so its error is only relative."""
    g = GRAPHS["embgraph"](spark, sf_dir)
    g = replace(g, features=g.features.select("vid", "tile", *[(F.col(c) / 65536.0).alias(c) for c in value_columns(g.features)]))
    rows = []
    for kind in ("graphconv", "sage", "gin"):
        m = layerwise.model(kind, g.d, hidden=HIDDEN, weights="glorot", shift=None)
        ref = layerwise.reference_numpy(g, m, exact=False)
        for system in ("push", "pull"):
            out, _ = engine.run_engine(g, m, exact=False) if system == "push" else layerwise.infer_layerwise(g, m, "pull", exact=False, materialize=True)
            out = store.written(out, "out")
            names = value_columns(out)
            known = store.written(spark.createDataFrame([(int(v), *map(float, x)) for v, x in ref.items()], "vid long, " + ", ".join(f"{c} double" for c in names)), "reference")
            rows.append((kind, system, errors.mean_max_abs_error(out, known).first().error, errors.mean_avg_rel_error(out, known, 1e-3).first().error))
    return _report(spark, rows, "model string, system string, max_abs double, avg_rel double")


@query("w3_resources")
def resource_traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages of GraphConv runs: seconds, and the JVM's CPU and memory; the rate at which the engine's first layer reads
    against that of a scan that does nothing else."""
    rows = []
    jvm = spark.sparkContext._jvm.java.lang.ProcessHandle.current().pid()
    for name in ("trade", "copurchase"):
        g = GRAPHS[name](spark, sf_dir)
        pos = stored_order(spark, sf_dir, name, "yield")
        with ProcessTrace(jvm, 0.25) as trace:
            _, report = engine.run_engine(g, layerwise.model("graphconv", g.d, hidden=HIDDEN), pos)
        rows += [(name, x["layer"], x["stage"], x["seconds"], None) for x in report.stages]
        rows += [(name, 0, "CPU percent", None, trace.cpu_percent()), (name, 0, "peak bytes", None, float(trace.peak_bytes()))]
        path = storage.write_layer(spark, g.features, 0, g.vertices.count())
        began = time.time()
        storage.scan_only(spark, path)
        scan = time.time() - began
        size = store.size(spark, path)
        active = next(x["seconds"] for x in report.stages if x["layer"] == 1)
        rows += [(name, 1, "read rate while combining", active, size / active), (name, 1, "read rate of a bare scan", scan, size / scan), (name, 1, "share of the scan's rate", None, scan / active)]
        store.delete(spark, path)
    return _report(spark, rows, "graph string, layer int, measure string, seconds double, value double")


def _trace(g, order: str, rows: int = CHUNK) -> tuple[DataFrame, DataFrame, int]:
    g = g.with_edges(store.written(g.edges, "edges"))
    pos = store.written(ORDER[order](g).select("vid", "pos"), "pos")
    trace = store.written(progress.message_trace(g.edges, pos, rows), "trace")
    store.discard(g.edges)
    return pos, trace, progress.trace_peak(trace)


_COUNTS = "evictions long, reloads long, reload_share double, most_parked long"


def _counts(trace: DataFrame, slots: int, policy: str = "fewest", state_bytes: int = 1) -> tuple:
    return _counted(tiers.replay_tiers(trace, max(1, slots), policy, state_bytes=state_bytes))


def _counted(replay: tiers.Replay) -> tuple:
    s = replay.summary().first()
    return s.evictions, s.reloads, float(s.reload_share), s.most_parked


@query("w4_orders")
def vertex_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders at 71 and 83 % of the yield order's peak, on three graphs."""
    rows = []
    for name in ("trade", "copurchase", "embgraph"):
        g = GRAPHS[name](spark, sf_dir)
        peak = _trace(g, "yield")[2]
        for order in ("original", "random", "degree_in", "yield"):
            pos, trace, own = _trace(g, order)
            span = progress.span_summary(g.edges, pos).first()
            for percent in (71, 83):
                began = time.time()
                counts = _counts(trace, peak * percent // 100)
                rows.append((name, order, percent, span.total / max(1, span.n), own, *counts, time.time() - began))
    return _report(spark, rows, f"graph string, order string, percent int, mean_span double, peak long, {_COUNTS}, seconds double")


@query("w5_policies")
def eviction_policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six policies at four budgets, under the yield order."""
    rows = []
    for name in ("trade", "copurchase"):
        _, trace, peak = _trace(GRAPHS[name](spark, sf_dir), "yield")
        rows += [(name, p, k, *_counts(trace, peak * k // 100, p)) for p in ("fewest", "lru", "random", "fifo", "most", "farthest") for k in ((30, 50, 71, 83) if name == "trade" else (50, 71))]
    return _report(spark, rows, f"graph string, policy string, percent int, {_COUNTS}")


@query("w6_slots")
def slot_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight budgets from 43 to 143 % of the peak: evictions vanish at 100 %."""
    rows = []
    for name in ("trade", "copurchase"):
        _, trace, peak = _trace(GRAPHS[name](spark, sf_dir), "yield")
        rows += [(name, k, *_counts(trace, -(-peak * k // 100))) for k in (43, 57, 71, 86, 100, 114, 129, 143)]
    return _report(spark, rows, f"graph string, percent int, {_COUNTS}")


@query("w8_reorder_cost")
def reorder_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds for scores, relabelled edges and features in the new layout."""
    g = GRAPHS["trade"](spark, sf_dir)
    n, began = g.vertices.count(), time.time()
    pos = store.written(orders.order_yield(g.edges, g.vertices), "pos")
    scored = time.time()
    store.written(orders.relabel_edges(g.edges, pos), "edges")
    moved = time.time()
    storage.relayout_rows(g.features, pos, store.new_path(spark, "relayout"), n, 8, 1 << 20)
    return _report(spark, [("order", scored - began), ("edges", moved - scored), ("features", time.time() - moved)], "step string, seconds double")


@query("w9_width")
def hidden_width(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two layers, d to 128 to classes: seconds and shuffled rows of both; and the bytes of the first layer mapped after
    and before aggregation."""
    base = GRAPHS["copurchase"](spark, sf_dir)
    pos = stored_order(spark, sf_dir, "copurchase", "yield")
    rows = []
    for d in (32, 64, 256, 1024):
        wide = replace(base, features=widen_features(base.features, d), d=d)
        _, report = engine.run_engine(wide, layerwise.model("graphconv", d, hidden=HIDDEN), pos)
        rows += [(d, f"layer {i + 1}", s, m * -(-w // 64) * min(w, 64) * 8) for i, (s, m, w) in enumerate(zip(report.seconds, report.messages, (d, HIDDEN)))]
        layer = layerwise.GraphConv([layerwise.make_weights(0, d, 16)], agg="sum", act="identity")
        for side in ("after", "before"):
            c = measured(spark, lambda w=wide, layer=layer, side=side, d=d: layerwise.run_layer(w, w.features, layer, side=side, width=d))
            rows.append((d, f"mapped {side}", c.seconds, c.shuffle_bytes))
    return _report(spark, rows, "width int, part string, seconds double, shuffle_bytes long")


@query("w10_sage_slots")
def sage_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One budget, slots of width d and 2d."""
    g = GRAPHS["trade"](spark, sf_dir)
    lists = arrays.both_lists(g.ends)
    packed = tiers.packed_runs(None, orders.order_yield(None, g.vertices, lists=lists).select("vid", "pos"), CHUNK, lists=lists)
    store.discard(lists.rows)
    budget = tiers.packed_peak(packed) * g.d * 4

    rows = []
    for kind, width in (("graphconv", g.d), ("sage", 2 * g.d)):  # in turn: together, two stores could meet in one executor
        slots = progress.slots_for(budget, width, 4)
        rows.append((kind, width, slots, *_counted(tiers.replay_packed(packed, max(1, slots), state_bytes=4 * width))))
    return _report(spark, rows, f"model string, width int, slots long, {_COUNTS}")


@query("w11_losses")
def losses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What sampling and partition-local edges change, by seed and number of parts."""
    rows = []
    for graph in ("embgraph", "knn"):
        g = GRAPHS[graph](spark, sf_dir)
        g = g.with_edges(store.written(g.edges, "edges"))
        m, n = layerwise.model("graphconv", g.d), g.vertices.count()
        full = store.written(layerwise.infer_layerwise(g, m)[0], "full")
        cases = [(f"sampled, seed {s}", sampling.sample_neighbors(g.edges, 3, s)) for s in (0, 1, 2)] + [(f"{k} parts", sampling.partition_local(g.edges, n, k)) for k in (2, 4, 8)]
        for name, edges in cases:
            out = store.written(layerwise.infer_layerwise(g.with_edges(edges), m)[0], "part")
            a = errors.label_agreement(layerwise_argmax(full), layerwise_argmax(out)).first()
            rows.append((graph, name, float(errors.mean_max_abs_error(out, full).first().error), a.same, a.total))
            store.discard(out)
    return _report(spark, rows, "graph string, case string, max_abs double, same long, total long")


def layerwise_argmax(x: DataFrame) -> DataFrame:
    from layerflow.operators.layers import argmax

    return argmax(x)


@query("w14_page_cache")
def page_cache(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks that pulling misses with caches from 5 to 110 % of all blocks, against each block once."""
    rows = []
    for name in ("embgraph", "trade"):
        g = GRAPHS[name](spark, sf_dir)
        trace = store.written(tiers.page_trace(g.edges, 64, 16), "pages")
        total = -(-g.vertices.count() // 16)
        for percent in (5, 25, 50, 75, 100, 110):
            r = tiers.cache_replay(trace, max(1, -(-total * percent // 100)), "lru").agg(F.sum("hits").alias("h"), F.sum("misses").alias("m")).first()
            rows.append((name, percent, r.h or 0, r.m or 0, total))
    return _report(spark, rows, "graph string, percent int, hits long, misses long, blocks long")
