"""All queries of the engine by name, with the SQL that checks them where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layerflow import oracle_sql as sql
from layerflow.functions.columns import to_long_rows
from layerflow.operators import aggregate, arrays, errors, layers, orders, progress, sampling, storage, tiers
from layerflow.operators.positions import dense_positions
from layerflow.plans import layerwise, vertexwise
from layerflow.sources.graphs import GRAPHS, Graph, widen_features
from layerflow.sources.tables import row_count, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
ROWS = 256  # of a chunk in these queries


def query(name: str, oracle: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return keep


def on(graph: str, f: Callable[[Graph], DataFrame]) -> Query:
    return lambda spark, sf_dir: f(GRAPHS[graph](spark, sf_dir))


# -- graphs -----------------------------------------------------------------------------------

for _g in GRAPHS:
    query(f"graph_{_g}_edges", sql.select(sql.graph(_g), "SELECT src, dst FROM edges"))(on(_g, lambda g: g.edges))
for _g in ("trade", "copurchase", "session", "geo", "isolated"):
    query(f"graph_{_g}_features", sql.select(sql.graph(_g, True), "SELECT vid, CAST(i AS INTEGER) AS i, q FROM h"))(on(_g, lambda g: to_long_rows(g.features)))
    query(f"graph_{_g}_vertices", sql.select(sql.graph(_g), "SELECT vid, kind FROM vertices"))(on(_g, lambda g: g.vertices))
query("graph_embgraph_features", sql.select(sql.graph("embgraph", True), "SELECT vid, i, q FROM h"))(on("embgraph", lambda g: to_long_rows(g.features)))
query("self_loops", sql.select(sql.graph("embgraph"), "SELECT src FROM edges WHERE src = dst"))(on("embgraph", lambda g: g.edges.where("src = dst").select("src")))
query("add_self_loops", sql.select(sql.graph("geo"), "SELECT src, dst FROM edges UNION SELECT vid, vid FROM vertices"))(on("geo", lambda g: aggregate.add_self_loops(g.edges, g.vertices)))
query(
    "widen_features",
    sql.select(sql.graph("geo", True), "SELECT h.vid, CAST(r.i AS INTEGER) AS i, CASE WHEN r.i < 8 THEN q ELSE (q * (1 + r.i // 8) + h.vid * 31 + r.i * 17) % 127 END AS q FROM h JOIN (SELECT unnest(range(0, 128)) AS i) r ON r.i % 8 = h.i"),
)(on("geo", lambda g: to_long_rows(widen_features(g.features, 128))))
query("degrees", sql.select(f"{sql.graph('trade')}, {sql.DEGREES}", "SELECT vid, d_in, d_out FROM degrees"))(on("trade", lambda g: aggregate.degrees(g.edges, g.vertices).select("vid", F.col("d_in").cast("long").alias("d_in"), F.col("d_out").cast("long").alias("d_out"))))

# -- storage ----------------------------------------------------------------------------------


def _offsets_sql(d: str) -> str:
    return sql.select(f"{sql.graph('trade')}, {sql.DEGREES}", f"SELECT vid, {d} AS deg, CAST(sum({d}) OVER (ORDER BY vid) - {d} AS BIGINT) AS off FROM degrees")


query("csr_offsets", _offsets_sql("d_out"))(on("trade", lambda g: storage.degree_offsets(g.edges, g.vertices, "src")))
query("csc_offsets", _offsets_sql("d_in"))(on("trade", lambda g: storage.degree_offsets(g.edges, g.vertices, "dst")))
query("csr_lists", sql.select(sql.graph("geo"), "SELECT src, dst FROM edges"))(on("geo", lambda g: storage.explode_adjacency(storage.adjacency(g.edges, g.vertices, "src", 16))))
query(
    "csr_segments",
    sql.select(sql.graph("geo"), "SELECT v.vid, coalesce(s.segment, 0) AS segment, coalesce(s.deg, 0) AS deg FROM vertices v LEFT JOIN (SELECT dst, r // 16 AS segment, count(*) AS deg FROM (SELECT dst, row_number() OVER (PARTITION BY dst ORDER BY src) - 1 AS r FROM edges) GROUP BY 1, 2) s ON s.dst = v.vid"),
)(on("geo", lambda g: storage.adjacency(g.edges, g.vertices, "dst", 16).select("vid", "segment", "deg")))
query("chunk_assign", sql.select(f"{sql.graph('trade')}, {sql.ORDERS['original']}", f"SELECT vid, pos, pos // {ROWS} AS chunk FROM pos"))(on("trade", lambda g: progress.assign_chunks(orders.order_original(g.vertices), ROWS)))


def _spilled(g: Graph, spark: SparkSession, sf_dir: str) -> tuple[str, int]:
    n = g.vertices.count()
    return storage.write_layer(spark, g.features, 1, n, 4, 1000), n


@query("range_manifest", sql.select(sql.graph("copurchase"), "SELECT CAST(vid // w AS INTEGER) AS range_id, min(vid) AS min_vid, max(vid) AS max_vid, count(*) AS n_rows FROM vertices, (SELECT -((-count(*)) // 4) AS w0, (count(*) + 3) // 4 AS w FROM vertices) GROUP BY 1"))
def _manifest(spark, sf_dir):
    path, _ = _spilled(GRAPHS["copurchase"](spark, sf_dir), spark, sf_dir)
    return storage.spill_manifest(spark, path).groupBy("range_id").agg(F.min("min_vid").alias("min_vid"), F.max("max_vid").alias("max_vid"), F.sum("n_rows").alias("n_rows"))


@query("spill_overlap", sql.select(sql.graph("copurchase"), "SELECT DISTINCT vid // 100 AS chunk, CAST(vid // ((SELECT count(*) FROM vertices) // 4 + CASE WHEN (SELECT count(*) FROM vertices) % 4 > 0 THEN 1 ELSE 0 END) AS INTEGER) AS range_id FROM vertices"))
def _overlap(spark, sf_dir):
    path, n = _spilled(GRAPHS["copurchase"](spark, sf_dir), spark, sf_dir)
    chunks = spark.range(0, n, 100).select(F.call_function("div", F.col("id"), F.lit(100)).alias("chunk"), F.col("id").alias("lo"), F.least(F.col("id") + 100, F.lit(n)).alias("hi"))
    return storage.spill_overlap(storage.spill_manifest(spark, path), chunks, n, 4).select("chunk", "range_id").distinct()


@query("read_chunk", sql.select(sql.graph("copurchase", True), "SELECT vid, CAST(i AS INTEGER) AS i, q FROM h WHERE vid >= 100 AND vid < 180"))
def _chunk(spark, sf_dir):
    path, n = _spilled(GRAPHS["copurchase"](spark, sf_dir), spark, sf_dir)
    return to_long_rows(storage.read_chunk(spark, path, 100, 180, n, 4))


@query("layer_spill_source", sql.select(sql.graph("copurchase", True), "SELECT vid, CAST(i AS INTEGER) AS i, q FROM h WHERE vid >= 150 AND vid < 190"))
def _source(spark, sf_dir):
    from layerflow.sources.spill_source import read_spills

    path, n = _spilled(GRAPHS["copurchase"](spark, sf_dir), spark, sf_dir)
    return to_long_rows(read_spills(spark, path).where("vid >= 150 and vid < 190").drop("range_id", "spill"))


query("relabel_edges", sql.select(f"{sql.graph('trade')}, {sql.ORDERS['yield']}", "SELECT a.pos AS src, b.pos AS dst FROM edges JOIN pos a ON a.vid = src JOIN pos b ON b.vid = dst"))(on("trade", lambda g: orders.relabel_edges(g.edges, orders.order_yield(g.edges, g.vertices))))


@query("relayout_features", sql.select(f"{sql.graph('copurchase', True)}, {sql.ORDERS['yield']}", "SELECT pos AS vid, CAST(i AS INTEGER) AS i, q FROM h JOIN pos USING (vid)"))
def _relayout(spark, sf_dir):
    from layerflow import store

    g = GRAPHS["copurchase"](spark, sf_dir)
    n, path = g.vertices.count(), store.new_path(spark, "relayout")
    storage.relayout_rows(g.features, orders.order_yield(g.edges, g.vertices), path, n, 4, 1000)
    return to_long_rows(spark.read.parquet(path).drop("range_id", "spill"))


# -- orders and progress ----------------------------------------------------------------------

ORDER = {
    "original": lambda g: orders.order_original(g.vertices),
    "random": lambda g: orders.order_random(g.vertices),
    "yield": lambda g: orders.order_yield(g.edges, g.vertices),
    "gain": lambda g: orders.order_yield(g.edges, g.vertices, cost="none"),
    "degree_in": lambda g: orders.order_degree(g.edges, g.vertices, "in"),
    "degree_out": lambda g: orders.order_degree(g.edges, g.vertices, "out"),
}
for _o in ORDER:
    _cols = "vid, score, pos" if _o in ("yield", "gain") else "vid, pos"
    query(f"order_{_o}", sql.select(f"{sql.graph('trade')}, {sql.ORDERS[_o]}", f"SELECT {_cols} FROM pos"))(on("trade", ORDER[_o]))
query("order_rcm")(on("embgraph", lambda g: orders.order_rcm(g.edges, g.vertices)))

for _g in ("trade", "copurchase", "embgraph"):
    for _o in ("original", "random", "yield"):
        _ctes = f"{sql.graph(_g)}, {sql.ORDERS[_o]}"
        query(f"span_{_g}_{_o}", sql.select(f"{_ctes}, {sql.SPANS}", "SELECT vid, first, last, last - first AS span FROM spans"))(on(_g, lambda g, o=_o: progress.vertex_span(g.edges, ORDER[o](g))))
for _o in ("original", "random", "yield", "degree_in"):
    _ctes = f"{sql.graph('trade')}, {sql.ORDERS[_o]}"
    query(f"span_percentiles_{_o}", sql.select(f"{_ctes}, {sql.SPANS}", "SELECT count(*) AS n, CAST(sum(last - first) AS BIGINT) AS total, CAST(quantile_disc(last - first, 0.5) AS DOUBLE) AS p50, CAST(quantile_disc(last - first, 0.9) AS DOUBLE) AS p90, CAST(quantile_disc(last - first, 0.99) AS DOUBLE) AS p99 FROM spans"))(
        on("trade", lambda g, o=_o: progress.span_summary(g.edges, ORDER[o](g)).select("n", "total", *[F.col(p).cast("double").alias(p) for p in ("p50", "p90", "p99")]))
    )
    query(f"active_series_{_o}", sql.select(f"{_ctes}, {sql.events(ROWS)}", "SELECT chunk, CAST(sum(opened - closed) OVER (ORDER BY chunk) + closed AS BIGINT) AS during, CAST(sum(opened - closed) OVER (ORDER BY chunk) AS BIGINT) AS after FROM ev"))(
        on("trade", lambda g, o=_o: progress.active_series(g.edges, ORDER[o](g), ROWS))
    )
    query(f"active_peak_{_o}", sql.select(f"{_ctes}, {sql.events(ROWS)}", "SELECT max(during) AS peak FROM (SELECT CAST(sum(opened - closed) OVER (ORDER BY chunk) + closed AS BIGINT) AS during FROM ev)"))(
        on("trade", lambda g, o=_o: progress.active_peak(g.edges, ORDER[o](g), ROWS))
    )
    query(f"finished_per_chunk_{_o}", sql.select(f"{_ctes}, {sql.events(ROWS)}", "SELECT chunk, closed AS finished FROM ev"))(on("trade", lambda g, o=_o: progress.finished_per_chunk(g.edges, ORDER[o](g), ROWS)))
    query(
        f"completion_curve_{_o}",
        sql.select(
            f"{_ctes}, d_ AS (SELECT dst, count(*) AS d FROM edges GROUP BY dst), g_ AS (SELECT src, CAST(sum(1099511627776 // d) AS BIGINT) AS g FROM edges JOIN d_ USING (dst) GROUP BY src)",
            "SELECT pos, CAST(sum(coalesce(g, 0)) OVER (ORDER BY pos) AS BIGINT) AS done FROM pos LEFT JOIN g_ ON g_.src = pos.vid",
        ),
    )(on("trade", lambda g, o=_o: progress.completion_curve(g.edges, ORDER[o](g))))
query("state_census", sql.select(f"{sql.graph('trade')}, {sql.ORDERS['yield']}, {sql.SPANS}", f"SELECT CASE WHEN first // {ROWS} > 10 THEN 'not started' WHEN last // {ROWS} > 10 THEN 'resident' ELSE 'completed' END AS state, count(*) AS n FROM spans GROUP BY 1"))(on("trade", lambda g: progress.state_census(g.edges, ORDER["yield"](g), ROWS, 10)))
query("message_trace", sql.select(f"{sql.graph('trade')}, {sql.ORDERS['yield']}", f"SELECT t.*, CAST(sum(cnt) OVER (PARTITION BY dst) AS BIGINT) AS d_in, p.pos AS dpos FROM (SELECT a.pos // {ROWS} AS chunk, dst, count(*) AS cnt FROM edges JOIN pos a ON a.vid = src GROUP BY 1, 2) t JOIN pos p ON p.vid = t.dst"))(
    on("trade", lambda g: progress.message_trace(g.edges, ORDER["yield"](g), ROWS))
)
query("early_low_degree", sql.select(f"{sql.graph('trade')}, {sql.ORDERS['yield']}, {sql.DEGREES}, {sql.SPANS}", f"SELECT least(d_in, 10) AS d_in, count(*) AS n, CAST(sum(last // {ROWS}) AS BIGINT) AS chunks FROM spans JOIN degrees USING (vid) GROUP BY 1"))(
    on("trade", lambda g: progress.vertex_span(g.edges, ORDER["yield"](g)).join(aggregate.degrees(g.edges, g.vertices), "vid").groupBy(F.least(F.col("d_in").cast("long"), F.lit(10).cast("long")).alias("d_in")).agg(F.count("*").alias("n"), F.sum(F.call_function("div", F.col("last"), F.lit(ROWS))).alias("chunks")))
)
for _o in ("original", "random", "yield"):
    query(f"combine_factor_{_o}", sql.select(f"{sql.graph('trade')}, {sql.ORDERS[_o]}, w_ AS (SELECT (count(*) + 15) // 16 AS w FROM vertices)", "SELECT count(*) AS edges, count(DISTINCT (p.pos // w, dst)) AS messages FROM edges JOIN pos p ON p.vid = src, w_"))(
        on("trade", lambda g, o=_o: aggregate.combine_factor(g.edges, ORDER[o](g), 16, g.vertices.count()))
    )

# -- aggregation and layers -------------------------------------------------------------------


def _against_own(x: DataFrame, own: DataFrame) -> DataFrame:
    """The aggregate less twice the own row."""
    cols = [f"c{i}" for i in range(8)]
    both = x.join(own.select("vid", "tile", *[F.col(c).alias(f"_{c}") for c in cols]), ["vid", "tile"])
    return both.select("vid", "tile", *[(F.col(c) - 2 * F.col(f"_{c}")).alias(c) for c in cols])


def _aggregate(engine: str, agg: str) -> Callable[[Graph], DataFrame]:
    f = {"push": aggregate.push_aggregate, "pull": aggregate.pull_aggregate}[engine]
    return lambda g: to_long_rows(f(g.edges, g.features, g.vertices, agg).drop("n_recv"))


for _g, _d in (("trade", 8), ("embgraph", 64), ("isolated", 8)):
    for _a in ("sum", "mean", "max", "min", "count") if _g != "isolated" else ("mean", "max"):
        _sql = sql.select(f"{sql.graph(_g, True)}, {sql.aggregated('h', 'x', _d, _a)}", "SELECT vid, i, q FROM x")
        query(f"push_{_a}_{_g}", _sql)(on(_g, _aggregate("push", _a)))
        if _a in ("sum", "mean", "max"):
            query(f"pull_{_a}_{_g}", _sql)(on(_g, _aggregate("pull", _a)))
query("push_bounded_sum", sql.select(f"{sql.graph('copurchase', True)}, {sql.aggregated('h', 'x', 8, 'sum')}", "SELECT vid, i, q FROM x"))(on("copurchase", lambda g: to_long_rows(tiers.push_combine_bounded(g.edges, g.features, g.vertices, 200).drop("n_recv"))))
query("push_bounded_mean", sql.select(f"{sql.graph('embgraph', True)}, {sql.aggregated('h', 'x', 64, 'mean')}", "SELECT vid, i, q FROM x"))(on("embgraph", lambda g: to_long_rows(tiers.push_combine_bounded(g.edges, g.features, g.vertices, 20, "lru", agg="mean").drop("n_recv"))))


def _rounded(rows: DataFrame) -> DataFrame:
    """Long rows of floats, rounded so that the order of sums doesn't show."""
    return to_long_rows(rows.drop("n_recv")).select("vid", "i", F.round("q", 4).alias("q"))


for _a, _v in (("std", "stddev_pop(h.q)"), ("both", "sum(h.q / sqrt(o.n * i.n))"), ("mean_in_message", "sum(h.q * (1.0 / i.n))")):
    query(
        f"agg_{ {'both': 'symmetric'}.get(_a, _a) }",
        sql.select(
            f"{sql.graph('embgraph', True)}, i_ AS (SELECT dst, count(*) AS n FROM edges GROUP BY dst), o_ AS (SELECT src, count(*) AS n FROM edges GROUP BY src)",
            f"SELECT v.vid, CAST(r.i AS INTEGER) AS i, round(coalesce(x, 0.0), 4) AS q FROM vertices v CROSS JOIN (SELECT unnest(range(0, 64)) AS i) r LEFT JOIN (SELECT e.dst, h.i, CAST({_v} AS DOUBLE) AS x FROM edges e JOIN h ON e.src = h.vid JOIN i_ i ON i.dst = e.dst JOIN o_ o ON o.src = e.src GROUP BY 1, 2) g ON g.dst = v.vid AND g.i = r.i",
        ),
    )(on("embgraph", lambda g, a=_a: _rounded(aggregate.push_aggregate(g.edges, g.features, g.vertices, a, False))))
query("messages_mean", sql.select(f"{sql.graph('trade', True)}, {sql.DEGREES}", "SELECT dst, CAST(h.i AS INTEGER) AS i, count(*) AS n, round(sum(h.q * (1.0 / d_in)), 4) AS q FROM edges JOIN degrees d ON d.vid = dst JOIN h ON h.vid = src GROUP BY 1, 2"))(
    on("trade", lambda g: to_long_rows(aggregate.make_messages(g.edges, g.features).withColumnRenamed("dst", "vid")).groupBy(F.col("vid").alias("dst"), "i").agg(F.count("*").alias("n"), F.round(F.sum("q"), 4).alias("q")))
)
query("message_layer", sql.select(f"{sql.graph('trade', True)}, {sql.aggregated('h', 'x', 8, 'max')}", "SELECT h.vid, CAST(h.i AS INTEGER) AS i, greatest(x.q - 2 * h.q, 0) AS q FROM h JOIN x USING (vid, i)"))(
    on("trade", lambda g: to_long_rows(layerwise.run_layer(g, g.features, layers.MessageLayer("max", _against_own, "relu", own=True))))
)


def _infer(kind: str, engine: str = "push", n: int = 2, materialize: bool = False) -> Callable[[Graph], DataFrame]:
    def run(g: Graph) -> DataFrame:
        out, _ = layerwise.infer_layerwise(g, layerwise.model(kind, g.d, layers=n), engine, materialize=materialize)
        return to_long_rows(out)

    return run


for _g, _d in (("trade", 8), ("embgraph", 64), ("copurchase", 8)):
    for _m in ("graphconv", "sage", "gin", "sgc"):
        _ctes, _last = sql.two_layers(_m, _d)
        _sql = sql.select(f"{sql.graph(_g, True)}, {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}")
        query(f"infer2_{_m}_{_g}", _sql)(on(_g, _infer(_m)))
        if _m != "sgc":
            query(f"pull2_{_m}_{_g}", _sql)(on(_g, _infer(_m, "pull")))
    for _m in ("graphconv", "sage", "gin"):
        _ctes, _last = sql.two_layers(_m, _d, layers=1)
        query(f"layer_{_m}_{_g}", sql.select(f"{sql.graph(_g, True)}, {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}"))(on(_g, _infer(_m, n=1)))
_ctes, _last = sql.two_layers("graphconv", 8)
query("infer2_graphconv_materialized", sql.select(f"{sql.graph('trade', True)}, {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}"))(on("trade", _infer("graphconv", materialize=True)))
query("layer_gat")(on("embgraph", lambda g: layerwise.infer_layerwise(g, layerwise.model("gat", g.d, layers=1), exact=False)[0]))
query("class_argmax", sql.select(f"{sql.graph('embgraph', True)}, {sql.two_layers('graphconv', 64)[0]}", "SELECT vid, CAST(min(i) FILTER (WHERE q = m) AS INTEGER) AS label FROM (SELECT vid, i, q, max(q) OVER (PARTITION BY vid) AS m FROM z1) GROUP BY vid"))(
    on("embgraph", lambda g: layers.argmax(layerwise.infer_layerwise(g, layerwise.model("graphconv", g.d))[0]))
)


@query("confusion", sql.select(f"{sql.graph('embgraph', True)}, {sql.two_layers('graphconv', 64)[0]}, p_ AS (SELECT vid, CAST(min(i) FILTER (WHERE q = m) AS INTEGER) AS predicted FROM (SELECT vid, i, q, max(q) OVER (PARTITION BY vid) AS m FROM z1) GROUP BY vid)", "SELECT label, predicted, count(*) AS n FROM embeddings JOIN p_ ON vid = vec_id WHERE label IS NOT NULL GROUP BY 1, 2"))
def _confusion(spark, sf_dir):
    predicted = QUERIES["class_argmax"](spark, sf_dir)
    return errors.confusion(predicted, table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), "label"))


@query("projection_sides", sql.select(f"{sql.graph('embgraph', True)}, {sql.aggregated('h', 'x', 64, 'sum')}, {sql.mapped('x', 'y', 64, 8, 0)}", "SELECT vid, i, q FROM y"))
def _projected(spark, sf_dir):
    """A sum layer whose rows are mapped to the narrower width before they are shuffled."""
    g = GRAPHS["embgraph"](spark, sf_dir)
    layer = layers.GraphConv([layerwise.make_weights(0, 64, 8)], agg="sum", act="identity")
    return to_long_rows(layerwise.run_layer(g, g.features, layer, side=layerwise.projection_side(layer, 64, 8)))


_WIDE = "h AS (SELECT b.vid, CAST(r.i AS INTEGER) AS i, CASE WHEN r.i < 8 THEN q ELSE (q * (1 + r.i // 8) + b.vid * 31 + r.i * 17) % 127 END AS q FROM base b JOIN (SELECT unnest(range(0, 256)) AS i) r ON r.i % 8 = b.i)"


@query("wide_layer_256", sql.select(f"{sql.graph('copurchase', True).replace('h AS (', 'base AS (', 1)}, {_WIDE}, {sql.aggregated('h', 'x', 256, 'mean')}, {sql.mapped('x', 'y', 256, 16, 0)}", "SELECT vid, i, q FROM y"))
def _wide(spark, sf_dir):
    """A mean layer over four tiles of 64 columns, mapped tile by tile."""
    g = GRAPHS["copurchase"](spark, sf_dir)
    g = Graph(g.name, g.vertices, g.edges, widen_features(g.features, 256), 256)
    layer = layers.GraphConv([layerwise.make_weights(0, 256, 16)], act="identity")
    return to_long_rows(layerwise.run_layer(g, g.features, layer))


# -- vertex-wise, samples, masks --------------------------------------------------------------


@query("vertexwise_batch", sql.select(f"{sql.graph('trade', True)}, {sql.two_layers('graphconv', 8)[0]}", "SELECT vid, CAST(z1.i AS INTEGER) AS i, z1.q FROM z1 JOIN vertices USING (vid) WHERE kind = 'supplier'"))
def _vertexwise(spark, sf_dir):
    """All suppliers, as one batch of targets."""
    g = GRAPHS["trade"](spark, sf_dir)
    return to_long_rows(vertexwise.infer_targets(g, layerwise.model("graphconv", g.d), g.vertices.where("kind = 'supplier'")))


@query("vertexwise_trade_all", sql.select(f"{sql.graph('trade', True)}, {sql.two_layers('graphconv', 8)[0]}", "SELECT vid, CAST(i AS INTEGER) AS i, q FROM z1"))
def _vertexwise_trade_all(spark, sf_dir):
    """Every vertex of trade, in four batches."""
    g = GRAPHS["trade"](spark, sf_dir)
    n = (g.vertices.agg(F.max("vid")).first()[0] or 0) + 1
    return to_long_rows(vertexwise.infer_vertexwise(g, layerwise.model("graphconv", g.d), n, -(-n // 4)))


@query("vertexwise_all", sql.select(f"{sql.graph('embgraph', True)}, {sql.two_layers('graphconv', 64)[0]}", "SELECT vid, CAST(i AS INTEGER) AS i, q FROM z1"))
def _vertexwise_all(spark, sf_dir):
    g = GRAPHS["embgraph"](spark, sf_dir)
    n = row_count(spark, sf_dir, "embeddings")
    return to_long_rows(vertexwise.infer_vertexwise(g, layerwise.model("graphconv", g.d), n, -(-n // 2)))


# -- the experiments' model: two layers, 128 wide, by the three systems ---------------------------

HIDDEN = 128
_stored_orders: dict[tuple, DataFrame] = {}


def stored_order(spark: SparkSession, sf_dir: str, graph: str, order: str) -> DataFrame:
    """(vid, pos) of a graph's order, made once a session."""
    from layerflow import store
    from layerflow.plans import engine

    key = (spark.sparkContext.applicationId, sf_dir, graph, order)
    if key not in _stored_orders:
        _stored_orders[key] = store.written(engine.ORDERS[order](GRAPHS[graph](spark, sf_dir)).select("vid", "pos"), "order")
    return _stored_orders[key]


def run_system(spark: SparkSession, sf_dir: str, graph: str, kind: str, system: str, hidden: int = HIDDEN):
    """(rows, reports) of one system: push over stored layers, pull in a bandwidth-reducing order, or superbatches."""
    from layerflow.plans import engine

    g = GRAPHS[graph](spark, sf_dir)
    m = layerwise.model(kind, g.d, hidden=hidden)
    if system == "push":
        return engine.run_engine(g, m, order=stored_order(spark, sf_dir, graph, "yield"))
    if system == "pull":
        return engine.pull_baseline(g, m, order=stored_order(spark, sf_dir, graph, "rcm"))
    n = (g.vertices.agg(F.max("vid")).first()[0] or 0) + 1
    return vertexwise.superbatch_baseline(g, m, n, -(-n // 8), 8, max(1, n // 5), max(1, n // 2))


def _system(graph: str, kind: str, system: str) -> Query:
    return lambda spark, sf_dir: to_long_rows(run_system(spark, sf_dir, graph, kind, system)[0]).where(F.col("i") < 4)


for _g, _d in (("embgraph", 64), ("copurchase", 8), ("trade", 8)):
    for _m in ("graphconv", "sage", "gin"):
        _ctes, _last = sql.two_layers(_m, _d, hidden=HIDDEN)
        # 128 x 128 products of every vertex of trade are too much for SQL; the other graphs check that model
        _sql = None if (_g, _m) == ("trade", "gin") else sql.select(f"{sql.graph(_g, True)}, {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}")
        for _s in ("push", "pull", "superbatch"):
            query(f"w1_{_g}_{_m}_{_s}", _sql)(_system(_g, _m, _s))
for _o in ("original", "random", "yield"):
    _ctes, _last = sql.two_layers("sage", 8, hidden=HIDDEN)
    query(f"engine_order_{_o}", sql.select(f"{sql.graph('copurchase', True)}, {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}"))(on("copurchase", lambda g, o=_o: to_long_rows(_run_bounded(g, o))))


def _run_bounded(g: Graph, order: str) -> DataFrame:
    """The stored engine with few slots, small chunks, spills and buffers."""
    from layerflow.plans import engine

    return engine.run_engine(g, layerwise.model("sage", g.d, hidden=HIDDEN), order, slots=50, chunk_rows=16, spill_rows=100, buffer_rows=64)[0]


@query("engine_chunks", sql.select(f"{sql.graph('copurchase', True)}, d_ AS (SELECT src, count(*) AS d FROM edges GROUP BY src)", "SELECT h.vid, h.vid // 64 AS chunk, d, CAST(sum(q) AS BIGINT) AS q FROM h JOIN d_ ON src = h.vid GROUP BY 1, 2, 3"))
def _engine_chunks(spark, sf_dir):
    """Topology and rows of the same vertices, chunk by chunk, as the engine reads them."""
    from layerflow import store
    from layerflow.plans import engine

    g = GRAPHS["copurchase"](spark, sf_dir)
    n, topology = g.vertices.count(), store.new_path(spark, "topology")
    engine.write_topology(g, topology, n, 4)
    rows = engine.iter_chunks(spark, topology, storage.write_layer(spark, g.features, 0, n, 4, 100), 64)
    return rows.select("vid", "chunk", F.size("dst").cast("long").alias("d"), sum((F.col(f"c{i}") for i in range(1, 8)), F.col("c0")).alias("q"))


@query("refresh_incremental", sql.select(f"{sql.graph('embgraph', True).replace('h AS (', 'old AS (', 1)}, h AS (SELECT vid, i, CASE WHEN vid % 50 = 0 THEN q + 1000 ELSE q END AS q FROM old), {sql.two_layers('graphconv', 64)[0]}", "SELECT vid, CAST(i AS INTEGER) AS i, q FROM z1"))
def _refresh(spark, sf_dir):
    g = GRAPHS["embgraph"](spark, sf_dir)
    m = layerwise.model("graphconv", g.d)
    old, _ = layerwise.infer_layerwise(g, m)
    cols = [c for c in g.features.columns if c[0] == "c"]
    new = g.features.select("vid", "tile", *[F.when(F.col("vid") % 50 == 0, F.col(c) + 1000).otherwise(F.col(c)).alias(c) for c in cols])
    changed = Graph(g.name, g.vertices, g.edges, new, g.d)
    return to_long_rows(vertexwise.refresh_incremental(changed, m, old, g.vertices.where("vid % 50 = 0")))


_SAMPLED = "sampled AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY dst ORDER BY md5('0:' || CAST(src AS VARCHAR) || ':' || CAST(dst AS VARCHAR)), src) AS r FROM edges) WHERE r <= 5)"
query("sampled_edges", sql.select(f"{sql.graph('trade')}, {_SAMPLED}", "SELECT src, dst FROM sampled"))(on("trade", lambda g: sampling.sample_neighbors(g.edges, 5)))
_ctes, _last = sql.two_layers("graphconv", 8, layers=1, edges="kept")
query("masked_layer", sql.select(f"{sql.graph('trade', True)}, kept AS (SELECT * FROM edges WHERE (src + dst) % 3 <> 0), {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}"))(
    on("trade", lambda g: _infer("graphconv", n=1)(g.with_edges(sampling.masked(sampling.mask_edges(g.edges, (F.col("src") + F.col("dst")) % 3 != 0)))))
)
query("sampled_layer", sql.select(f"{sql.graph('trade', True)}, {_SAMPLED}, {sql.two_layers('graphconv', 8, layers=1, edges='sampled')[0]}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}"))(on("trade", lambda g: _infer("graphconv", n=1)(g.with_edges(sampling.sample_neighbors(g.edges, 5)))))
query("partition_local_layer", sql.select(f"{sql.graph('trade', True)}, w_ AS (SELECT (count(*) + 3) // 4 AS w FROM vertices), kept AS (SELECT src, dst FROM edges, w_ WHERE src // w = dst // w), {_ctes}", f"SELECT vid, CAST(i AS INTEGER) AS i, q FROM {_last}"))(
    on("trade", lambda g: _infer("graphconv", n=1)(g.with_edges(sampling.partition_local(g.edges, g.vertices.count(), 4))))
)
_STEP = "f{n} AS (SELECT vid, {n} AS hop FROM (SELECT DISTINCT src AS vid FROM edges SEMI JOIN f{m} ON dst = f{m}.vid) ANTI JOIN s{m} USING (vid)), s{n} AS (SELECT * FROM s{m} UNION ALL SELECT * FROM f{n})"


def _hops(seeds: str, hops: int) -> str:
    """CTEs f0.. of vertices first reached at each hop, and s0.. of all up to there."""
    return ", ".join([f"f0 AS (SELECT vid, 0 AS hop FROM vertices WHERE {seeds}), s0 AS (SELECT * FROM f0)", *(_STEP.format(n=n, m=n - 1) for n in range(1, hops + 1))])


#: The k-hop queries' targets are all suppliers; the working set of training steps starts from one vertex in a hundred.
_TARGETS, _SEEDS = "kind = 'supplier'", "vid % 100 = 0"
query("khop_frontier", sql.select(f"{sql.graph('trade')}, {_hops(_TARGETS, 2)}", "SELECT vid, hop FROM s2"))(on("trade", lambda g: sampling.frontier(g.edges, g.vertices.where(_TARGETS), 2)))
query("khop_subgraph", sql.select(f"{sql.graph('trade')}, {_hops(_TARGETS, 1)}", "SELECT src, dst FROM edges SEMI JOIN s1 ON dst = s1.vid"))(on("trade", lambda g: sampling.khop_subgraph(g.edges, g.vertices.where(_TARGETS), 2)))
for _k in (2, 3):
    for _f in ("", "_fanout"):
        _e = f", {_SAMPLED}, {_hops(_SEEDS, _k).replace('FROM edges', 'FROM sampled')}" if _f else f", {_hops(_SEEDS, _k)}"
        query(f"w7_touched_share_{_k}{_f}", sql.select(f"{sql.graph('trade')}{_e}", f"SELECT (SELECT count(*) FROM f0) AS seeds, (SELECT count(*) FROM s{_k}) AS touched, (SELECT count(*) FROM vertices) AS vertices"))(
            on("trade", lambda g, k=_k, f=5 if _f else None: sampling.touched_share(g.edges, g.vertices, 100, k, f))
        )
query("subgraph_bytes", sql.select(f"{sql.graph('trade')}, {_hops(_TARGETS, 2)}, e_ AS (SELECT count(*) AS edges FROM edges SEMI JOIN s1 ON dst = s1.vid), v_ AS (SELECT count(*) AS rows_ FROM s2)", "SELECT edges, rows_ AS rows, edges * 16 + rows_ * 16 AS bytes FROM e_, v_"))(
    on("trade", lambda g: sampling.subgraph_bytes(g.edges, g.vertices.where(_TARGETS), 2, 8, 2))
)
query("frontier_redundancy", sql.select(f"{sql.graph('embgraph')}, l0 AS (SELECT vid // 100 AS batch, vid FROM vertices), l1 AS (SELECT DISTINCT batch, src AS vid FROM l0 JOIN edges ON dst = vid), l2 AS (SELECT DISTINCT batch, src AS vid FROM l1 JOIN edges ON dst = vid)", "SELECT batch, 0 AS hop, count(*) AS n FROM l0 GROUP BY 1 UNION ALL SELECT batch, 1, count(*) FROM l1 GROUP BY 1 UNION ALL SELECT batch, 2, count(*) FROM l2 GROUP BY 1"))(
    on("embgraph", lambda g: sampling.frontier_redundancy(g.edges, g.vertices, 100, 2))
)

# -- tiers, caches, modelled reads --------------------------------------------------------------


def _replay(g: Graph, policy: str, percent: int, order: str = "yield") -> tiers.Replay:
    from layerflow import store

    lists = arrays.both_lists(g.ends)
    pos = orders.order_yield(None, g.vertices, lists=lists) if order == "yield" else ORDER[order](g)
    packed = tiers.packed_runs(None, pos.select("vid", "pos"), 64, far=policy == "farthest", lists=lists)
    store.discard(lists.rows)
    return tiers.replay_packed(packed, max(1, tiers.packed_peak(packed) * percent // 100), policy)


for _p in tiers.POLICIES:
    query(f"replay_{_p}")(on("trade", lambda g, p=_p: _replay(g, p, 50).summary()))
for _s in (30, 50, 71, 83, 100, 143):
    query(f"replay_slots_{_s}")(on("trade", lambda g, s=_s: _replay(g, "fewest", s).summary()))
for _o in ("original", "random", "yield"):
    query(f"replay_order_{_o}")(on("trade", lambda g, o=_o: _replay(g, "fewest", 71, o).summary()))
query("reload_cdf")(on("trade", lambda g: _replay(g, "fewest", 50).reload_cdf()))
query("parked_series")(on("trade", lambda g: _replay(g, "fewest", 50).parked_series()))
query("belady")(on("embgraph", lambda g: tiers.cache_replay(tiers.page_trace(g.edges, 64, 1), 100, "farthest")))
query("page_cache")(on("embgraph", lambda g: tiers.page_cache_replay(g.edges, 64, 16, 16)))
query("pull_read_blocks", sql.select(sql.graph("trade"), "SELECT dst // 64 AS batch, count(DISTINCT src // 16) AS blocks FROM edges GROUP BY 1"))(on("trade", lambda g: progress.pull_read_blocks(g.edges, 64, 16)))
query("read_amplification", sql.select(f"{sql.graph('trade')}, b_ AS (SELECT count(*) AS blocks FROM (SELECT DISTINCT dst // 64, src // 16 FROM edges)), o_ AS (SELECT (count(*) + 15) // 16 AS once FROM vertices)", "SELECT blocks, once, blocks * 1000 // once AS per_mille FROM b_, o_"))(on("trade", lambda g: progress.read_amplification(g.edges, g.vertices.count(), 64, 16)))
query("push_read_bytes", sql.select(sql.graph("trade"), "SELECT (SELECT count(*) FROM vertices) * 16 + 8 * ((SELECT count(*) FROM vertices) + (SELECT count(*) FROM edges)) AS bytes"))(
    on("trade", lambda g: g.edges.agg(F.count("*").alias("e")).join(g.vertices.agg(F.count("*").alias("v"))).select((F.col("v") * 16 + (F.col("v") + F.col("e")) * 8).alias("bytes")))
)
query("neighbor_cache", sql.select(f"{sql.graph('trade')}, {sql.DEGREES}, r_ AS (SELECT vid, d_in, row_number() OVER (ORDER BY d_out DESC, vid) - 1 AS rank FROM degrees), u_ AS (SELECT vid, rank, CAST(sum(d_in) OVER (ORDER BY rank) AS BIGINT) AS used FROM r_)", "SELECT vid, rank, used FROM u_ WHERE used <= 20000"))(on("trade", lambda g: progress.neighbor_cache(g.edges, g.vertices, 20_000)))
query("dynamic_batches", sql.select(f"{sql.graph('trade')}, {sql.DEGREES}", "SELECT vid, CAST((sum(d_in) OVER (ORDER BY vid) - d_in) // 1000 AS BIGINT) AS batch FROM degrees"))(on("trade", lambda g: progress.dynamic_batches(g.edges, orders.order_original(g.vertices), 1000)))


@query("class_accuracy", sql.select(f"{sql.graph('embgraph', True)}, {sql.two_layers('graphconv', 64)[0]}, p_ AS (SELECT vid, min(i) FILTER (WHERE q = m) AS predicted FROM (SELECT vid, i, q, max(q) OVER (PARTITION BY vid) AS m FROM z1) GROUP BY vid)", "SELECT count(*) FILTER (WHERE label = predicted) AS right, count(*) AS total FROM embeddings JOIN p_ ON vid = vec_id WHERE label IS NOT NULL"))
def _accuracy(spark, sf_dir):
    predicted = QUERIES["class_argmax"](spark, sf_dir)
    return errors.class_accuracy(predicted, table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), "label"))


_ERRORS = f"{sql.graph('embgraph', True)}, {_SAMPLED}, {sql.two_layers('graphconv', 64)[0]}, {sql.two_layers('graphconv', 64, edges='sampled', prefix='s_')[0]}"


@query("err_max_abs", sql.select(_ERRORS, "SELECT round(avg(m), 6) AS error FROM (SELECT z1.vid, CAST(max(abs(z1.q - s_z1.q)) AS DOUBLE) AS m FROM z1 JOIN s_z1 USING (vid, i) GROUP BY 1)"))
def _max_error(spark, sf_dir):
    """What sampling five in-edges changes: mean over vertices of the largest difference."""
    g = GRAPHS["embgraph"](spark, sf_dir)
    m = layerwise.model("graphconv", g.d)
    sampled, _ = layerwise.infer_layerwise(g.with_edges(sampling.sample_neighbors(g.edges, 5)), m)
    return errors.mean_max_abs_error(sampled, layerwise.infer_layerwise(g, m)[0]).select(F.round("error", 6).alias("error"))


@query("err_avg_rel", sql.select(_ERRORS, "SELECT round(avg(m), 9) AS error FROM (SELECT z1.vid, avg(abs(z1.q - s_z1.q) / greatest(abs(z1.q), 1.0)) AS m FROM z1 JOIN s_z1 USING (vid, i) GROUP BY 1)"))
def _sampled_error(spark, sf_dir):
    """What sampling five in-edges costs in accuracy."""
    g = GRAPHS["embgraph"](spark, sf_dir)
    m = layerwise.model("graphconv", g.d)
    return errors.mean_avg_rel_error(layerwise.infer_layerwise(g.with_edges(sampling.sample_neighbors(g.edges, 5)), m)[0], layerwise.infer_layerwise(g, m)[0], 1.0).select(F.round("error", 9).alias("error"))


_PRICE = "CAST(floor(abs(coalesce(o_totalprice, 0))) AS BIGINT)"


@query(
    "arithmetic",
    f"SELECT o_orderkey, greatest(1, 8388608 // (width * itemsize)) AS rows, price * 1048576 // (width * itemsize) AS slots, CAST(CASE WHEN price < 21600 THEN price ELSE price * 4 END AS DOUBLE) AS extrapolated FROM (SELECT o_orderkey, 128 + o_custkey % 897 AS width, 2 + 2 * (o_orderkey % 2) AS itemsize, {_PRICE} AS price FROM orders)",
)
def _arithmetic(spark, sf_dir):
    """Rows of an 8 MiB chunk, slots of a budget and a stopped run's time, for each order's width, budget (MiB) and seconds."""
    price = F.floor(F.abs(F.coalesce(F.col("o_totalprice"), F.lit(0.0)))).cast("long")
    o = table(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_custkey") % 897 + 128).alias("width"), (F.col("o_orderkey") % 2 * 2 + 2).alias("itemsize"), price.alias("price"))
    rows = F.udf(lambda d, size: progress.chunk_rows(8 << 20, d, size), "long", useArrow=True)
    slots = F.udf(lambda mb, d, size: progress.slots_for(mb << 20, d, size), "long", useArrow=True)
    stopped = F.udf(lambda seconds: float(errors.extrapolate(seconds, 0.25, 1.0)), "double", useArrow=True)
    return o.select("o_orderkey", rows("width", "itemsize").alias("rows"), slots("price", "width", "itemsize").alias("slots"), stopped("price").alias("extrapolated"))


@query("recommend_slots", sql.select(f"{sql.graph('trade')}, {sql.ORDERS['yield']}, {sql.events(ROWS)}", "SELECT CAST(ceil(max(during) * 0.9) AS BIGINT) AS slots, least(CAST(ceil(max(during) * 0.9) AS BIGINT), 100) AS capped FROM (SELECT sum(opened - closed) OVER (ORDER BY chunk) + closed AS during FROM ev)"))
def _recommended(spark, sf_dir):
    g = GRAPHS["trade"](spark, sf_dir)
    pos = stored_order(spark, sf_dir, "trade", "yield")
    return spark.createDataFrame([(progress.recommend_slots(g.edges, pos, ROWS, 0.1), progress.recommend_slots(g.edges, pos, ROWS, 0.1, 100))], "slots long, capped long")


@query("speedup_table", "SELECT n_name AS graph, CAST(n_regionkey AS VARCHAR) AS model, CAST(n_nationkey + 1 AS DOUBLE) AS push, CAST(3 * (n_nationkey + 1) AS DOUBLE) AS pull, CAST(3.0 AS DOUBLE) AS pull_over_push FROM nation")
def _speedups(spark, sf_dir):
    """Made-up seconds by nation: what counts is the table's shape."""
    t = table(spark, sf_dir, "nation").select(F.col("n_name").alias("graph"), F.col("n_regionkey").cast("string").alias("model"), (F.col("n_nationkey") + 1).cast("double").alias("s"))
    return errors.speedup_table(t.select("graph", "model", F.lit("push").alias("engine"), F.col("s").alias("seconds")).unionByName(t.select("graph", "model", F.lit("pull").alias("engine"), (F.col("s") * 3).alias("seconds"))), "push")


@query("memory_model", sql.select(sql.graph("trade"), "SELECT count(*) * 13 AS orchestrator, 64 * 128 * 4 + 3 * 1048576 + count(*) * 13 AS total FROM vertices"))
def _memory(spark, sf_dir):
    n = GRAPHS["trade"](spark, sf_dir).vertices.count()
    return spark.createDataFrame([(progress.orchestrator_bytes(n), errors.memory_plan(64, 128, 4, 1 << 20, 3, 0, n)["total"])], "orchestrator long, total long")


query("early_low_degree_self_loops", sql.select(f"{sql.graph('trade').replace('edges AS (', 'given AS (', 1)}, edges AS (SELECT src, dst FROM given UNION SELECT vid, vid FROM vertices), {sql.ORDERS['yield']}, {sql.DEGREES}, {sql.SPANS}", f"SELECT least(d_in, 10) AS d_in, count(*) AS n, CAST(sum(last // {ROWS}) AS BIGINT) AS chunks FROM spans JOIN degrees USING (vid) GROUP BY 1"))(
    on("trade", lambda g: _early(g.with_edges(aggregate.add_self_loops(g.edges, g.vertices))))
)


def _early(g: Graph) -> DataFrame:
    """Chunks in which vertices complete, by in-degree."""
    spans = progress.vertex_span(g.edges, ORDER["yield"](g)).join(aggregate.degrees(g.edges, g.vertices), "vid")
    return spans.groupBy(F.least(F.col("d_in").cast("long"), F.lit(10).cast("long")).alias("d_in")).agg(F.count("*").alias("n"), F.sum(F.call_function("div", F.col("last"), F.lit(ROWS))).alias("chunks"))


query("dense_positions", "SELECT n_nationkey, row_number() OVER (ORDER BY n_name, n_nationkey) - 1 AS pos FROM nation")(lambda spark, d: dense_positions(table(spark, d, "nation").select("n_nationkey", "n_name"), [F.col("n_name"), F.col("n_nationkey")]).select("n_nationkey", "pos"))


def queries() -> dict[str, Query]:
    from layerflow.operators import relational  # noqa: F401  adds its own
    from layerflow.plans import workloads  # noqa: F401

    return dict(QUERIES)


def oracles() -> dict[str, str]:
    queries()
    return dict(ORACLES)
