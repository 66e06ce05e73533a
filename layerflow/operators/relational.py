"""Operators around the graph engine: what it takes to build graphs, look at embeddings and serve results.

Each registers a query on the given tables with SQL to check it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from layerflow.catalog import query
from layerflow.sources.tables import table


def asof_join(left: DataFrame, right: DataFrame, time: str, by: str | None, value: str) -> DataFrame:
    """Adds to each row of left the value of right's last row at or before its time.

    Both sides are united and one ordered window carries the last value forward: no pair of rows is formed.  Without
    ``by`` the windows are cut by day, and a day's first rows take the last value of the days before.
    """
    l = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_s", F.lit(1))  # noqa: E741
    r = right.select(*[F.col(c) if c in right.columns else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value).alias("_v"), F.lit(0).alias("_s"))
    u = l.unionByName(r)
    if by:
        w = Window.partitionBy(by).orderBy(time, "_s").rowsBetween(Window.unboundedPreceding, 0)
        return u.withColumn(value, F.last("_v", True).over(w)).where("_s = 1").drop("_v", "_s")
    u = u.withColumn("_d", F.to_date(time))
    w = Window.partitionBy("_d").orderBy(time, "_s").rowsBetween(Window.unboundedPreceding, 0)
    days = u.where("_s = 0").groupBy("_d").agg(F.max_by("_v", F.struct(time)).alias("_l"))
    before = u.select("_d").distinct().join(days, "_d", "left").select("_d", F.last("_l", True).over(Window.orderBy("_d").rowsBetween(Window.unboundedPreceding, -1)).alias("_b"))
    return u.withColumn("_in", F.last("_v", True).over(w)).join(F.broadcast(before), "_d", "left").where("_s = 1").withColumn(value, F.coalesce("_in", "_b")).drop("_v", "_s", "_d", "_in", "_b")


def range_join(points: DataFrame, ranges: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points within [lo, hi) of ranges: ranges are laid over buckets of ``width``, and buckets joined by equality."""
    div = lambda c: F.call_function("div", c, F.lit(width))
    r = ranges.withColumn("_b", F.explode(F.sequence(div(F.col(lo)), div(F.col(hi) - 1))))
    return points.withColumn("_b", div(F.col(at))).join(r, "_b").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_b")


def _t(name: str):
    return lambda spark, d: table(spark, d, name)


def simple(name: str, sql: str, *tables: str):
    """A query of a function of tables."""

    def keep(f):
        def run(spark: SparkSession, d: str) -> DataFrame:
            return f(*[table(spark, d, t) for t in tables])

        query(name, sql)(run)
        return f

    return keep


LONG = "long"


@simple("op_project", "SELECT c_custkey, c_custkey * 2 + 1 AS odd, upper(c_mktsegment) AS segment FROM customer", "customer")
def _project(c):
    return c.select("c_custkey", (F.col("c_custkey") * 2 + 1).alias("odd"), F.upper("c_mktsegment").alias("segment"))


@simple("op_filter_range", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_partkey BETWEEN 10 AND 40 AND l_returnflag IN ('R', 'A')", "lineitem")
def _range(x):
    return x.where(F.col("l_partkey").between(10, 40) & F.col("l_returnflag").isin("R", "A")).select("l_orderkey", "l_partkey")


@simple("op_filter_like", "SELECT p_partkey, p_type FROM part WHERE p_name LIKE '%1%' AND p_brand IS NOT NULL", "part")
def _like(p):
    return p.where(F.col("p_name").like("%1%") & F.col("p_brand").isNotNull()).select("p_partkey", "p_type")


@simple("op_filter_snapshot", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderdate < TIMESTAMP '1996-01-01'", "orders")
def _snapshot(o):
    return o.where(F.col("o_orderdate") < F.lit("1996-01-01").cast("timestamp")).select("o_orderkey", "o_custkey")


_JOIN = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"
for _hint, _name in (("shuffle_hash", "hash"), ("merge", "merge"), (None, "planned")):

    @simple(f"op_join_{_name}", _JOIN, "orders", "customer")
    def _join(o, c, hint=_hint):
        c = c.hint(hint) if hint else c
        return o.join(c, o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_mktsegment")


@simple("op_join_broadcast", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey", "supplier", "nation", "region")
def _broadcast(s, n, r):
    """Nation and region have a fixed size."""
    return s.join(F.broadcast(n), s["s_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), F.col("n_regionkey") == r["r_regionkey"]).select("s_suppkey", "n_name", "r_name")


@simple("op_join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", "nation")
def _theta(n):
    a, b = n.select(F.col("n_nationkey").alias("a"), "n_regionkey"), n.select(F.col("n_nationkey").alias("b"), "n_regionkey")
    return a.join(b, "n_regionkey").where("a < b").select("a", "b")


@simple("op_join_range", "SELECT event_id, lo FROM events JOIN (SELECT i * 700 AS lo, i * 700 + 1000 AS hi FROM (SELECT unnest(range(0, 20)) AS i)) r ON event_id >= lo AND event_id < hi", "events")
def _range_join(e):
    r = e.sparkSession.range(20).select((F.col("id") * 700).alias("lo"), (F.col("id") * 700 + 1000).alias("hi"))
    return range_join(e.select("event_id"), r, "event_id", "lo", "hi", 1000).select("event_id", "lo")


@simple("op_join_range_all", "SELECT event_id, lo FROM events JOIN (SELECT i * 700 AS lo, i * 700 + 1000 AS hi FROM (SELECT unnest(range(0, max(event_id) // 700 + 1)) AS i FROM events)) r ON event_id >= lo AND event_id < hi", "events")
def _range_join_all(e):
    """As many ranges as it takes to cover every event."""
    r = e.agg(F.expr("max(event_id) div 700").alias("last")).select(F.explode(F.expr("sequence(0L, last)")).alias("id")).select((F.col("id") * 700).alias("lo"), (F.col("id") * 700 + 1000).alias("hi"))
    return range_join(e.select("event_id"), r, "event_id", "lo", "hi", 1000).select("event_id", "lo")


@simple(
    "op_join_asof",
    "SELECT o.event_id AS probe, max_by(e.event_id, (e.ts, e.event_id)) AS latest FROM events o JOIN events e ON o.user_id = e.user_id AND e.event_type = 'click' AND e.ts <= o.ts WHERE o.event_type = 'purchase' GROUP BY 1",
    "events",
)
def _asof(e):
    clicks = e.where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("latest"))
    # of clicks at one time the one with the largest id
    clicks = clicks.groupBy("user_id", "ts").agg(F.max("latest").alias("latest"))
    probes = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("probe"))
    return asof_join(probes, clicks, "ts", "user_id", "latest").where("latest is not null").select("probe", "latest")


@simple("op_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')", "customer", "orders")
def _semi(c, o):
    return c.join(o.where("o_orderstatus = 'F'"), c["c_custkey"] == o["o_custkey"], "left_semi").select("c_custkey")


@simple("op_anti", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')", "part", "lineitem")
def _anti(p, x):
    return p.join(x.where("l_returnflag = 'R'"), p["p_partkey"] == x["l_partkey"], "left_anti").select("p_partkey")


@simple("op_outer", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1", "customer", "orders")
def _outer(c, o):
    n = o.groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("o_orderkey").alias("n"))
    return c.join(n, "c_custkey", "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"))


@simple("op_full_outer", "SELECT coalesce(a.k, b.k) AS k, a.n AS a, b.n AS b FROM (SELECT p_size AS k, count(*) AS n FROM part WHERE p_size < 30 GROUP BY 1) a FULL JOIN (SELECT p_size AS k, count(*) AS n FROM part WHERE p_size > 20 GROUP BY 1) b ON a.k = b.k", "part")
def _full(p):
    a = p.where("p_size < 30").groupBy(F.col("p_size").alias("k")).agg(F.count("*").alias("a"))
    b = p.where("p_size > 20").groupBy(F.col("p_size").alias("k")).agg(F.count("*").alias("b"))
    return a.join(b, "k", "full")


@simple("op_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1", "lineitem")
def _distinct(x):
    return x.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


_CUBE = "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem GROUP BY {}"


def _counts(g):
    return g.agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


simple("op_cube", _CUBE.format("CUBE (l_returnflag, l_linestatus)"), "lineitem")(lambda x: _counts(x.cube("l_returnflag", "l_linestatus")))
simple("op_rollup", _CUBE.format("ROLLUP (l_returnflag, l_linestatus)"), "lineitem")(lambda x: _counts(x.rollup("l_returnflag", "l_linestatus")))
simple("op_gsets", _CUBE.format("GROUPING SETS ((l_returnflag), (l_linestatus))"), "lineitem")(lambda x: _counts(x.groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus")))


@simple("op_pivot", "SELECT o_orderstatus, count(*) FILTER (WHERE o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (WHERE o_orderpriority = '5-LOW') AS low FROM orders GROUP BY 1", "orders")
def _pivot(o):
    p = o.groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).count()
    return p.select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low"))


@simple("op_unpivot", "SELECT p_partkey, 'p_size' AS name, CAST(p_size AS BIGINT) AS value FROM part UNION ALL SELECT p_partkey, 'p_partkey2', p_partkey * 2 FROM part", "part")
def _unpivot(p):
    return p.select("p_partkey", F.col("p_size").cast("long").alias("p_size"), (F.col("p_partkey") * 2).alias("p_partkey2")).unpivot("p_partkey", ["p_size", "p_partkey2"], "name", "value")


@simple("op_win_rank", "SELECT p_partkey, row_number() OVER w AS a, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS b, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS c, ntile(4) OVER w AS d FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)", "part")
def _rank(p):
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    return p.select("p_partkey", *[f.cast("long").alias(n) for f, n in ((F.row_number().over(w), "a"), (F.rank().over(v), "b"), (F.dense_rank().over(v), "c"), (F.ntile(4).over(w), "d"))])


@simple("op_win_lag", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after2, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")
def _lag(e):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after2"), F.first("event_id").over(w).alias("first"))


@simple("op_win_frame", "SELECT o_orderkey, CAST(sum(o_custkey) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS BIGINT) AS moving, CAST(count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS BIGINT) AS near FROM orders", "orders")
def _frame(o):
    w = Window.partitionBy("o_orderstatus").orderBy("o_orderkey")
    return o.select("o_orderkey", F.sum("o_custkey").over(w.rowsBetween(-3, 0)).alias("moving"), F.count("*").over(w.rangeBetween(-10, 10)).alias("near"))


@simple("op_topk", "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, l_partkey LIMIT 10", "lineitem")
def _topk(x):
    return x.groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").limit(10)


@simple("op_topk_group", "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_size DESC, p_partkey) AS r FROM part) WHERE r <= 3", "part")
def _topk_group(p):
    r = F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("p_size"), "p_partkey"))
    return p.withColumn("r", r).where("r <= 3").select("p_brand", "p_partkey")


@simple("op_setops", "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A' EXCEPT SELECT p_partkey FROM part WHERE p_size < 25", "lineitem", "part")
def _setops(x, p):
    k = x.select(F.col("l_partkey").alias("k"), "l_returnflag")
    return k.where("l_returnflag = 'R'").select("k").intersect(k.where("l_returnflag = 'A'").select("k")).subtract(p.where("p_size < 25").select(F.col("p_partkey").alias("k")))


@simple("op_string", "SELECT page_id, md5(url) AS digest, lower(split_part(url, '/', 3)) AS host, len(regexp_extract_all(html, '<p>')) AS paragraphs FROM pages", "pages")
def _string(p):
    return p.select("page_id", F.md5("url").alias("digest"), F.lower(F.split_part("url", F.lit("/"), F.lit(3))).alias("host"), F.size(F.regexp_extract_all("html", F.lit("(<p>)"), F.lit(1))).cast("long").alias("paragraphs"))


@simple("op_date", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n, max(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS days FROM orders GROUP BY 1, 2", "orders")
def _date(o):
    days = F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).cast("long")
    return o.groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n"), F.max(days).alias("days"))


@simple("op_math", "SELECT p_partkey, CAST(floor(sqrt(p_size * 100)) AS BIGINT) AS root, greatest(p_size - 25, 0) AS relu FROM part", "part")
def _math(p):
    return p.select("p_partkey", F.floor(F.sqrt(F.col("p_size") * 100)).alias("root"), F.greatest(F.col("p_size") - 25, F.lit(0)).alias("relu"))


@simple("op_array", "SELECT vec_id, len(embedding) AS d, CAST(list_position(embedding, list_max(embedding)) - 1 AS BIGINT) AS largest FROM embeddings", "embeddings")
def _array(e):
    return e.select("vec_id", F.size("embedding").cast("long").alias("d"), (F.array_position("embedding", F.array_max("embedding")) - 1).alias("largest"))


@simple("op_json", "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS total, count(*) AS n FROM events GROUP BY 1", "events")
def _json(e):
    k = F.from_json("props", "k long")["k"]
    return e.groupBy("event_type").agg(F.sum(k).alias("total"), F.count("*").alias("n"))


def _epoch(c):
    return F.unix_seconds(F.col(c).cast("timestamp"))


_WINDOWED = "SELECT CAST(floor(epoch(ts) / {w}) * {w} AS BIGINT) + {o} AS start, event_type, count(*) AS n FROM events {j} GROUP BY 1, 2"


@simple("op_tumble", "SELECT CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2", "events")
def _tumble(e):
    w = e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return w.select(_epoch("window.start").alias("start"), "event_type", "n")


@simple("op_slide", "SELECT CAST(floor(epoch(ts) / 1800) * 1800 AS BIGINT) - o AS start, event_type, count(*) AS n FROM events, (SELECT 0 AS o UNION ALL SELECT 1800) GROUP BY 1, 2", "events")
def _slide(e):
    w = e.groupBy(F.window("ts", "1 hour", "30 minutes"), "event_type").agg(F.count("*").alias("n"))
    return w.select(_epoch("window.start").alias("start"), "event_type", "n")


@simple(
    "op_session",
    "SELECT user_id, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s, event_id FROM (SELECT user_id, ts, event_id, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 86400000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s",
    "events",
)
def _session(e):
    return e.groupBy("user_id", F.session_window("ts", "1 day")).agg(F.count("*").alias("n")).select("user_id", "n")


@simple("op_approx_distinct", "SELECT l_returnflag, true AS close FROM lineitem GROUP BY 1", "lineitem")
def _approx(x):
    a = x.groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("e"))
    return a.select("l_returnflag", (F.abs(F.col("a") - F.col("e")) <= F.col("e") * 0.1).alias("close"))


@simple("op_udf", "SELECT vec_id, true AS same FROM embeddings", "embeddings")
def _udf(e):
    """Vector functions in Arrow against the same by built-in array functions."""
    from layerflow.functions.vectors import vec_dot

    exact = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", (F.abs(vec_dot("embedding", "embedding") - exact) < 1e-9).alias("same"))


@simple("op_udtf", "SELECT n_nationkey AS vid, CAST(unnest(range(0, n_regionkey + 1)) AS INTEGER) AS k FROM nation", "nation")
def _udtf(n):
    from layerflow.functions.vectors import register

    register(n.sparkSession)
    n.createOrReplaceTempView("_udtf_nation")
    return n.sparkSession.sql("SELECT n_nationkey AS vid, t.k FROM _udtf_nation, LATERAL count_up(n_regionkey) t")


@simple("op_sql_surface", "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity > 10 GROUP BY 1", "lineitem")
def _sql(x):
    x.createOrReplaceTempView("_surface_lineitem")
    return x.sparkSession.sql("SELECT l_returnflag, count(*) AS n FROM _surface_lineitem WHERE l_quantity > 10 GROUP BY l_returnflag")
