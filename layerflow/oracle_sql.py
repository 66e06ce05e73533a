"""SQL that computes what the engine's queries return, written apart from them, for a checking database."""

from __future__ import annotations

N = "n AS (SELECT (SELECT count(*) FROM customer) AS nc, (SELECT count(*) FROM orders) AS no_, (SELECT count(*) FROM part) AS np, (SELECT count(*) FROM region) AS nr, (SELECT count(*) FROM nation) AS nn, (SELECT count(*) FROM supplier) AS ns, (SELECT count(*) FROM embeddings) AS ne, (SELECT count(*) FROM pages) AS ng, (SELECT count(*) FROM documents) AS nd)"


def _amount(c: str) -> str:
    return f"CAST(floor(abs(coalesce({c}, 0))) AS BIGINT)"


_VROWS = {
    "trade": f"""SELECT c_custkey AS vid, 'customer' AS kind, 0 AS k, {_amount("c_acctbal")} AS a FROM customer
        UNION ALL SELECT nc + o_orderkey, 'orders', 1, {_amount("o_totalprice")} FROM orders, n
        UNION ALL SELECT nc + no_ + p_partkey, 'part', 2, {_amount("p_retailprice")} FROM part, n
        UNION ALL SELECT nc + no_ + np + s_suppkey, 'supplier', 3, {_amount("s_acctbal")} FROM supplier, n""",
    "copurchase": f"SELECT p_partkey AS vid, 'part' AS kind, p_size AS k, {_amount('p_retailprice')} AS a FROM part",
    "session": f"SELECT event_id AS vid, event_type AS kind, hour(ts) AS k, {_amount('value')} AS a FROM events",
    "geo": """SELECT CAST(r_regionkey AS BIGINT) AS vid, 'region' AS kind, 0 AS k, CAST(r_regionkey AS BIGINT) AS a FROM region
        UNION ALL SELECT nr + n_nationkey, 'nation', 1, n_nationkey FROM nation, n
        UNION ALL SELECT nr + nn + c_custkey, 'customer', 2, c_custkey FROM customer, n
        UNION ALL SELECT nr + nn + nc + s_suppkey, 'supplier', 3, s_suppkey FROM supplier, n""",
    "embgraph": "SELECT vec_id AS vid, 'vector' AS kind, 0 AS k, 0 AS a FROM embeddings",
}
_VROWS["isolated"] = _VROWS["geo"] + " UNION ALL SELECT nr + nn + nc + ns + item_id, 'benchmark', 4, item_id FROM benchmark, n"

_EDGES = {
    "trade": """one AS (SELECT o_custkey AS src, nc + o_orderkey AS dst FROM orders, n
        UNION ALL SELECT nc + l_orderkey, nc + no_ + l_partkey FROM lineitem, n
        UNION ALL SELECT nc + no_ + l_partkey, nc + no_ + np + l_suppkey FROM lineitem, n),
        edges AS (SELECT DISTINCT src, dst FROM (SELECT src, dst FROM one UNION ALL SELECT dst, src FROM one))""",
    "embgraph": "edges AS (SELECT DISTINCT l_partkey % ne AS src, (31 * l_orderkey + l_suppkey) % ne AS dst FROM lineitem, n WHERE l_returnflag = 'R' AND l_linenumber = 1)",
    "copurchase": "edges AS (SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_partkey <> b.l_partkey)",
    "session": "edges AS (SELECT src, dst FROM (SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL)",
    "links": """found AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS name FROM pages),
        targets AS (SELECT name, ng + row_number() OVER (ORDER BY name) - 1 AS vid FROM (SELECT DISTINCT name FROM found), n),
        edges AS (SELECT DISTINCT page_id AS src, vid AS dst FROM found JOIN targets USING (name))""",
    "hubs": """langs AS (SELECT name, nd + row_number() OVER (ORDER BY name) - 1 AS vid FROM (SELECT DISTINCT lang AS name FROM documents WHERE lang IS NOT NULL), n),
        sources AS (SELECT name, nd + (SELECT count(*) FROM langs) + row_number() OVER (ORDER BY name) - 1 AS vid FROM (SELECT DISTINCT source AS name FROM documents WHERE source IS NOT NULL), n),
        edges AS (SELECT DISTINCT doc_id AS src, vid AS dst FROM documents JOIN langs ON lang = name UNION SELECT doc_id, vid FROM documents JOIN sources ON source = name)""",
    "turns": "ranked AS (SELECT row_number() OVER (ORDER BY conv_id, turn) - 1 AS pos, conv_id, turn FROM conversations), edges AS (SELECT src, dst FROM (SELECT pos AS src, lead(pos) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM ranked) WHERE dst IS NOT NULL)",
    "geo": "edges AS (SELECT nr + n_nationkey AS src, CAST(n_regionkey AS BIGINT) AS dst FROM nation, n UNION SELECT nr + nn + c_custkey, nr + c_nationkey FROM customer, n UNION SELECT nr + nn + nc + s_suppkey, nr + s_nationkey FROM supplier, n)",
    "knn": """qv AS (SELECT vec_id, generate_subscripts(embedding, 1) AS i, CAST(floor(CAST(unnest(embedding) AS DOUBLE) * 65536) AS BIGINT) AS q FROM embeddings),
        dots AS (SELECT a.vec_id AS src, b.vec_id AS dst, sum(a.q * b.q) AS s FROM qv a JOIN qv b ON a.i = b.i AND a.vec_id <> b.vec_id GROUP BY 1, 2),
        edges AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY s DESC, dst) AS r FROM dots) WHERE r <= 5)""",
}
_EDGES["isolated"] = _EDGES["geo"]

BASE = ["k + 1", "a % 1000", "(a // 1000) % 100", "vid % 97", "(vid * 31 + 7) % 101", "(vid * 17 + 3) % 89", "(a * 7 + vid) % 113", "50"]


def graph(name: str, features: bool = False) -> str:
    """CTEs n, edges, vertices (vid, kind) and, if asked for, h (vid, i, q)."""
    parts = [N, _EDGES[name]]
    if name in _VROWS:
        parts += [f"vrows AS ({_VROWS[name]})", "vertices AS (SELECT vid, kind FROM vrows)"]
    if features:
        if name == "embgraph":
            parts.append("h AS (SELECT vec_id AS vid, CAST(generate_subscripts(embedding, 1) - 1 AS INTEGER) AS i, CAST(floor(CAST(unnest(embedding) AS DOUBLE) * 65536) AS BIGINT) AS q FROM embeddings)")
        else:
            parts.append("h AS (" + " UNION ALL ".join(f"SELECT vid, {i} AS i, CAST({e} AS BIGINT) AS q FROM vrows" for i, e in enumerate(BASE)) + ")")
    return ", ".join(parts)


def aggregated(h: str, out: str, d: int, agg: str, edges: str = "edges") -> str:
    """CTE ``out`` (vid, i, q): h aggregated over in-edges of every vertex."""
    fn = {"sum": "sum", "mean": "sum", "max": "max", "min": "min", "count": "count"}[agg]
    value = "CASE WHEN g.n IS NULL THEN 0 ELSE " + ("(g.s - ((g.s % g.n) + g.n) % g.n) // g.n" if agg == "mean" else "g.s") + " END"
    return f"""{out}_g AS (SELECT dst, i, CAST({fn}(q) AS BIGINT) AS s, count(*) AS n FROM {edges} JOIN {h} ON src = vid GROUP BY dst, i),
        {out} AS (SELECT v.vid, CAST(r.i AS INTEGER) AS i, CAST({value} AS BIGINT) AS q FROM vertices v CROSS JOIN (SELECT unnest(range(0, {d})) AS i) r LEFT JOIN {out}_g g ON g.dst = v.vid AND g.i = r.i)"""


def mapped(x: str, out: str, d: int, o: int, layer: int) -> str:
    """CTE ``out`` (vid, i, q): x times the lattice weights of a layer number."""
    return f"""{out} AS (SELECT vid, w.j AS i, CAST(sum(q * w.w) AS BIGINT) AS q FROM {x} x JOIN (SELECT CAST(a.i AS INTEGER) AS i, CAST(b.j AS INTEGER) AS j, ((31 * a.i + 17 * b.j + 7 * {layer}) % 13) - 6 AS w
        FROM (SELECT unnest(range(0, {d})) AS i) a, (SELECT unnest(range(0, {o})) AS j) b) w ON w.i = x.i GROUP BY vid, w.j)"""


def finished(y: str, out: str, relu: bool, shift: int | None) -> str:
    v = "greatest(q, 0)" if relu else "q"
    return f"{out} AS (SELECT vid, i, CAST(" + (f"floor({v} / {float(1 << shift)})" if shift else v) + f" AS BIGINT) AS q FROM {y})"


def two_layers(kind: str, d: int, hidden: int = 8, classes: int = 4, layers: int = 2, edges: str = "edges", shift: int = 4, prefix: str = "") -> tuple[str, str]:
    """CTEs of a model over h, all named with the prefix, and the name of the last one."""
    parts, h, widths = [], "h", [d, *[hidden] * (layers - 1), classes]
    if kind == "sgc":
        for n in range(layers):
            parts.append(aggregated(h, f"{prefix}x{n}", d, "mean", edges))
            h = f"{prefix}x{n}"
        return ", ".join([*parts, mapped(h, "out_", d, classes, 0)]), "out_"
    for n in range(layers):
        a, b, last = widths[n], widths[n + 1], n == layers - 1
        end = (False, None) if last else (True, shift)
        if kind == "graphconv":
            parts += [aggregated(h, f"{prefix}x{n}", a, "mean", edges), mapped(f"{prefix}x{n}", f"{prefix}y{n}", a, b, 3 * n), finished(f"{prefix}y{n}", f"{prefix}z{n}", *end)]
        elif kind == "sage":
            parts += [aggregated(h, f"{prefix}x{n}", a, "mean", edges), mapped(h, f"{prefix}p{n}", a, b, 3 * n), mapped(f"{prefix}x{n}", f"{prefix}q{n}", a, b, 3 * n + 1)]
            parts += [f"{prefix}y{n} AS (SELECT p.vid, p.i, p.q + r.q AS q FROM {prefix}p{n} p JOIN {prefix}q{n} r USING (vid, i))", finished(f"{prefix}y{n}", f"{prefix}z{n}", *end)]
        elif kind == "gin":
            parts += [aggregated(h, f"{prefix}x{n}", a, "sum", edges), f"{prefix}m{n} AS (SELECT p.vid, p.i, p.q + r.q AS q FROM {h} p JOIN {prefix}x{n} r USING (vid, i))"]
            parts += [mapped(f"{prefix}m{n}", f"{prefix}s{n}", a, hidden, 3 * n), finished(f"{prefix}s{n}", f"{prefix}t{n}", True, end[1]), mapped(f"{prefix}t{n}", f"{prefix}y{n}", hidden, b, 3 * n + 1), finished(f"{prefix}y{n}", f"{prefix}z{n}", *end)]
        h = f"{prefix}z{n}"
    return ", ".join(parts), h


DEGREES = "degrees AS (SELECT v.vid, coalesce(i.n, 0) AS d_in, coalesce(o.n, 0) AS d_out FROM vertices v LEFT JOIN (SELECT dst, count(*) AS n FROM edges GROUP BY dst) i ON i.dst = v.vid LEFT JOIN (SELECT src, count(*) AS n FROM edges GROUP BY src) o ON o.src = v.vid)"
_SCORES = """din AS (SELECT dst, count(*) AS d FROM edges GROUP BY dst),
    gains AS (SELECT src, CAST(sum(1099511627776 // d) AS BIGINT) AS s, count(*) AS n FROM edges JOIN din USING (dst) GROUP BY src)"""
ORDERS = {
    "original": "pos AS (SELECT vid, row_number() OVER (ORDER BY vid) - 1 AS pos FROM vertices)",
    "random": "pos AS (SELECT vid, row_number() OVER (ORDER BY md5('0:' || CAST(vid AS VARCHAR)), vid) - 1 AS pos FROM vertices)",
    "yield": _SCORES + ", scores AS (SELECT v.vid, coalesce(s // n, 0) AS score FROM vertices v LEFT JOIN gains ON src = v.vid), pos AS (SELECT vid, score, row_number() OVER (ORDER BY score DESC, vid) - 1 AS pos FROM scores)",
    "gain": _SCORES + ", scores AS (SELECT v.vid, coalesce(s, 0) AS score FROM vertices v LEFT JOIN gains ON src = v.vid), pos AS (SELECT vid, score, row_number() OVER (ORDER BY score DESC, vid) - 1 AS pos FROM scores)",
    "degree_in": DEGREES + ", pos AS (SELECT vid, row_number() OVER (ORDER BY d_in, vid) - 1 AS pos FROM degrees)",
    "degree_out": DEGREES + ", pos AS (SELECT vid, row_number() OVER (ORDER BY d_out DESC, vid) - 1 AS pos FROM degrees)",
}
SPANS = "spans AS (SELECT dst AS vid, min(p.pos) AS first, max(p.pos) AS last FROM edges JOIN pos p ON p.vid = src GROUP BY dst)"


def events(rows: int) -> str:
    """CTE ev (chunk, opened, closed)."""
    return f"""{SPANS}, ev AS (SELECT c.chunk, coalesce(o.n, 0) AS opened, coalesce(l.n, 0) AS closed FROM (SELECT DISTINCT pos // {rows} AS chunk FROM pos) c
        LEFT JOIN (SELECT first // {rows} AS chunk, count(*) AS n FROM spans GROUP BY 1) o USING (chunk) LEFT JOIN (SELECT last // {rows} AS chunk, count(*) AS n FROM spans GROUP BY 1) l USING (chunk))"""


def select(ctes: str, query: str) -> str:
    return f"WITH {ctes} {query}"
