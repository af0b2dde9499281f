"""Queries on the graphs themselves: edges, profile, vertex stream, buffers, edge classes."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from cutstream.functions.columns import M31, mix31_sql
from cutstream.operators import stream_order as S
from cutstream.plans.graph import Graph
from cutstream.sources import graphs as G

K = "1000000000000"
#: Raw edges (a, b, w) of each graph in SQL, over the same keys as sources.graphs.
RAW = {
    "copurchase": "SELECT x.p AS a, y.p AS b, 1.0 AS w FROM (SELECT DISTINCT l_orderkey o, l_partkey p FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey o, l_partkey p FROM lineitem) y ON x.o = y.o AND x.p < y.p",
    "orderpart": f"SELECT DISTINCT l_orderkey AS a, l_partkey + {K} AS b, 1.0 AS w FROM lineitem",
    "fkforest": f"SELECT n_regionkey AS a, n_nationkey + {K} AS b, 1.0 AS w FROM nation UNION ALL SELECT c_nationkey + {K}, c_custkey + 2 * {K}, 1.0 FROM customer UNION ALL SELECT o_custkey + 2 * {K}, o_orderkey + 3 * {K}, 1.0 FROM orders",
    "docline_star": "SELECT min(d) OVER (PARTITION BY line) AS a, d AS b, 1.0 AS w FROM l",
    "docline": """SELECT x.d AS a, y.d AS b, 1.0 AS w FROM (SELECT * FROM l JOIN (SELECT line FROM l GROUP BY line HAVING count(*) BETWEEN 2 AND 20) USING (line)) x
        JOIN l y ON x.line = y.line AND x.d < y.d""",
    "docsource": f"SELECT doc_id AS a, CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) + {K} AS b, 1.0 AS w FROM documents UNION ALL SELECT doc_id, ascii(lang) * 256 + ascii(substr(lang, 2, 1)) + 2 * {K}, 1.0 FROM documents",
    "weblink": """SELECT 'p:' || lpad(CAST(page_id AS VARCHAR), 12, '0') AS a, 't:' || t AS b, 1.0 AS w FROM (SELECT page_id, unnest(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))) AS t FROM pages)
        UNION ALL SELECT 'p:' || lpad(CAST(page_id AS VARCHAR), 12, '0'), 'h:' || regexp_extract(url, '^[a-z]+://([^/]+)', 1), 1.0 FROM pages""",
    "userprop": f"SELECT DISTINCT user_id AS a, CAST(json_extract(props, '$.k') AS BIGINT) + {K} AS b, 1.0 AS w FROM events",
    "userflow": "SELECT * FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b, 1.0 AS w FROM events) WHERE b IS NOT NULL",
    "cosession": "SELECT x.u AS a, y.u AS b, 1.0 AS w FROM (SELECT DISTINCT date_trunc('hour', ts) h, user_id u FROM events) x JOIN (SELECT DISTINCT date_trunc('hour', ts) h, user_id u FROM events) y ON x.h = y.h AND x.u < y.u",
    "convchain": "SELECT * FROM (SELECT conv_id * 10000 + turn AS a, lead(conv_id * 10000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b, 1.0 AS w FROM conversations) WHERE b IS NOT NULL",
    "tradeflow": "SELECT c_nationkey AS a, s_nationkey AS b, sum(l_quantity) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2",
    "benchleak": f"SELECT doc_id AS a, item_id + {K} AS b, 1.0 AS w FROM documents d JOIN benchmark i ON contains(d.text, i.text)",
    "grid": "SELECT id AS a, id + 1 AS b, 1.0 AS w FROM range(1024) t(id) WHERE id % 32 < 31 UNION ALL SELECT id, id + 32, 1.0 FROM range(1024) t(id) WHERE id < 32 * 31",
    "er": f"SELECT {mix31_sql('id', 3, 'duckdb')} % 1024 AS a, {mix31_sql('id', 4, 'duckdb')} % 1024 AS b, 1.0 AS w FROM range(4096) t(id)",
    "chords": f"SELECT id AS a, (id + 1) % 1024 AS b, 1.0 AS w FROM range(1024) t(id) UNION ALL SELECT id % 1024, CAST(floor(u * u * u * 1024) AS BIGINT), 1.0 FROM (SELECT id, {mix31_sql('id', 5, 'duckdb')} / {float(M31)} AS u FROM range(2048) t(id))",
    "knn": """SELECT a, b, s AS w FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS r FROM (
        SELECT x.vec_id AS a, y.vec_id AS b, round(list_dot_product(x.e, y.e) / (sqrt(list_dot_product(x.e, x.e)) * sqrt(list_dot_product(y.e, y.e))), 5) AS s
        FROM (SELECT vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) e FROM embeddings) x JOIN (SELECT vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) e FROM embeddings) y ON x.vec_id <> y.vec_id)) WHERE r <= 3""",
}
RAW["fkstar"] = RAW["fkforest"] + f" UNION ALL SELECT DISTINCT l_orderkey + 3 * {K}, l_suppkey + 4 * {K}, 1.0 FROM lineitem UNION ALL SELECT DISTINCT l_orderkey + 3 * {K}, l_partkey + 5 * {K}, 1.0 FROM lineitem"
_R = repr(0.55 * math.sqrt(math.log(1024) / 1024) * (0.55 * math.sqrt(math.log(1024) / 1024)))
_POINTS = f"SELECT id, {mix31_sql('id', 1, 'duckdb')} / {float(M31)} AS px, {mix31_sql('id', 2, 'duckdb')} / {float(M31)} AS py FROM range(1024) t(id)"
_NEAR = "SELECT p.id AS a, q.id AS b, 1.0 AS w FROM {0} p JOIN {0} q ON p.id < q.id AND (p.px - q.px) * (p.px - q.px) + (p.py - q.py) * (p.py - q.py) < CAST(" + _R + " AS DOUBLE)"
RAW["rgg_random"] = _NEAR.format(f"({_POINTS})")
RAW["rgg"] = _NEAR.format(f"(SELECT row_number() OVER (ORDER BY px, id) - 1 AS id, px, py FROM ({_POINTS}))")
#: The same kinds of graphs over given tables (sources.graphs.CARRIED).
_CUST = f"SELECT c_custkey AS id, (c_acctbal + 1000) / CAST(11000 AS DOUBLE) AS px, {mix31_sql('c_custkey', 2, 'duckdb')} / {float(M31)} AS py FROM customer WHERE c_custkey IS NOT NULL AND c_acctbal IS NOT NULL"
RAW["customer_rgg"] = RAW["customer_rgg_random"] = """SELECT p.id AS a, q.id AS b, 1.0 AS w FROM cell p JOIN (SELECT id, px, py, cx + i AS cx, cy + j AS cy FROM cell, (VALUES (-1), (0), (1)) x(i), (VALUES (-1), (0), (1)) y(j)) q
        ON p.cx = q.cx AND p.cy = q.cy AND p.id < q.id JOIN rad ON (p.px - q.px) * (p.px - q.px) + (p.py - q.py) * (p.py - q.py) < r * r"""
RAW["order_grid"] = "SELECT x.o_orderkey AS a, y.o_orderkey AS b, 1.0 AS w FROM (SELECT o_orderkey, unnest(CASE WHEN o_orderkey % w < w - 1 THEN [1, w] ELSE [w] END) AS step FROM orders, wide) x JOIN orders y ON y.o_orderkey = x.o_orderkey + x.step"
RAW["order_er"] = f"SELECT o_custkey AS a, {mix31_sql('o_orderkey', 4, 'duckdb')} % (SELECT max(o_custkey) + 1 FROM orders) AS b, 1.0 AS w FROM orders"
RAW["order_chords"] = f"SELECT c_custkey AS a, (c_custkey + 1) % (SELECT max(c_custkey) + 1 FROM customer) AS b, 1.0 AS w FROM customer UNION ALL SELECT o_custkey, CAST(floor(u * u * u * (SELECT max(c_custkey) + 1 FROM customer)) AS BIGINT), 1.0 FROM (SELECT o_custkey, {mix31_sql('o_orderkey', 5, 'duckdb')} / {float(M31)} AS u FROM orders)"
#: Leading common table expressions that some raw edges need.
PRELUDE = {"docline": "l AS (SELECT DISTINCT doc_id AS d, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20), "}
PRELUDE["docline_star"] = PRELUDE["docline"]
_CELLS = "rad AS (SELECT 0.55 * sqrt(ln(count(*)) / count(*)) AS r FROM pt), cell AS (SELECT pt.*, floor(px * c) AS cx, floor(py * c) AS cy FROM pt, (SELECT greatest(1, floor(1 / r)) AS c FROM rad)), "
PRELUDE["customer_rgg"] = f"cust AS ({_CUST}), pt AS (SELECT row_number() OVER (ORDER BY px, id) - 1 AS id, px, py FROM cust), {_CELLS}"
PRELUDE["customer_rgg_random"] = f"pt AS ({_CUST}), {_CELLS}"
PRELUDE["order_grid"] = "wide AS (SELECT CAST(floor(sqrt(max(o_orderkey) + 1)) AS BIGINT) AS w FROM orders), "


def edge_cte(name: str) -> str:
    """CTEs ending in e(src, dst, weight): clean edges over keys."""
    return f"{PRELUDE.get(name, '')}raw AS ({RAW[name]}), e AS (SELECT least(a, b) AS src, greatest(a, b) AS dst, CAST(sum(w) AS DOUBLE) AS weight FROM raw WHERE a <> b GROUP BY 1, 2)"


def graph_cte(name: str) -> str:
    """CTEs ending in v(pos, key) and g(src, dst, weight): unit edges between positions."""
    return f"{edge_cte(name)}, v AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS pos FROM (SELECT src AS key FROM e UNION SELECT dst FROM e)), g AS (SELECT least(x.pos, y.pos) AS src, greatest(x.pos, y.pos) AS dst, CAST(1 AS DOUBLE) AS weight FROM e JOIN v x ON e.src = x.key JOIN v y ON e.dst = y.key)"


PROFILED = ("docline", "fkforest", "convchain", "userprop", "rgg", "grid")


def graph_profile(spark, d):
    """Vertices, edges, largest and mean degree, density."""
    out = None
    for name in PROFILED:
        deg = G.edges(spark, d, name).select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").alias("d"))
        n = F.count("*")
        row = deg.agg(n.alias("n"), (F.sum("d") / 2).cast("long").alias("m"), F.max("d").alias("max_degree"), F.round(F.avg("d"), 6).alias("avg_degree"), F.round(F.sum("d") / (n * (n - 1)), 9).alias("density")).select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def vertex_stream(spark, d):
    a = S.adjacency(Graph.load(spark, d, "docline"), None)
    return a.select("pos", F.col("degree").cast("long").alias("degree"), F.coalesce(F.array_join(F.transform("nbrs", lambda x: x["pos"].cast("string")), ","), F.lit("")).alias("nbrs"))


def batches_fixed(spark, d):
    return S.assign_batches(Graph.load(spark, d, "docline").nodes, 64).groupBy("batch_id").agg(F.count("*").alias("vertices"))


def batches_budget(spark, d):
    return S.assign_batches_by_budget(Graph.load(spark, d, "docline"), 300).groupBy("batch_id").agg(F.count("*").alias("vertices"), F.sum("cost").alias("cost"))


def edge_classes(spark, d):
    return S.classify_edges(Graph.load(spark, d, "docline").edges, 64).groupBy("batch_id", "class").agg(F.count("*").alias("edges"), F.sum("w").alias("w"))


def op_classify(spark, d):
    return S.classify_edges(Graph.load(spark, d, "userprop").edges, 32).groupBy("class").agg(F.count("*").alias("edges"))


_CLASSES = "c AS (SELECT src // {0} AS batch_id, src AS pos, dst AS other, 'intra' AS class, weight AS w FROM g WHERE src // {0} = dst // {0} UNION ALL SELECT src // {0}, src, dst, 'forward', weight FROM g WHERE src // {0} <> dst // {0} UNION ALL SELECT dst // {0}, dst, src, 'backward', weight FROM g WHERE src // {0} <> dst // {0})"

QUERIES = {f"g_{name}": (lambda s, d, name=G.ON_TABLES.get(name, name): G.edges(s, d, name)) for name in G.BUILDERS} | {
    "graph_profile": graph_profile,
    "vertex_stream": vertex_stream,
    "batches_fixed": batches_fixed,
    "batches_budget": batches_budget,
    "edge_classes": edge_classes,
    "op_classify": op_classify,
}
_DEG = "h AS (SELECT src AS p, dst AS q FROM g UNION ALL SELECT dst, src FROM g), deg AS (SELECT p, count(*) AS d, string_agg(CAST(q AS VARCHAR), ',' ORDER BY q) AS s FROM h GROUP BY p)"
ORACLES = {f"g_{name}": f"WITH {edge_cte(G.ON_TABLES.get(name, name))} SELECT src, dst, weight FROM e" for name in G.BUILDERS} | {
    "graph_profile": " UNION ALL ".join(
        f"(WITH {edge_cte(n)}, deg AS (SELECT v, count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v) SELECT '{n}' AS graph, count(*) AS n, CAST(sum(d) / 2 AS BIGINT) AS m, max(d) AS max_degree, round(avg(d), 6) AS avg_degree, round(sum(d) / (count(*) * (count(*) - 1)), 9) AS density FROM deg)"
        for n in PROFILED
    ),
    "vertex_stream": f"WITH {graph_cte('docline')}, {_DEG} SELECT p AS pos, d AS degree, s AS nbrs FROM deg",
    "batches_fixed": f"WITH {graph_cte('docline')} SELECT pos // 64 AS batch_id, count(*) AS vertices FROM v GROUP BY 1",
    "batches_budget": f"WITH {graph_cte('docline')}, {_DEG}, s AS (SELECT p, 1 + d AS cost, sum(1 + d) OVER (ORDER BY p) - 1 - d AS before FROM deg) SELECT CAST(before // 300 AS BIGINT) AS batch_id, count(*) AS vertices, CAST(sum(cost) AS BIGINT) AS cost FROM s GROUP BY 1",
    "edge_classes": f"WITH {graph_cte('docline')}, {_CLASSES.format(64)} SELECT batch_id, class, count(*) AS edges, sum(w) AS w FROM c GROUP BY 1, 2",
    "op_classify": f"WITH {graph_cte('userprop')}, {_CLASSES.format(32)} SELECT class, count(*) AS edges FROM c GROUP BY 1",
}
