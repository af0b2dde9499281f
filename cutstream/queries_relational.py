"""Queries that cover the relational operators the engine is made of, on graph tables and plain data."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from cutstream.functions.columns import mix31, mix31_sql
from cutstream.operators import measures as M
from cutstream.operators.stream_order import degrees
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph
from cutstream.queries_graph import edge_cte, graph_cte
from cutstream.sources import graphs as G

_mix = lambda c, s=0: mix31_sql(f"CAST({c} AS BIGINT)", s, "duckdb")


def _t(s, d, name):
    return G.load_table(s, d, name)


def _e(s, d, name="userprop"):
    return G.edges(s, d, name)


def _edges_sql(name="userprop"):
    return f"WITH {edge_cte(name)} "


def project_canonical(s, d):
    return G.canonical_edge(_t(s, d, "lineitem").select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b"), F.col("l_quantity").alias("weight"))).groupBy("src").agg(F.sum("weight").alias("w"), F.count("*").alias("n"))


def filter_loops(s, d):
    return G.drop_loops(G.canonical_edge(G.order_er(s, d))).agg(F.count("*").alias("n"))


def pushdown(s, d):
    """One buffer's edges by a predicate that reaches the scan: orders of a month."""
    o = _t(s, d, "orders").where((F.col("o_orderdate") >= "1995-01-01") & (F.col("o_orderdate") < "1995-02-01"))
    return o.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def _joined(hint):
    def run(s, d):
        g = Graph.load(s, d, "orderpart")
        return M.attach_blocks(g.edges, E.place_hash(g, 8), hint, g.n).groupBy("bi", "bj").agg(F.count("*").alias("n"))

    return run


def nested_loop(s, d):
    """Pairs of labels' mean vectors nearer than a bound: a small theta join."""
    v = _t(s, d, "embeddings").select("vec_id", "label", F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    m = v.groupBy("label").agg(F.round(F.avg("x"), 6).alias("x"), F.round(F.avg("y"), 6).alias("y"))
    a, b = m.select(*[F.col(c).alias(f"a_{c}") for c in m.columns]), m.select(*[F.col(c).alias(f"b_{c}") for c in m.columns])
    return a.join(F.broadcast(b), (F.col("a_label") < F.col("b_label")) & (F.abs(F.col("a_x") - F.col("b_x")) + F.abs(F.col("a_y") - F.col("b_y")) < 0.03)).select("a_label", "b_label")


def theta(s, d):
    """Pairs of blocks, lighter one first."""
    g = Graph.load(s, d, "fkforest")
    b = M.block_load(g.nodes, E.place_hash(g, 8))
    return b.select(F.col("block").alias("light"), F.col("load").alias("l1")).join(F.broadcast(b.select(F.col("block").alias("heavy"), F.col("load").alias("l2"))), F.col("l1") < F.col("l2")).select("light", "heavy", (F.col("l2") - F.col("l1")).alias("gap"))


def range_join(s, d):
    """Neighbours by grid cells, counted by degree."""
    return _e(s, d, "customer_rgg_random").select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))


def asof(s, d):
    """The latest earlier event of the same user that was a purchase, for every event: union and a filled window."""
    ev = _t(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return ev.withColumn("before", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)).select("event_id", "before")


def interval_join(s, d):
    """Pairs of a user's events within ten minutes: equi-join on user and time bucket, then the exact bound."""
    ev = _t(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    width = 600_000_000
    a = ev.withColumn("bucket", F.floor(F.col("t") / width))
    b = ev.select(F.col("event_id").alias("other"), F.col("user_id"), F.col("t").alias("u"), F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) - 1)).alias("bucket"))
    return a.join(b, ["user_id", "bucket"]).where((F.col("u") > F.col("t")) & (F.col("u") - F.col("t") <= width)).groupBy("user_id").agg(F.count("*").alias("pairs"))


def semi_induced(s, d):
    """Edges inside the vertices of three neighbours or more: two semi-joins."""
    g = Graph.load(s, d, "docline")
    keep = degrees(g.edges).where("degree >= 3").select("pos")
    e = g.edges.join(keep.withColumnRenamed("pos", "src"), "src", "left_semi").join(keep.withColumnRenamed("pos", "dst"), "dst", "left_semi")
    return e.select("src", "dst")


def anti_unassigned(s, d):
    """Orders without lines, which no edge of the order graph places."""
    li = _t(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return _t(s, d, "orders").join(li, "o_orderkey", "left_anti").select("o_orderkey")


def self_join_pairs(s, d):
    return _e(s, d, "cosession").groupBy("src").agg(F.count("*").alias("n"), F.sum("weight").alias("w"))


def full_outer_audit(s, d):
    """Customers and the keys that orders name, on both sides."""
    o = _t(s, d, "orders").select(F.col("o_custkey").alias("k")).distinct().withColumn("o", F.lit(1))
    c = _t(s, d, "customer").select(F.col("c_custkey").alias("k")).withColumn("c", F.lit(1))
    return o.join(c, "k", "full_outer").groupBy(F.col("o").isNotNull().alias("ordered"), F.col("c").isNotNull().alias("known")).agg(F.count("*").alias("n"))


def lateral_neighbours(s, d):
    """Half-edges from neighbour lists, by LATERAL VIEW."""
    _e(s, d, "docline").createOrReplaceTempView("edges_docline")
    return s.sql("SELECT v, count(*) AS degree, sum(w) AS w FROM (SELECT x.v, x.w FROM edges_docline LATERAL VIEW explode(array(named_struct('v', src, 'w', weight), named_struct('v', dst, 'w', weight))) t AS x) GROUP BY v")


def left_ghost(s, d):
    """Orders with and without lines of their own."""
    li = _t(s, d, "lineitem").select("l_orderkey").distinct()
    return _t(s, d, "orders").join(li, F.col("o_orderkey") == F.col("l_orderkey"), "left").groupBy(F.col("l_orderkey").isNull().alias("bare")).agg(F.count("*").alias("n"))


def cross_tau(s, d):
    """Share of parts of at most each size."""
    taus = s.createDataFrame([(10,), (20,), (40,)], "tau int")
    return _t(s, d, "part").crossJoin(F.broadcast(taus)).groupBy("tau").agg(F.count_if(F.col("p_size") <= F.col("tau")).alias("n"))


def multiway_fk(s, d):
    t = lambda x: _t(s, d, x)
    j = t("region").join(t("nation"), F.expr("r_regionkey = n_regionkey")).join(t("customer"), F.expr("n_nationkey = c_nationkey")).join(t("orders"), F.expr("c_custkey = o_custkey")).join(t("lineitem"), F.expr("o_orderkey = l_orderkey"))
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


def parallel_edges(s, d):
    return _e(s, d, "copurchase").groupBy("weight").agg(F.count("*").alias("n"))


def adjacency(s, d):
    half = _e(s, d, "docline").select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("o")), F.struct(F.col("dst").alias("v"), F.col("src").alias("o")))).alias("x")).select("x.*")
    return half.groupBy("v").agg(F.array_join(F.array_sort(F.collect_list("o")), ",").alias("nbrs"))


def agg_distinct(s, d):
    return _t(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"))


def agg_approx(s, d):
    deg = _e(s, d, "userprop").select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").alias("d"))
    return deg.agg(F.approx_count_distinct("v").alias("vertices"), F.percentile_approx("d", F.array(F.lit(0.5), F.lit(0.9))).alias("degrees"))


def argmax(s, d):
    return _t(s, d, "lineitem").groupBy("l_suppkey").agg(F.max(F.struct("l_quantity", (-F.col("l_orderkey")).alias("o"), (-F.col("l_linenumber")).alias("l"))).alias("x")).select("l_suppkey", (-F.col("x.o")).alias("orderkey"), F.col("x.l_quantity").alias("quantity"))


def grouping_sets(s, d):
    _t(s, d, "orders").createOrReplaceTempView("orders_v")
    return s.sql("SELECT o_orderstatus, o_orderpriority, grouping_id(o_orderstatus, o_orderpriority) AS gid, count(*) AS n FROM orders_v GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())")


def cube(s, d):
    return _t(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def rollup(s, d):
    return _t(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def pivot(s, d):
    return _t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).fillna(0)


def geomean(s, d):
    return _t(s, d, "part").groupBy("p_brand").agg(F.round(F.exp(F.avg(F.log("p_retailprice"))), 6).alias("geomean"))


def filtered_agg(s, d):
    return _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("many"), F.expr("sum(l_quantity) FILTER (WHERE l_discount > 0.05)").alias("discounted"))


def checksum(s, d):
    """Order-free checksum of the hash placement."""
    g = Graph.load(s, d, "fkforest")
    return E.place_hash(g, 32).agg(F.bit_xor(mix31("pos * 32 + block", 9)).alias("x"))


def having(s, d):
    return _t(s, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).where("n > 40")


def row_number(s, d):
    return _t(s, d, "customer").select("c_custkey", F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")).alias("r"))


def rank(s, d):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return _t(s, d, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"))


def lead_lag(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return _t(s, d, "conversations").select("conv_id", "turn", F.lead("role").over(w).alias("after"), F.lag("turn").over(w).alias("before"))


def running_sum(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return _t(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("total"))


def partition_max(s, d):
    return _t(s, d, "part").select("p_partkey", F.round(F.col("p_retailprice") / F.max("p_retailprice").over(Window.partitionBy("p_brand")), 6).alias("ratio"))


def ntile(s, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return _t(s, d, "customer").select("c_custkey", F.ntile(4).over(w).alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


def range_frame(s, d):
    """Events of the same user in the hour before."""
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return _t(s, d, "events").select("event_id", F.count("*").over(w).alias("n"))


def first_last(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _t(s, d, "events").select("user_id", F.first("event_id").over(w).alias("f"), F.last("event_id").over(w).alias("l")).distinct()


def sort_natural(s, d):
    """Vertex order inside each range of positions."""
    g = Graph.load(s, d, "docline")
    return g.nodes.repartitionByRange(4, "pos").sortWithinPartitions("pos").select("pos", "key")


def topk(s, d):
    return _e(s, d, "tradeflow").orderBy(F.desc("weight"), "src", "dst").limit(10)


def topk_group(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(s, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey", "r")


def limit_offset(s, d):
    return _t(s, d, "part").orderBy("p_partkey").offset(64).limit(64).select("p_partkey", "p_brand")


def union(s, d):
    return G.clean(G.fkforest(s, d)).groupBy(F.floor(F.col("dst") / G.KIND).alias("kind")).agg(F.count("*").alias("n"))


def intersect(s, d):
    """Edges cut under 4 blocks as under 6."""
    g = Graph.load(s, d, "docline")
    cut = lambda k: g.edges.where(mix31("src") % k != mix31("dst") % k).select("src", "dst")
    return cut(4).intersect(cut(6))


def except_(s, d):
    """Vertices that two hash seeds place apart."""
    g = Graph.load(s, d, "docline")
    return E.place_hash(g, 4).select("pos", "block").exceptAll(E.place_hash(g, 4, 1).select("pos", "block"))


def distinct(s, d):
    return _t(s, d, "lineitem").select("l_orderkey", "l_partkey").distinct().groupBy("l_partkey").agg(F.count("*").alias("orders"))


def salted_agg(s, d):
    """Degrees of a skewed graph by a two-step sum over salts."""
    half = _e(s, d, "fkforest").select(F.explode(F.array("src", "dst")).alias("v"), F.pmod(F.xxhash64("src", "dst"), F.lit(8)).alias("salt"))
    return half.groupBy("v", "salt").agg(F.count("*").alias("n")).groupBy("v").agg(F.sum("n").alias("degree"))


def scalar_string(s, d):
    p = _t(s, d, "pages").select("page_id", "url")
    return p.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.lower(F.substring("url", 1, 4)).alias("scheme"), F.length("url").alias("n"), F.translate("url", "/", "|").alias("bars"), F.md5(F.col("url").cast("binary")).alias("md5"), F.size(F.split("url", "/")).alias("parts"))


def scalar_time(s, d):
    o = _t(s, d, "orders")
    return o.groupBy(F.date_trunc("month", "o_orderdate").alias("m")).agg(F.count("*").alias("n"), F.sum(F.datediff(F.lit("1998-12-31").cast("date"), F.to_date("o_orderdate"))).alias("days"))


def scalar_math(s, d):
    p = _t(s, d, "part")
    return p.select("p_partkey", F.pmod(F.col("p_partkey") - 50, F.lit(7)).alias("pm"), F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.ceil("p_retailprice").alias("up"), F.floor("p_retailprice").alias("down"), F.greatest("p_size", F.lit(20)).alias("big"), F.shiftleft("p_size", 2).alias("four"), F.round(F.pow(F.col("p_size").cast("double"), F.lit(1.5)), 6).alias("power"))


def scalar_array(s, d):
    o = _t(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_linenumber")).alias("a"))
    return o.select("l_orderkey", F.aggregate("a", F.lit(0), lambda x, y: x + y).alias("total"), F.size(F.filter("a", lambda x: x > 3)).alias("late"), F.array_join(F.transform("a", lambda x: (x * 2).cast("string")), ",").alias("twice"), F.size(F.array_distinct("a")).alias("distinct"), F.element_at("a", -1).alias("last"))


def scalar_map(s, d):
    """Loads by block as a map and back."""
    g = Graph.load(s, d, "fkforest")
    m = M.block_load(g.nodes, E.place_hash(g, 8)).agg(F.map_from_entries(F.collect_list(F.struct("block", "load"))).alias("m"))
    return m.select(F.explode(F.transform_values("m", lambda k, v: v * 2))).select(F.col("key").alias("block"), F.col("value").alias("twice"))


def scalar_json(s, d):
    ev = _t(s, d, "events")
    return ev.groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"), F.max(F.to_json(F.struct("event_type"))).alias("js"))


def message_hops(s, d):
    """Every vertex asks each neighbour once: questions that cross blocks, of all, under hash placement and ranges."""
    g = Graph.load(s, d, "docline")
    out = None
    for name, a in (("hash", E.place_hash(g, 8)), ("range", E.place_range(g, 8))):
        cross = M.attach_blocks(g.edges, a).agg((2 * F.count_if(F.col("bi") != F.col("bj"))).alias("messages"), (2 * F.count("*")).alias("hops")).select(F.lit(name).alias("alg"), "messages", "hops")
        out = cross if out is None else out.unionByName(cross)
    return out


_BLOCKS = lambda k, seed=0: f"CAST({_mix('pos', seed)} % {k} AS INTEGER)"
_G = graph_cte("docline")
_JOINED = f"WITH {graph_cte('orderpart')} SELECT CAST({_mix('src')} % 8 AS INTEGER) AS bi, CAST({_mix('dst')} % 8 AS INTEGER) AS bj, count(*) AS n FROM g GROUP BY 1, 2"
_FULL = {
    "op_project_canonical": (project_canonical, "SELECT least(l_partkey, l_suppkey) AS src, sum(l_quantity) AS w, count(*) AS n FROM lineitem GROUP BY 1"),
    "op_filter_loops": (filter_loops, f"SELECT count(*) AS n FROM orders WHERE o_custkey <> {_mix('o_orderkey', 4)} % (SELECT max(o_custkey) + 1 FROM orders)"),
    "op_pushdown": (pushdown, "SELECT o_orderpriority, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders WHERE o_orderdate >= '1995-01-01' AND o_orderdate < '1995-02-01' GROUP BY 1"),
    "op_join_broadcast": (_joined("broadcast"), _JOINED),
    "op_join_sortmerge": (_joined("merge"), _JOINED),
    "op_join_shuffle_hash": (_joined("shuffle_hash"), _JOINED),
    "op_join_nested_loop": (nested_loop, "WITH m AS (SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS x, round(avg(CAST(embedding[2] AS DOUBLE)), 6) AS y FROM embeddings GROUP BY 1) SELECT a.label AS a_label, b.label AS b_label FROM m a JOIN m b ON a.label < b.label AND abs(a.x - b.x) + abs(a.y - b.y) < 0.03"),
    "op_join_theta": (theta, f"WITH {graph_cte('fkforest')}, l AS (SELECT {_BLOCKS(8)} AS block, CAST(count(*) AS DOUBLE) AS load FROM v GROUP BY 1) SELECT a.block AS light, b.block AS heavy, b.load - a.load AS gap FROM l a JOIN l b ON a.load < b.load"),
    "op_join_range": (range_join, f"WITH {edge_cte('customer_rgg_random')} SELECT degree, count(*) AS n FROM (SELECT v, count(*) AS degree FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v) GROUP BY degree"),
    "op_join_asof": (asof, "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events"),
    "op_join_interval": (interval_join, "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE GROUP BY 1"),
    "op_semi_induced": (semi_induced, f"WITH {_G}, ends AS (SELECT src AS v FROM g UNION ALL SELECT dst FROM g), keep AS (SELECT v FROM ends GROUP BY v HAVING count(*) >= 3) SELECT src, dst FROM g WHERE src IN (SELECT v FROM keep) AND dst IN (SELECT v FROM keep)"),
    "op_anti_unassigned": (anti_unassigned, "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)"),
    "op_self_join_pairs": (self_join_pairs, f"{_edges_sql('cosession')} SELECT src, count(*) AS n, sum(weight) AS w FROM e GROUP BY src"),
    "op_full_outer_audit": (full_outer_audit, "SELECT o.k IS NOT NULL AS ordered, c.k IS NOT NULL AS known, count(*) AS n FROM (SELECT DISTINCT o_custkey AS k FROM orders) o FULL JOIN (SELECT c_custkey AS k FROM customer) c ON o.k = c.k GROUP BY 1, 2"),
    "op_lateral_neighbours": (lateral_neighbours, f"{_edges_sql('docline')} SELECT v, count(*) AS degree, sum(weight) AS w FROM (SELECT src AS v, weight FROM e UNION ALL SELECT dst, weight FROM e) GROUP BY v"),
    "op_left_ghost": (left_ghost, "SELECT l_orderkey IS NULL AS bare, count(*) AS n FROM orders LEFT JOIN (SELECT DISTINCT l_orderkey FROM lineitem) ON o_orderkey = l_orderkey GROUP BY 1"),
    "op_cross_tau": (cross_tau, "SELECT tau, count(*) FILTER (WHERE p_size <= tau) AS n FROM part, (VALUES (10), (20), (40)) t(tau) GROUP BY tau"),
    "op_multiway_fk": (multiway_fk, "SELECT r_name, count(*) AS n, sum(l_quantity) AS quantity FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON n_nationkey = c_nationkey JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"),
    "op_agg_parallel_edges": (parallel_edges, f"{_edges_sql('copurchase')} SELECT weight, count(*) AS n FROM e GROUP BY 1"),
    "op_agg_adjacency": (adjacency, f"{_edges_sql('docline')} SELECT v, string_agg(CAST(o AS VARCHAR), ',' ORDER BY o) AS nbrs FROM (SELECT src AS v, dst AS o FROM e UNION ALL SELECT dst, src FROM e) GROUP BY v"),
    "op_agg_distinct": (agg_distinct, "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1"),
    "op_agg_approx": (agg_approx, None),
    "op_agg_argmax": (argmax, "SELECT l_suppkey, l_orderkey AS orderkey, l_quantity AS quantity FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_quantity DESC, l_orderkey, l_linenumber) AS r FROM lineitem) WHERE r = 1"),
    "op_grouping_sets": (grouping_sets, "SELECT o_orderstatus, o_orderpriority, CAST(grouping(o_orderstatus, o_orderpriority) AS BIGINT) AS gid, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())"),
    "op_cube": (cube, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    "op_rollup": (rollup, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "op_pivot": (pivot, "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY 1"),
    "op_geomean": (geomean, "SELECT p_brand, round(exp(avg(ln(p_retailprice))), 6) AS geomean FROM part GROUP BY 1"),
    "op_filtered_agg": (filtered_agg, "SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS many, sum(l_quantity) FILTER (WHERE l_discount > 0.05) AS discounted FROM lineitem GROUP BY 1"),
    "op_checksum": (checksum, f"WITH {graph_cte('fkforest')}, p AS (SELECT pos, {_BLOCKS(32)} AS block FROM v) SELECT bit_xor({_mix('pos * 32 + block', 9)}) AS x FROM p"),
    "op_having": (having, "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 40"),
    "op_win_row_number": (row_number, "SELECT c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer"),
    "op_win_rank": (rank, "SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)"),
    "op_win_lead_lag": (lead_lag, "SELECT conv_id, turn, lead(role) OVER w AS after, lag(turn) OVER w AS before FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)"),
    "op_win_running_sum": (running_sum, "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS total FROM orders"),
    "op_win_partition_max": (partition_max, "SELECT p_partkey, round(p_retailprice / max(p_retailprice) OVER (PARTITION BY p_brand), 6) AS ratio FROM part"),
    "op_win_ntile": (ntile, "SELECT c_custkey, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"),
    "op_win_range": (range_frame, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events"),
    "op_win_first_last": (first_last, "SELECT user_id, arg_min(event_id, (ts, event_id)) AS f, arg_max(event_id, (ts, event_id)) AS l FROM events GROUP BY 1"),
    "op_sort_natural": (sort_natural, f"WITH {_G} SELECT pos, key FROM v"),
    "op_topk": (topk, f"{_edges_sql('tradeflow')} SELECT src, dst, weight FROM e ORDER BY weight DESC, src, dst LIMIT 10"),
    "op_topk_group": (topk_group, "SELECT o_custkey, o_orderkey, r FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2"),
    "op_limit_offset": (limit_offset, "SELECT p_partkey, p_brand FROM part ORDER BY p_partkey LIMIT 64 OFFSET 64"),
    "op_union": (union, f"{_edges_sql('fkforest')} SELECT dst // 1000000000000 AS kind, count(*) AS n FROM e GROUP BY 1"),
    "op_intersect": (intersect, f"WITH {_G} SELECT src, dst FROM g WHERE {_mix('src')} % 4 <> {_mix('dst')} % 4 AND {_mix('src')} % 6 <> {_mix('dst')} % 6"),
    "op_except": (except_, f"WITH {_G} SELECT pos, {_BLOCKS(4)} AS block FROM v WHERE {_BLOCKS(4)} <> {_BLOCKS(4, 1)}"),
    "op_distinct": (distinct, "SELECT l_partkey, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1"),
    "op_salted_agg": (salted_agg, f"{_edges_sql('fkforest')} SELECT v, count(*) AS degree FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v"),
    "op_scalar_string": (scalar_string, "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, lower(substr(url, 1, 4)) AS scheme, CAST(length(url) AS INTEGER) AS n, replace(url, '/', '|') AS bars, md5(url) AS md5, CAST(len(string_split(url, '/')) AS INTEGER) AS parts FROM pages"),
    "op_scalar_time": (scalar_time, "SELECT CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS m, count(*) AS n, CAST(sum(date_diff('day', CAST(o_orderdate AS DATE), DATE '1998-12-31')) AS BIGINT) AS days FROM orders GROUP BY 1"),
    "op_scalar_math": (scalar_math, "SELECT p_partkey, (p_partkey - 50) % 7 + CASE WHEN (p_partkey - 50) % 7 < 0 THEN 7 ELSE 0 END AS pm, round(sqrt(p_retailprice), 6) AS root, CAST(ceil(p_retailprice) AS BIGINT) AS up, CAST(floor(p_retailprice) AS BIGINT) AS down, greatest(p_size, 20) AS big, p_size * 4 AS four, round(pow(CAST(p_size AS DOUBLE), 1.5), 6) AS power FROM part"),
    "op_scalar_array": (scalar_array, "WITH a AS (SELECT l_orderkey, list(l_linenumber ORDER BY l_linenumber) AS a FROM lineitem GROUP BY 1) SELECT l_orderkey, CAST(list_sum(a) AS INTEGER) AS total, CAST(len(list_filter(a, lambda x: x > 3)) AS INTEGER) AS late, array_to_string(list_transform(a, lambda x: CAST(x * 2 AS VARCHAR)), ',') AS twice, CAST(len(list_distinct(a)) AS INTEGER) AS distinct, a[-1] AS last FROM a"),
    "op_scalar_map": (scalar_map, f"WITH {graph_cte('fkforest')} SELECT {_BLOCKS(8)} AS block, CAST(count(*) * 2 AS DOUBLE) AS twice FROM v GROUP BY 1"),
    "op_scalar_json": (scalar_json, "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n, '{\"event_type\":\"' || max(event_type) || '\"}' AS js FROM events GROUP BY 1"),
    "op_message_hops": (message_hops, f"WITH {_G}, t AS (SELECT count(*) AS n FROM v) SELECT 'hash' AS alg, 2 * count(*) FILTER (WHERE {_mix('src')} % 8 <> {_mix('dst')} % 8) AS messages, 2 * count(*) AS hops FROM g UNION ALL SELECT 'range', 2 * count(*) FILTER (WHERE src * 8 // n <> dst * 8 // n), 2 * count(*) FROM g, t"),
}
QUERIES = {name: q for name, (q, _) in _FULL.items()}
ORACLES = {name: sql for name, (_, sql) in _FULL.items() if sql}
