"""Graphs carried by the given tables, and generated ones: raw edges (a, b, weight) between node keys.

Keys of several kinds are told apart by `KIND` (kind * KIND + natural key), so that key order is the natural order of the
vertex stream. `clean` gives what all methods take: undirected simple edges (src, dst, weight), src < dst.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cutstream.functions.columns import M31, mix31
from cutstream.scratch import materialise

KIND = 10**12


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def canonical_edge(df: DataFrame, a: str = "a", b: str = "b", w: str = "weight") -> DataFrame:
    """Undirected pairs: the smaller key first."""
    return df.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"), F.col(w).cast("double").alias("weight"))


def drop_loops(edges: DataFrame) -> DataFrame:
    return edges.where("src <> dst")


def clean(raw: DataFrame, unit: bool = False) -> DataFrame:
    """Simple undirected edges: no loops, no null ends, parallel edges summed (or of weight 1)."""
    weight = F.lit(1.0) if unit else F.sum("weight")
    return drop_loops(canonical_edge(raw).dropna(subset=["src", "dst"])).groupBy("src", "dst").agg(weight.alias("weight"))


def pairs_within(df: DataFrame, group: str, item: str, cap: int | None = None) -> DataFrame:
    """Unordered pairs of distinct items of a group, (a, b, weight): one shuffle by group, then pairs row by row.

    Groups of over `cap` items, if given, are left out (a hub's pairs grow with its square).
    """
    sets = df.select(group, item).dropna().groupBy(group).agg(F.array_sort(F.collect_set(item)).alias("s")).where("size(s) > 1")
    if cap:
        sets = sets.where(F.size("s") <= cap)
    return sets.select("s", F.posexplode("s").alias("i", "a")).select("a", F.explode(F.slice("s", F.col("i") + 2, F.size("s"))).alias("b"), F.lit(1.0).alias("weight"))


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    """Parts bought in one order; weight: orders shared."""
    return pairs_within(load_table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def orderpart(spark: SparkSession, d: str) -> DataFrame:
    li = load_table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    return li.select(F.col("l_orderkey").alias("a"), (F.col("l_partkey") + KIND).alias("b"), F.lit(1.0).alias("weight"))


def _fk(df: DataFrame, kind_a: int, a: str, kind_b: int, b: str) -> DataFrame:
    return df.select((F.col(a).cast("long") + kind_a * KIND).alias("a"), (F.col(b).cast("long") + kind_b * KIND).alias("b"), F.lit(1.0).alias("weight"))


def fkforest(spark: SparkSession, d: str) -> DataFrame:
    """Region, nation, customer, order: a tree along foreign keys."""
    t = lambda x: load_table(spark, d, x)
    return _fk(t("nation"), 0, "n_regionkey", 1, "n_nationkey").unionByName(_fk(t("customer"), 1, "c_nationkey", 2, "c_custkey")).unionByName(_fk(t("orders"), 2, "o_custkey", 3, "o_orderkey"))


def fkstar(spark: SparkSession, d: str) -> DataFrame:
    li = load_table(spark, d, "lineitem")
    return fkforest(spark, d).unionByName(_fk(li.select("l_orderkey", "l_suppkey").distinct(), 3, "l_orderkey", 4, "l_suppkey")).unionByName(_fk(li.select("l_orderkey", "l_partkey").distinct(), 3, "l_orderkey", 5, "l_partkey"))


def docline(spark: SparkSession, d: str, least: int = 20, low: int = 2, high: int = 20) -> DataFrame:
    """Documents that share a line of at least `least` characters found in low to high documents."""
    lines = load_table(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= least)
    keyed = lines.select("doc_id", F.xxhash64("line").alias("h1"), F.crc32(F.col("line").cast("binary")).alias("h2")).distinct()
    few = keyed.groupBy("h1", "h2").agg(F.array_sort(F.collect_set("doc_id")).alias("s")).where(F.size("s").between(low, high))
    return few.select("s", F.posexplode("s").alias("i", "a")).select("a", F.explode(F.slice("s", F.col("i") + 2, F.size("s"))).alias("b"), F.lit(1.0).alias("weight"))


def docline_star(spark: SparkSession, d: str, least: int = 20) -> DataFrame:
    """Every line shared by documents, however many: each is linked to the smallest of them, so edges grow with the lines."""
    lines = load_table(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= least)
    keyed = lines.select("doc_id", F.xxhash64("line").alias("h1"), F.crc32(F.col("line").cast("binary")).alias("h2")).distinct()
    first = keyed.groupBy("h1", "h2").agg(F.min("doc_id").alias("a"), F.count("*").alias("n")).where("n > 1").select("h1", "h2", "a")
    return keyed.join(first, ["h1", "h2"]).select("a", F.col("doc_id").alias("b"), F.lit(1.0).alias("weight")).where("a <> b")


def docsource(spark: SparkSession, d: str) -> DataFrame:
    docs = load_table(spark, d, "documents")
    source = docs.select(F.col("doc_id").alias("a"), (F.regexp_extract("source", "([0-9]+)$", 1).cast("long") + KIND).alias("b"), F.lit(1.0).alias("weight"))
    lang = docs.select(F.col("doc_id").alias("a"), (F.ascii("lang") * 256 + F.ascii(F.substring("lang", 2, 1)) + 2 * KIND).alias("b"), F.lit(1.0).alias("weight"))
    return source.unionByName(lang)


def weblink(spark: SparkSession, d: str) -> DataFrame:
    """Pages and link targets, pages and their hosts; string keys."""
    pages = load_table(spark, d, "pages").select(F.concat(F.lit("p:"), F.lpad(F.col("page_id").cast("string"), 12, "0")).alias("a"), "url", "html")
    links = pages.select("a", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))).alias("t")).select("a", F.concat(F.lit("t:"), "t").alias("b"))
    hosts = pages.select("a", F.concat(F.lit("h:"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).alias("b"))
    return links.unionByName(hosts).withColumn("weight", F.lit(1.0))


def userprop(spark: SparkSession, d: str) -> DataFrame:
    ev = load_table(spark, d, "events").select("user_id", F.from_json("props", "k long").getField("k").alias("k")).dropna().distinct()
    return ev.select(F.col("user_id").alias("a"), (F.col("k") + KIND).alias("b"), F.lit(1.0).alias("weight"))


def userflow(spark: SparkSession, d: str) -> DataFrame:
    """Users whose events follow each other in time. Days are ordered apart; a day's last event joins the next day's first."""
    ev = load_table(spark, d, "events").select("ts", "event_id", "user_id", F.to_date("ts").alias("day"))
    inner = ev.select(F.col("user_id").alias("a"), F.lead("user_id").over(Window.partitionBy("day").orderBy("ts", "event_id")).alias("b"))
    ends = ev.groupBy("day").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("first"), F.max(F.struct("ts", "event_id", "user_id")).alias("last"))
    over = ends.select(F.col("last.user_id").alias("a"), F.lead("first.user_id").over(Window.orderBy("day")).alias("b"))  # a row a day
    return inner.unionByName(over).dropna().withColumn("weight", F.lit(1.0))


def pair_counts(df: DataFrame, group: str, item: str, tile_rows: int = 1_000_000) -> DataFrame:
    """Pairs of items that share a group with the number of groups shared, (a < b, weight), each pair once.

    Items are dealt to blocks by a hash; a tile is two blocks, and a task counts a tile's pairs item by item. So what is
    shuffled are the members of the groups, once for each block, and never the pairs. item is a whole number.
    """
    from cutstream.plans.engine import runs  # which needs this module

    members = materialise(df.select(group, F.col(item).cast("long").alias("item")).dropna().distinct(), "members")
    blocks = max(1, -(-members.count() // tile_rows))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    sets = members.groupBy(group, F.pmod(F.xxhash64("item"), F.lit(blocks)).cast("int").alias("block")).agg(F.array_sort(F.collect_list("item")).alias("s"))
    sides = sets.withColumn("other", other).select((F.least("block", "other") * blocks + F.greatest("block", "other")).cast("long").alias("tile"), (F.col("block") > F.col("other")).cast("int").alias("side"), F.struct(group).alias("g"), "s")

    def count(t: pa.Table) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        side, s = t.column("side").to_numpy(), t.column("s").combine_chunks()
        flat, ends = s.flatten().to_numpy(), np.cumsum(s.value_lengths().to_numpy())
        start = ends - s.value_lengths().to_numpy()
        names = pc.dictionary_encode(pc.struct_field(t.column("g").combine_chunks(), [0])).indices.to_numpy()
        same = not side.any()
        own = {g: flat[a:b] for g, a, b, x in zip(names.tolist(), start.tolist(), ends.tolist(), side.tolist(), strict=True) if not x}
        far = own if same else {g: flat[a:b] for g, a, b, x in zip(names.tolist(), start.tolist(), ends.tolist(), side.tolist(), strict=True) if x}
        both = [g for g in own if g in far]
        if not both:
            return
        ids = np.unique(np.concatenate([far[g] for g in both]))
        near = {g: np.searchsorted(ids, far[g]) for g in both}
        who = np.concatenate([own[g] for g in both])
        where = np.repeat(np.array(both), [len(own[g]) for g in both])
        order = np.argsort(who, kind="stable")
        who, where = who[order], where[order]
        cuts = np.flatnonzero(np.concatenate([[True], who[1:] != who[:-1], [True]]))
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            total = np.bincount(np.concatenate([near[g] for g in where[lo:hi].tolist()]), minlength=len(ids))
            at = np.flatnonzero(total)
            v, n, u = ids[at], total[at], who[lo]
            if same:
                v, n = v[v > u], n[v > u]
            yield np.minimum(u, v), np.maximum(u, v), n.astype(np.float64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, t in runs(batches, "tile"):
            held, rows = [], 0
            for x in count(t):
                held.append(x)
                rows += len(x[0])
                if rows >= 1 << 17:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], ["a", "b", "weight"])
                    held, rows = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], ["a", "b", "weight"])

    return sides.repartition(max(1, blocks * (blocks + 1) // 2), "tile").sortWithinPartitions("tile").mapInArrow(run, "a long, b long, weight double")


def cosession(spark: SparkSession, d: str, length: str = "1 hour") -> DataFrame:
    """Users with events in the same hour; weight: hours shared."""
    ev = load_table(spark, d, "events").select(F.unix_micros(F.window("ts", length).getField("start").cast("timestamp")).alias("w"), "user_id")
    return pair_counts(ev, "w", "user_id")


def convchain(spark: SparkSession, d: str) -> DataFrame:
    key = F.col("conv_id") * 10_000 + F.col("turn")
    c = load_table(spark, d, "conversations").select("conv_id", "turn", key.alias("a"))
    return c.select("a", F.lead("a").over(Window.partitionBy("conv_id").orderBy("turn")).alias("b")).dropna().withColumn("weight", F.lit(1.0))


def tradeflow(spark: SparkSession, d: str) -> DataFrame:
    """Nations of customer and supplier; weight: quantity."""
    t = lambda x: load_table(spark, d, x)
    li = t("lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    flow = li.join(t("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(t("supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return flow.groupBy(F.col("c_nationkey").cast("long").alias("a"), F.col("s_nationkey").cast("long").alias("b")).agg(F.sum("l_quantity").alias("weight"))


def benchleak(spark: SparkSession, d: str) -> DataFrame:
    """Documents and the benchmark items they contain word for word; the items, a small table, are broadcast."""
    docs = load_table(spark, d, "documents").select("doc_id", "text")
    items = F.broadcast(load_table(spark, d, "benchmark").select("item_id", F.col("text").alias("item")))
    return docs.join(items, F.col("text").contains(F.col("item"))).select(F.col("doc_id").alias("a"), (F.col("item_id") + KIND).alias("b"), F.lit(1.0).alias("weight"))


def knn(spark: SparkSession, d: str, k: int = 3, rows: int = 4096) -> DataFrame:
    """Each vector and its k nearest by cosine (ties: the lower id); weight: the cosine rounded to 5 places.

    Vectors are packed to blocks; each pair of blocks is a matrix product that gives every vector's candidates there: what
    the rounding could put among its k nearest, with the cosine summed again in order of the columns.
    """
    v = load_table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), F.transform("embedding", lambda x: x.cast("double")).alias("e"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, rows):
                own = b.slice(lo, rows)
                e = own.column("e").flatten().to_numpy()
                yield pa.RecordBatch.from_arrays([pa.array([own.column("vec_id").to_numpy().tobytes()]), pa.array([e.tobytes()])], ["ids", "vectors"])

    blocks = materialise(v.mapInArrow(pack, "ids binary, vectors binary"), "vectors")
    pairs = blocks.crossJoin(blocks.select(F.col("ids").alias("other_ids"), F.col("vectors").alias("other_vectors")).hint("shuffle_replicate_nl"))

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in zip(*(batch.column(c).to_pylist() for c in ("ids", "vectors", "other_ids", "other_vectors")), strict=True):
                a, e, b, f = (np.frombuffer(y, t) for y, t in zip(x, (np.int64, np.float64) * 2, strict=True))
                out = nearest(a, e.reshape(len(a), -1), b, f.reshape(len(b), -1), k)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in out], ["a", "b", "cosine"])

    sim = pairs.mapInArrow(near, "a long, b long, cosine double").select("a", "b", F.round("cosine", 5).alias("weight"))
    return sim.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("weight"), "b"))).where(F.col("r") <= k).drop("r")


def _in_order(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Row by row product, summed in order of the columns."""
    total = np.zeros(len(x))
    for j in range(x.shape[1]):
        total = total + x[:, j] * y[:, j]
    return total


def nearest(a: np.ndarray, e: np.ndarray, b: np.ndarray, f: np.ndarray, k: int, step: int = 512) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(a, b, cosine): of the vectors f named b, all that may be among the k nearest to each vector of e named a after
    rounding to 5 places; of those with the same cosine only the k of the lowest ids."""
    order = np.argsort(b, kind="stable")
    b, f = b[order], f[order]
    norm, other = np.sqrt(_in_order(e, e)), np.sqrt(_in_order(f, f))
    unit = f / other[:, None]
    found = []
    for lo in range(0, len(a), step):
        own = slice(lo, lo + step)
        s = (e[own] / norm[own, None]) @ unit.T
        s[a[own][:, None] == b[None, :]] = -np.inf
        bound = np.partition(s, -k, axis=1)[:, -k] if len(b) > k else np.full(len(s), -np.inf)
        i, j = np.nonzero((s >= (bound - 3e-5)[:, None]) & (s > -np.inf))
        i = i + lo
        cosine = _in_order(e[i], f[j]) / (norm[i] * other[j])
        by = np.lexsort((j, -cosine, i))  # j: by id
        i, j, cosine = i[by], j[by], cosine[by]
        head = np.concatenate([[True], (i[1:] != i[:-1]) | (cosine[1:] != cosine[:-1])]) if len(i) else np.zeros(0, bool)
        at = np.arange(len(i))
        keep = at - np.maximum.accumulate(np.where(head, at, 0)) < k
        found.append((a[i[keep]], b[j[keep]], cosine[keep]))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True))


# ---------------------------------------------------------------- generated graphs


def points(spark: SparkSession, x: int, seed: int = 1) -> DataFrame:
    """2^x points of the unit square: (id, px, py)."""
    return spark.range(1 << x).select("id", (mix31("id", seed) / F.lit(float(M31))).alias("px"), (mix31("id", seed + 1) / F.lit(float(M31))).alias("py"))


def rgg(spark: SparkSession, x: int = 10, order: str = "spatial", seed: int = 1) -> DataFrame:
    """Random geometric graph: points nearer than 0.55 sqrt(ln n / n) are joined, by an equi-join on 3 x 3 grid cells.

    order 'spatial' numbers the points by px (ties by id), 'random' keeps their ids.
    """
    return geometric(points(spark, x, seed), 1 << x, order)


def geometric(p: DataFrame, n: int, order: str) -> DataFrame:
    """Geometric graph of n points (id, px, py) of the unit square, as rgg."""
    radius = 0.55 * math.sqrt(math.log(n) / n) if n > 1 else 0.0
    if order == "spatial":
        # px is a whole number over 2^31, so equal strips of it give each task a slice of the order
        strip = F.floor(F.col("px") * 64)
        inside = F.row_number().over(Window.partitionBy("strip").orderBy("px", "id"))
        sizes = p.groupBy(strip.alias("strip")).count().select("strip", (F.sum("count").over(Window.orderBy("strip")) - F.col("count")).alias("before"))  # 64 rows
        p = p.withColumn("strip", strip).withColumn("i", inside).join(F.broadcast(sizes), "strip").select((F.col("i") - 1 + F.col("before")).alias("id"), "px", "py")
    cells = max(1, int(1 / radius)) if radius else 1
    p = p.withColumn("cx", F.floor(F.col("px") * cells)).withColumn("cy", F.floor(F.col("py") * cells))
    near = F.explode(F.array(*[F.struct((F.col("cx") + i).alias("cx"), (F.col("cy") + j).alias("cy")) for i in (-1, 0, 1) for j in (-1, 0, 1)]))
    q = p.select(F.col("id").alias("b"), F.col("px").alias("qx"), F.col("py").alias("qy"), near.alias("c")).select("b", "qx", "qy", "c.cx", "c.cy")
    d2 = (F.col("px") - F.col("qx")) * (F.col("px") - F.col("qx")) + (F.col("py") - F.col("qy")) * (F.col("py") - F.col("qy"))
    return p.join(q, ["cx", "cy"]).where((F.col("id") < F.col("b")) & (d2 < radius * radius)).select(F.col("id").alias("a"), "b", F.lit(1.0).alias("weight"))


def grid(spark: SparkSession, x: int = 10) -> DataFrame:
    """Square mesh of 2^x vertices (x even), rows one after another."""
    w = 1 << (x // 2)
    v = spark.range(w * w)
    right = v.where((F.col("id") % w) < w - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    down = v.where(F.col("id") < w * (w - 1)).select(F.col("id").alias("a"), (F.col("id") + w).alias("b"))
    return right.unionByName(down).withColumn("weight", F.lit(1.0))


def er(spark: SparkSession, x: int = 10, degree: int = 8, seed: int = 3) -> DataFrame:
    """Uniform random pairs, degree * n / 2 drawn."""
    n = 1 << x
    return spark.range(n * degree // 2).select((mix31("id", seed) % n).alias("a"), (mix31("id", seed + 1) % n).alias("b"), F.lit(1.0).alias("weight"))


def chords(spark: SparkSession, x: int = 10, seed: int = 5) -> DataFrame:
    """A ring with chords to vertices of low number: degrees fall as a power (u -> floor(n u^3))."""
    n = 1 << x
    ring = spark.range(n).select(F.col("id").alias("a"), ((F.col("id") + 1) % n).alias("b"))
    u = mix31("id", seed) / F.lit(float(M31))
    more = spark.range(2 * n).select((F.col("id") % n).alias("a"), F.floor(u * u * u * n).cast("long").alias("b"))
    return ring.unionByName(more).withColumn("weight", F.lit(1.0))


# ---------------------------------------------------------------- the same kinds of graphs over rows of given tables


def _last(df: DataFrame, key: str) -> int:
    """The largest key; keys are 0, 1, ..."""
    return df.agg(F.max(key)).first()[0] or 0


def customer_rgg(spark: SparkSession, d: str, order: str = "spatial") -> DataFrame:
    """Random geometric graph of customers: placed by account balance (-1,000 to 10,000) and by a keyed number."""
    c = load_table(spark, d, "customer").select("c_custkey", "c_acctbal").dropna()
    p = c.select(F.col("c_custkey").alias("id"), ((F.col("c_acctbal") + 1000) / F.lit(11000.0)).alias("px"), (mix31("c_custkey", 2) / F.lit(float(M31))).alias("py"))
    return geometric(p, c.count(), order)


def order_grid(spark: SparkSession, d: str) -> DataFrame:
    """Mesh of the orders in key order, rows one after another, as wide as the root of their number."""
    o = load_table(spark, d, "orders").select(F.col("o_orderkey").alias("a"))
    w = max(1, math.isqrt(_last(o, "a") + 1))
    step = F.explode(F.when(F.col("a") % w < w - 1, F.array(F.lit(1), F.lit(w))).otherwise(F.array(F.lit(w)))) if w > 1 else F.lit(1)
    return o.withColumn("step", step).select("a", (F.col("a") + F.col("step")).alias("b")).join(o.select(F.col("a").alias("b")), "b", "left_semi").select("a", "b", F.lit(1.0).alias("weight"))


def order_er(spark: SparkSession, d: str) -> DataFrame:
    """Uniform random pairs of customers, one drawn by each order: its own customer and any one."""
    o = load_table(spark, d, "orders").select("o_orderkey", "o_custkey")
    return o.select(F.col("o_custkey").alias("a"), (mix31("o_orderkey", 4) % (_last(o, "o_custkey") + 1)).alias("b"), F.lit(1.0).alias("weight"))


def order_chords(spark: SparkSession, d: str) -> DataFrame:
    """A ring of the customers, with a chord for each order from its customer to one of low number."""
    c, o = load_table(spark, d, "customer").select("c_custkey"), load_table(spark, d, "orders").select("o_orderkey", "o_custkey")
    n = _last(c, "c_custkey") + 1
    u = mix31("o_orderkey", 5) / F.lit(float(M31))
    ring = c.select(F.col("c_custkey").alias("a"), ((F.col("c_custkey") + 1) % n).alias("b"))
    return ring.unionByName(o.select(F.col("o_custkey").alias("a"), F.floor(u * u * u * n).cast("long").alias("b"))).withColumn("weight", F.lit(1.0))


Builder = Callable[[SparkSession, str], DataFrame]
BUILDERS: dict[str, Builder] = {
    f.__name__: f for f in (copurchase, orderpart, fkforest, fkstar, docline, docline_star, docsource, weblink, userprop, userflow, cosession, convchain, tradeflow, benchleak, knn)
} | {
    "rgg": lambda s, d: rgg(s, 10),
    "rgg_random": lambda s, d: rgg(s, 10, "random"),
    "grid": lambda s, d: grid(s, 10),
    "er": lambda s, d: er(s, 10),
    "chords": lambda s, d: chords(s, 10),
}

#: Graphs of the kinds above that a given table carries; ON_TABLES names them by kind.
CARRIED: dict[str, Builder] = {
    "customer_rgg": customer_rgg,
    "customer_rgg_random": lambda s, d: customer_rgg(s, d, "random"),
    "order_grid": order_grid,
    "order_er": order_er,
    "order_chords": order_chords,
}
ON_TABLES = {"rgg": "customer_rgg", "rgg_random": "customer_rgg_random", "grid": "order_grid", "er": "order_er", "chords": "order_chords"}
#: Builders that give each pair once, the smaller key first, without loops: nothing to clean.
SIMPLE = {"cosession", "customer_rgg", "customer_rgg_random", "order_grid"}


def edges(spark: SparkSession, sf_dir: str, name: str, unit: bool = False) -> DataFrame:
    """Clean edges of a graph by name, over natural keys."""
    raw = (BUILDERS | CARRIED)[name](spark, sf_dir)
    if name in SIMPLE:
        return raw.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(1.0).alias("weight") if unit else F.col("weight"))
    return clean(raw, unit)


def column_of_order(kind: str, degree: Column, key: Column, seed: int) -> list[Column]:
    """Sort columns of a vertex order: natural (by key), degree (rising), random (keyed hash)."""
    return {"natural": [key], "degree": [degree, key], "random": [F.xxhash64(F.lit(seed), key), key]}[kind]
