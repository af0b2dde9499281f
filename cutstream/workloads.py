"""The experiment workloads on graphs of the given tables: each runs its cells and reports the measure it is about.

A cell is a method on a graph with k blocks; independent cells run side by side from a small pool of driver threads. The
defaults are small; every function takes larger graphs, more blocks or seeds, and `full` of FULL gives the whole grids.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from contextlib import nullcontext
from threading import Lock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.operators import compare as C
from cutstream.operators import measures as M
from cutstream.params import PartitionParams
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph
from cutstream.plans.kernel import AllBlocks
from cutstream.scratch import materialise, path
from cutstream.sources.files import write_by_block
from cutstream.sources.graphs import KIND, load_table

RUN = "alg string, graph string, k int, delta long, model string, passes int, seed int, cut double, cut_pct double, max_load double, lmax double, feasible boolean, seconds double"
TUNING = ("docline", "rgg", "grid")
TEST = ("docline", "fkforest", "rgg", "grid", "convchain", "userprop")
POOL = 3
#: Vertices of a graph from which on its cells run one at a time: tasks of two would not fit the memory of one executor. Only
#: a cell that holds no model, which is one ordered task, may run beside one that does.
LARGE_GRAPH, ONE_LARGE, ONE_ORDERED = 1 << 21, Lock(), Lock()
ORDERED = ("hp", "cdg", "pgg", "pgg_scan", "pgg2")
#: Whole grids of the workloads that are registered with smaller ones.
FULL = {
    "against_discount": {"graphs": ("docline", "fkforest", "rgg", "grid", "convchain"), "ks": (4, 8, 16, 32, 64, 128)},
    "wide_k": {"ks": tuple(range(2, 129))},
    "profiles": {"graphs": TEST, "ks": (2, 4, 8, 16, 32, 64, 128)},
    "offline_yardstick": {"graphs": TUNING, "ks": (2, 4, 8, 16, 32, 64, 128), "seeds": tuple(range(1, 11)), "passes": 10},
    "large_graphs": {"graphs": ("orderpart", "copurchase", "userprop", "fkforest"), "ks": (8, 16, 32, 64, 128, 256), "share": 64},
    "seeds": {"graphs": TEST, "count": 10},
    "memory": {"graphs": ("orderpart", "copurchase", "userprop")},
}
#: Methods by name: parameters to an assignment.
METHODS = {
    "hp": lambda g, p: E.place_hash(g, p.k, p.seed),
    "cdg": lambda g, p: E.place_capacity_discount(g, p),
    "pgg": lambda g, p: E.place_penalty_gain(g, p.with_(passes=1)),
    "pgg_scan": lambda g, p: materialise(E.place_greedy(g, p.with_(objective="penalty_gain"), blocks=AllBlocks), "assignment"),
    "pgg2": lambda g, p: E.place_penalty_gain(g, p.with_(passes=2)),
    "bmp": lambda g, p: E.partition_buffered(g, p).assignment,
    "bmp_int": lambda g, p: E.partition_buffered(g, p.with_(delta=None)).assignment,
    "mcd": lambda g, p: E.partition_buffered(g, p.with_(objective="capacity_discount")).assignment,
    "mcd_int": lambda g, p: E.partition_buffered(g, p.with_(objective="capacity_discount", delta=None)).assignment,
    "offline": lambda g, p: E.partition_offline(g, p, (1, 2), 3),
}


def timed_run(g: Graph, label: str, method: str, p: PartitionParams) -> tuple:
    with (ONE_ORDERED if method in ORDERED else ONE_LARGE) if g.n >= LARGE_GRAPH else nullcontext():
        began = time.time()
        out = METHODS[method](g, p) if isinstance(method, str) else method(g, p)
    if method == "hp":  # the others write their assignment as they run
        out = materialise(out, "assignment")
    seconds = time.time() - began
    r = M.summary(g, out, p.k, p.eps).first()
    return (label, g.name, p.k, p.delta, p.model, p.passes, p.seed, r.cut, r.cut_pct, r.max_load, r.lmax, bool(r.feasible), seconds)


def run_cells(spark: SparkSession, cells: list[tuple[Graph, str, str, PartitionParams]]) -> DataFrame:
    """Rows of RUN for the cells (graph, label, method, parameters)."""
    with ThreadPoolExecutor(POOL) as small, ThreadPoolExecutor(2) as models, ThreadPoolExecutor(2) as ordered:  # of two, one measures
        pool = lambda g, method: small if g.n < LARGE_GRAPH else ordered if method in ORDERED else models
        rows = [x.result() for x in [pool(c[0], c[2]).submit(timed_run, *c) for c in cells]]
    return spark.createDataFrame(rows, RUN)


def full(spark: SparkSession, d: str, name: str) -> DataFrame:
    """The workload of that function name on its whole grid."""
    return globals()[name](spark, d, **FULL[name])


def load(spark: SparkSession, d: str, names, **options) -> list[Graph]:
    with ThreadPoolExecutor(POOL) as pool:
        return list(pool.map(lambda n: Graph.load(spark, d, n, **options), names))


def _delta(g: Graph) -> int:
    return max(64, g.n // 8)


def score(runs: DataFrame) -> DataFrame:
    """Runs with the score that comparisons use: the cut, at least one edge."""
    return runs.withColumn("score", F.greatest("cut", F.lit(1.0)))


def _sweep(spark, d, name, values, change, graphs=TUNING, k=8, method="bmp"):
    """One parameter over values: mean cut, improvement over the first value, and time, by value."""
    cells = [(g, str(v), method, change(PartitionParams(k=k, delta=_delta(g)), g, v)) for g in load(spark, d, graphs) for v in values]
    runs = score(run_cells(spark, cells))
    gained = C.improvement(runs, str(values[0])).groupBy("alg").agg(F.avg("improvement").alias("improvement"))
    return runs.groupBy("alg").agg(F.exp(F.avg(F.log("score"))).alias("geomean_cut"), F.avg("seconds").alias("seconds"), F.bool_and("feasible").alias("feasible")).join(gained, "alg").withColumnRenamed("alg", name)


def refinement_rounds(spark, d, values=(1, 5, 25)):
    """Rounds of local search, at the coarsest-size factor that leaves it the most to do."""
    return _sweep(spark, d, "rounds", values, lambda p, g, v: p.with_(refine_rounds=v, x=64))


def coarsest_size(spark, d, values=(64, 32, 16, 8, 4, 2, 1)):
    return _sweep(spark, d, "x", values, lambda p, g, v: p.with_(x=v))


def buffer_size(spark, d, values=(64, 128, 256, 512, 1024, 0)):
    """0: the whole graph in one buffer."""
    return _sweep(spark, d, "delta", values, lambda p, g, v: p.with_(delta=v or None))


def model_kind(spark, d, graphs=("docline", "fkforest", "rgg", "grid")):
    return _sweep(spark, d, "model", ("basic", "extended"), lambda p, g, v: p.with_(model=v), graphs)


def restreaming(spark, d, graphs=("docline", "rgg"), passes=10, k=8):
    """Cut after each pass and what it gained on the one before."""
    rows = []
    for g in load(spark, d, graphs):
        for i, r in enumerate(E.pass_results(g, PartitionParams(k=k, delta=_delta(g)), passes)):
            rows.append((g.name, k, i + 1, float(M.edge_cut(g.edges, r.assignment, g.n).first()["cut"]), sum(r.seconds.values())))
    return C.pass_trace(spark.createDataFrame(rows, "graph string, k int, pass int, cut double, seconds double"))


def comparison(spark, d, graphs=TEST, k=32, methods=("bmp_int", "mcd_int", "bmp", "pgg2", "pgg", "cdg", "hp")):
    """Cut percentages of all methods, a row a graph."""
    cells = [(g, m, m, PartitionParams(k=k, delta=_delta(g))) for g in load(spark, d, graphs) for m in methods]
    return run_cells(spark, cells).groupBy("graph").pivot("alg", list(methods)).agg(F.round(F.first("cut_pct"), 2))


def against_discount(spark, d, graphs=("docline", "rgg"), ks=(4, 16, 64)):
    """Cuts over those of the same method with the capacity discount."""
    cells = [(g, m, m, PartitionParams(k=k, delta=_delta(g))) for g in load(spark, d, graphs) for k in ks for m in ("bmp", "mcd", "mcd_int")]
    return C.relative(score(run_cells(spark, cells)), "mcd")


def wide_k(spark, d, graphs=("docline", "rgg"), ks=(2, 5, 13, 32, 64, 127), methods=("bmp", "pgg", "cdg", "hp")):
    """Improvement over the one-pass penalty gain, by k."""
    cells = [(g, m, m, PartitionParams(k=k, delta=_delta(g))) for g in load(spark, d, graphs) for k in ks for m in methods]
    return C.improvement(score(run_cells(spark, cells)), "pgg").groupBy("alg", "k").agg(F.avg("improvement").alias("improvement"))


def profiles(spark, d, graphs=("docline", "fkforest", "rgg"), ks=(4, 16), methods=("bmp_int", "bmp", "pgg2", "pgg", "cdg", "hp")):
    cells = [(g, m, m, PartitionParams(k=k, delta=_delta(g))) for g in load(spark, d, graphs) for k in ks for m in methods]
    return C.performance_profile(score(run_cells(spark, cells)), [1.0, 1.1, 1.5, 2.0, 5.0, 100.0])


def offline_yardstick(spark, d, graphs=("docline", "rgg"), ks=(2, 8, 32), seeds=(1, 2), passes=3):
    """Cuts over that of the whole graph in one model, replayed, the best of several seeds."""
    cells = [(g, m, m, PartitionParams(k=k, delta=_delta(g))) for g in load(spark, d, graphs) for k in ks for m in ("bmp_int", "bmp", "pgg")]
    runs = run_cells(spark, cells)
    best = [(g, "offline", lambda g, p: E.partition_offline(g, p, seeds, passes), PartitionParams(k=k, delta=None)) for g in load(spark, d, graphs) for k in ks]
    return C.relative(score(runs.unionByName(run_cells(spark, best))), "offline")


def geometry(spark, d, k=16, delta=128):
    """Pieces of blocks on a geometric graph, in place of a picture."""
    g = Graph.load(spark, d, "rgg")
    out = None
    for name in ("hp", "pgg", "bmp", "bmp_int"):
        f = M.fragmentation(g.edges, g.nodes, METHODS[name](g, PartitionParams(k=k, delta=delta))).agg(F.avg("pieces").alias("pieces"), F.avg("largest").alias("largest")).select(F.lit(name).alias("alg"), "*")
        out = f if out is None else out.unionByName(f)
    return out


def large_graphs(spark, d, graphs=("orderpart",), ks=(8, 32), methods=("bmp", "pgg", "cdg", "hp"), share=16):
    """Cut and time on the largest graphs, buffers of one in `share` parts."""
    cells = [(g, m, m, PartitionParams(k=k, delta=max(64, g.n // share))) for g in load(spark, d, graphs) for k in ks for m in methods]
    return run_cells(spark, cells).select("graph", "k", "alg", "cut_pct", "seconds", "feasible")


def memory(spark, d, graphs=("fkforest",), k=32):
    """Peak bytes of the ordered task above its start, as its worker measures them, for large and small buffers and for the
    one-pass methods; bytes of the largest buffer's model (none in the one-pass methods) and of the state that stays."""
    rows = []
    for g in load(spark, d, graphs):
        for delta in (max(64, g.n // 2), max(64, g.n // 64)):
            p = PartitionParams(k=k, delta=delta)
            coarse = E.coarsened(g, p)
            size = coarse.groupBy("batch").agg(F.sum(F.length("blob")).alias("bytes")).agg(F.max("bytes")).first()[0]
            rows.append((g.name, "bmp", delta, E.fold(g, p, coarse, probe=True).first().peak_bytes, int(size), 4 * g.n + 16 * k))
        for m, objective in (("pgg", "penalty_gain"), ("cdg", "capacity_discount")):
            peak = E.place_greedy(g, PartitionParams(k=k, objective=objective), probe=True).first().peak_bytes
            rows.append((g.name, m, 1, peak, None, 8 * g.n + 16 * k))
    return spark.createDataFrame(rows, "graph string, alg string, delta long, peak_bytes long, model_bytes long, state_bytes long")


def loading(spark, d, graphs=("orderpart", "fkforest")):
    """Seconds to read the edges and nothing else."""
    rows = []
    for g in load(spark, d, graphs):
        began = time.time()
        g.edges.write.format("noop").mode("overwrite").save()
        rows.append((g.name, g.m, time.time() - began))
    return spark.createDataFrame(rows, "graph string, m long, seconds double")


def time_by_k(spark, d, graph="fkforest", ks=(8, 32, 128)):
    """Seconds by k and the slope of each method; pgg_scan looks at all k blocks for every vertex."""
    g = Graph.load(spark, d, graph)
    runs = run_cells(spark, [(g, m, m, PartitionParams(k=k, delta=_delta(g))) for k in ks for m in ("bmp", "pgg", "pgg_scan", "cdg")])
    return runs.groupBy("alg").agg(F.regr_slope("seconds", "k").alias("seconds_per_block"), F.map_from_entries(F.collect_list(F.struct("k", "seconds"))).cast("string").alias("seconds"))


def seeds(spark, d, graphs=("docline", "rgg"), k=8, count=3):
    """Mean over seeds, then geometric mean over graphs."""
    cells = [(g, "bmp", "bmp", PartitionParams(k=k, delta=_delta(g), seed=s)) for g in load(spark, d, graphs) for s in range(count)]
    return C.aggregate_runs(score(run_cells(spark, cells)))


def order_sensitivity(spark, d, graph="rgg", k=8):
    cells = []
    for order in ("natural", "random", "degree"):
        g = Graph.load(spark, d, graph, order=order)
        cells += [(g, f"{m}_{order}", m, PartitionParams(k=k, delta=_delta(g))) for m in ("bmp", "pgg")]
    return run_cells(spark, cells).select("alg", "cut_pct", "feasible")


def live_stream(spark, d):
    from cutstream.queries_streaming import stream_partition

    return stream_partition(spark, d)


def application(spark, d, k=8):
    """A store of orders and parts placed by hash and by buffers: messages that one- and two-hop look-ups of all vertices
    need, and rows of lineitem, stored by their order's block, whose part lies in the same block."""
    g = Graph.load(spark, d, "orderpart")
    lines = load_table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")

    def measured(name: str) -> DataFrame:
        placed = materialise(METHODS[name](g, PartitionParams(k=k, delta=_delta(g))), "assignment")
        home = g.nodes.join(placed.select("pos", "block"), "pos").select("key", "block")
        at = path(spark, "store")
        write_by_block(lines, home.withColumnRenamed("key", "l_orderkey"), "l_orderkey", at, k)
        part = home.where(F.col("key") >= KIND).select((F.col("key") - KIND).alias("l_partkey"), F.col("block").alias("part_block"))
        stored = spark.read.parquet(at).join(part, "l_partkey").agg(F.count("*").alias("rows_stored"), F.count_if(F.col("block") == F.col("part_block")).alias("rows_local"))
        return materialise(M.query_messages(g.edges, placed).select(F.lit(name).alias("alg"), "one_hop", "two_hop").crossJoin(stored), "measured")  # a row each

    with ThreadPoolExecutor(2) as pool:
        hp, bmp = pool.map(measured, ("hp", "bmp"))
    return hp.unionByName(bmp)


QUERIES = {
    "w01_refinement_rounds": refinement_rounds,
    "w02_coarsest_size": coarsest_size,
    "w03_buffer_size": buffer_size,
    "w04_model_kind": model_kind,
    "w05_restreaming": restreaming,
    "w06_comparison": comparison,
    "w07_against_discount": against_discount,
    "w08_wide_k": wide_k,
    "w09_profiles": profiles,
    "w10_offline_yardstick": offline_yardstick,
    "w11_geometry": geometry,
    "w12_large_graphs": large_graphs,
    "w13_memory": memory,
    "w14_loading": loading,
    "w15_time_by_k": time_by_k,
    "w16_seeds": seeds,
    "w17_order_sensitivity": order_sensitivity,
    "w18_live_stream": live_stream,
    "w19_application": application,
}
ORACLES: dict[str, str] = {}
