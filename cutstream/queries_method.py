"""Queries on the methods: placements and their measures, buffer models, gains, clustering rounds, greedies, comparisons."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from contextlib import nullcontext

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutstream import workloads as W
from cutstream.functions.columns import mix31, mix31_sql
from cutstream.operators import compare as C
from cutstream.operators import measures as M
from cutstream.operators import models as B
from cutstream.params import PartitionParams, alpha
from cutstream.plans import engine as E
from cutstream.operators.stream_order import degrees
from cutstream.plans.graph import Graph
from cutstream.queries_graph import graph_cte
from cutstream.scratch import materialise
from cutstream.twins import multilevel_sql

DELTA, K = 64, 4
SEED = 42


def _docline(s, d):
    return Graph.load(s, d, "docline")


# ---------------------------------------------------------------- hash placement and measures


def cut_hash_by_k(s, d):
    out = None
    for name in ("docline", "fkforest", "userprop"):
        e = Graph.load(s, d, name).edges.withColumn("k", F.explode(F.array(*[F.lit(k) for k in (2, 4, 8, 16, 32)])))
        cut = F.count_if(mix31("src") % F.col("k") != mix31("dst") % F.col("k"))
        row = e.groupBy("k").agg(cut.alias("cut"), F.count("*").alias("m"), F.round(100 * cut / F.count("*"), 6).alias("cut_pct")).select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def balance_hash(s, d):
    g = Graph.load(s, d, "fkforest")
    return M.balance(g.nodes, E.place_hash(g, 8), 8, 0.03, g.node_weight).select("max_load", F.round("imbalance", 6).alias("imbalance"), "lmax", "feasible")


def block_load_hash(s, d):
    g = Graph.load(s, d, "fkforest")
    return M.block_load(g.nodes, E.place_hash(g, 8))


def quotient_hash(s, d):
    g = _docline(s, d)
    return M.quotient(g.edges, E.place_hash(g, 8))


def boundary_hash(s, d):
    g = _docline(s, d)
    return M.boundary(g.edges, E.place_hash(g, 2))


def comm_volume_hash(s, d):
    g = _docline(s, d)
    return M.comm_volume(g.edges, E.place_hash(g, 8))


def fragmentation_hash(s, d):
    g = _docline(s, d)
    return M.fragmentation(g.edges, g.nodes, E.place_hash(g, 4))


def controls(s, d):
    """Cut of the balanced controls: contiguous ranges and round robin."""
    g = _docline(s, d)
    rows = [M.edge_cut(g.edges, f(g, 8)).select(F.lit(n).alias("alg"), "cut_edges", F.round("cut_pct", 6).alias("cut_pct")) for n, f in (("range", E.place_range), ("round_robin", E.place_round_robin))]
    return rows[0].unionByName(rows[1])


# ---------------------------------------------------------------- models (blocks: contiguous ranges, as if placed already)


def model_basic(s, d):
    g = _docline(s, d)
    return B.model_basic(g.edges, E.place_range(g, K), g.n, DELTA)


def model_extended(s, d):
    g = _docline(s, d)
    return B.model_extended(g.edges, E.place_range(g, K), g.n, DELTA, SEED)


def model_restream(s, d):
    g = _docline(s, d)
    return B.model_restream(g.edges, E.place_range(g, K), g.n, DELTA)


def model_nodes(s, d):
    g = _docline(s, d)
    return B.model_nodes(g.nodes, g.edges, E.place_range(g, K), g.n, DELTA, K, SEED)


def ghost_reps(s, d):
    return B.ghost_representatives(_docline(s, d).edges, DELTA, SEED)


def _map(g):
    return g.nodes.select(F.col("pos").alias("fine"), F.floor(F.col("pos") / 4).cast("long").alias("coarse"))


def contract_once(s, d):
    g = _docline(s, d)
    return B.contract(g.edges, _map(g))


def gain_table(s, d):
    g = _docline(s, d)
    return B.gain_table(g.edges, g.nodes, E.place_range(g, K), alpha(g.n, g.m, K, 1.5)).withColumn("gain", F.round("gain", 6))


def gain_additivity(s, d):
    g = _docline(s, d)
    t = B.gain_additivity(g.edges, g.nodes, E.place_range(g, K), _map(g), alpha(g.n, g.m, K, 1.5))
    return t.select("coarse", "block", F.round("merged", 6).alias("merged"), (F.abs(F.col("merged") - F.col("members")) < 1e-9).alias("additive"))


def _lp(rounds):
    def run(s, d):
        g = _docline(s, d)
        labels = g.nodes.select("pos", F.col("pos").alias("label"))
        for _ in range(rounds):
            labels = B.lp_sync_round(g.edges, labels)
        return labels

    return run


def refine_sync_round(s, d):
    from cutstream.params import lmax

    g = _docline(s, d)
    return B.refine_sync_round(g.edges, g.nodes, E.place_range(g, K), alpha(g.n, g.m, K, 1.5), lmax(g.n, K, 0.2))


def lp_distributed(s, d):
    """Cluster sizes of the size-bounded distributed clustering."""
    g = _docline(s, d)
    return B.lp_cluster_distributed(g.nodes, g.edges, 5, 12.0, SEED).groupBy("label").agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- sequential methods


def _greedy(graph, k, objective="penalty_gain", passes=1, unit=True):
    def run(s, d):
        g = Graph.load(s, d, graph, unit)
        return E.greedy(g, PartitionParams(k=k, objective=objective, passes=passes)).assignment.select("pos", "block")

    return run


def bmp_delta1_docline(s, d):
    g = _docline(s, d)
    return E.partition_buffered(g, PartitionParams(k=8, delta=1, model="basic")).assignment.select("pos", "block")


def initial_tiny(s, d):
    g = _docline(s, d)
    lm = g.nodes.select(F.col("pos").alias("fine"), F.floor(F.col("pos") / 8).cast("long").alias("coarse"))
    sizes = lm.groupBy(F.col("coarse").alias("key")).agg(F.count("*").cast("double").alias("weight"))
    tiny = Graph.from_edges(B.contract(g.edges, lm), extra=sizes.select("key"), weights=sizes)
    return E.greedy(tiny, PartitionParams(k=K, eps=0.5)).assignment.select("pos", "block")


def _bmp(graph, k=8, unit=True, **changes):
    def run(s, d):
        g = Graph.load(s, d, graph, unit)
        p = PartitionParams(k=k, **({"delta": max(64, g.n // 8)} | changes))
        return M.summary(g, E.partition_buffered(g, p).assignment, k, p.eps).select(F.lit(graph).alias("graph"), "cut", "cut_pct", "max_load", "lmax", "feasible")

    return run


def _blocks(k=8, unit=True, graph="docline", **changes):
    """Blocks of every vertex."""

    def run(s, d):
        g = Graph.load(s, d, graph, unit)
        return E.partition_buffered(g, PartitionParams(k=k, **({"delta": max(64, g.n // 8)} | changes))).assignment.select("pos", "block")

    return run


def bmp_invariants(s, d):
    """Each is true for every engine, model and pass count: all vertices once, balanced, loads add up, cut counted two ways."""

    def row_of(cell: tuple[str, str, dict]) -> DataFrame:
        graph, label, changes = cell
        g = graphs[graph]
        p = PartitionParams(k=8, **({"delta": max(64, g.n // 8)} | changes))
        with W.ONE_LARGE if g.n >= W.LARGE_GRAPH else nullcontext():
            a = E.partition_buffered(g, p).assignment
        full = M.edge_cut(g.edges, a).crossJoin(M.balance(g.nodes, a, 8, p.eps, g.node_weight)).crossJoin(a.agg(F.count("*").alias("rows"), F.countDistinct("pos").alias("ids"), F.max("block").alias("top")))
        full = full.crossJoin(M.quotient(g.edges, a).agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("between"))).crossJoin(M.block_load(g.nodes, a).agg(F.sum("load").alias("loads")))
        row = full.select(F.lit(graph).alias("graph"), F.lit(label).alias("variant"), ((F.col("rows") == g.n) & (F.col("ids") == g.n)).alias("covers"), (F.col("top") < 8).alias("in_range"), F.col("feasible"), (F.col("loads") == g.node_weight).alias("loads_add_up"), (F.col("between") == F.col("cut")).alias("cut_twice"))
        return materialise(row, "invariants")  # a plan for each row: all in one would not fit the driver

    names = ("docline", "fkforest", "rgg", "convchain")
    variants = (("extended", {}), ("basic", {"model": "basic"}), ("restreamed", {"passes": 2}), ("internal", {"delta": None}), ("discount", {"objective": "capacity_discount"}))
    with ThreadPoolExecutor(2) as small, ThreadPoolExecutor(2) as large:  # of two large ones, one is measured
        graphs = dict(zip(names, small.map(lambda name: Graph.load(s, d, name), names), strict=True))
        rows = [(large if graphs[name].n >= W.LARGE_GRAPH else small).submit(row_of, (name, *x)) for name in names for x in variants]
        out = rows[0].result()
        for row in rows[1:]:
            out = out.unionByName(row.result())
    return out


def bmp_budget(s, d):
    """Buffers by space: no buffer but that of one vertex takes more than the budget, all vertices once, balanced."""
    g = _docline(s, d)
    p = PartitionParams(k=8, budget=600)
    a = E.partition_buffered(g, p).assignment
    cost = a.join(degrees(g.edges), "pos", "left").groupBy("batch_id").agg(F.sum(1 + F.coalesce("degree", F.lit(0))).alias("cost"), F.count("*").alias("n"), F.max(1 + F.coalesce("degree", F.lit(0))).alias("top"))
    within = cost.agg(F.bool_and(F.col("cost") - F.col("top") <= p.budget).alias("within"))
    return within.crossJoin(M.balance(g.nodes, a, 8, 0.03, g.n).select("feasible")).crossJoin(a.agg((F.countDistinct("pos") == g.n).alias("covers")))


def lanes_feasible(s, d):
    """Two lanes against a snapshot: all vertices once, no block above its capacity."""
    g = _docline(s, d)
    a = E.partition_buffered(g, PartitionParams(k=8, delta=64, engine="lanes", lanes=2)).assignment
    return M.balance(g.nodes, a, 8, 0.03, g.n).select("feasible").crossJoin(a.agg((F.countDistinct("pos") == g.n).alias("covers")))


def bmp_distributed(s, d):
    """Coarsened by DataFrame rounds to 200 vertices at most, refined by a replayed pass."""
    from cutstream.plans.distributed import partition_distributed

    g = Graph.load(s, d, "rgg")
    return M.summary(g, partition_distributed(g, PartitionParams(k=8, delta=256), 200).assignment, 8, 0.03).select("cut", "cut_pct", "max_load", "lmax", "feasible")


def hierarchy(s, d):
    """Levels of each buffer's hierarchy."""
    g = Graph.load(s, d, "fkforest")
    return M.hierarchy_stats(E.coarsened(g, PartitionParams(k=8, delta=2048)))


# ---------------------------------------------------------------- comparisons

_KS, _GRAPHS = (4, 8, 16), ("docline", "fkforest", "userprop")


def control_runs(s, d, ks=_KS):
    """Runs of the deterministic placements: alg, graph, k, score (cut edges)."""
    out = None
    for name in _GRAPHS:
        g = Graph.load(s, d, name)
        e = g.edges.withColumn("k", F.explode(F.array(*[F.lit(k) for k in ks])))
        cut = {"hash": F.count_if(mix31("src") % F.col("k") != mix31("dst") % F.col("k")), "round_robin": F.count_if(F.col("src") % F.col("k") != F.col("dst") % F.col("k")), "range": F.count_if(F.floor(F.col("src") * F.col("k") / g.n) != F.floor(F.col("dst") * F.col("k") / g.n))}
        wide = e.groupBy("k").agg(*[v.cast("double").alias(n) for n, v in cut.items()])
        row = wide.select("k", F.explode(F.array(*[F.struct(F.lit(n).alias("alg"), F.col(n).alias("score")) for n in cut])).alias("x")).select("x.alg", F.lit(name).alias("graph"), "k", "x.score")
        out = row if out is None else out.unionByName(row)
    return out


def _r(df, *names):
    for n in names:
        df = df.withColumn(n, F.round(n, 6))
    return df


def paper_k32_check(s, d):
    """Graphs of given tables on which each placement in order beats each other one at 32 blocks."""
    p = control_runs(s, d, (32,))
    a = p.where("alg in ('range', 'round_robin')").select("graph", F.col("alg").alias("setup"), F.col("score").alias("own"))
    b = p.where("alg not in ('range', 'round_robin')").select("graph", F.col("alg").alias("other"), "score")
    return a.join(b, "graph").groupBy("setup", "other").agg(F.count_if(F.col("own") < F.col("score")).alias("wins"), F.count("*").alias("graphs"))


def paper_k32_geomeans(s, d):
    """Mean cut of each placement over graphs of given tables at 32 blocks."""
    return control_runs(s, d, (32,)).groupBy("alg").agg(F.round(F.exp(F.avg(F.log(F.greatest("score", F.lit(1.0))))), 4).alias("geomean"))


QUERIES = {
    "cut_hash_by_k": cut_hash_by_k,
    "balance_hash": balance_hash,
    "block_load_hash": block_load_hash,
    "quotient_hash": quotient_hash,
    "boundary_hash": boundary_hash,
    "comm_volume_hash": comm_volume_hash,
    "fragmentation_hash": fragmentation_hash,
    "cut_controls": controls,
    "model_basic": model_basic,
    "model_extended": model_extended,
    "model_restream": model_restream,
    "model_nodes": model_nodes,
    "ghost_reps": ghost_reps,
    "contract_once": contract_once,
    "gain_table": gain_table,
    "gain_additivity": gain_additivity,
    "lp_sync_round": _lp(1),
    "lp_sync_rounds3": _lp(3),
    "refine_sync_round": refine_sync_round,
    "lp_distributed": lp_distributed,
    "pgg_docline": _greedy("docline", 8),
    "cdg_docline": _greedy("docline", 8, "capacity_discount"),
    "pgg2_docline": _greedy("docline", 8, passes=2),
    "cdg2_docline": _greedy("docline", 8, "capacity_discount", 2),
    "pgg_tradeflow": _greedy("tradeflow", 4, unit=False),
    "bmp_delta1_docline": bmp_delta1_docline,
    "initial_tiny": initial_tiny,
    "bmp_docline": _blocks(),
    "bmp_docline_basic": _blocks(model="basic"),
    "bmp_docline_internal": _blocks(delta=None),
    "bmp_docline_discount": _blocks(objective="capacity_discount"),
    "bmp_docline_lowest_ties": _blocks(tie="lowest", delta=None),
    "bmp_docline_restreamed": _blocks(passes=2),
    "bmp_docline_driver_loop": _blocks(engine="driver_loop"),
    "bmp_docline_budget": bmp_budget,
    "bmp_docline_k4": _blocks(k=4, x=2, refine_rounds=2, coarsen_rounds=3),
    "bmp_fkforest": _bmp("fkforest", 32),
    "bmp_fkforest_restreamed": _bmp("fkforest", 32, passes=3),
    "bmp_fkforest_discount": _bmp("fkforest", 32, objective="capacity_discount"),
    "bmp_rgg": _bmp("rgg"),
    "bmp_grid": _bmp("grid"),
    "bmp_chords": _bmp("chords"),
    "bmp_convchain": _bmp("convchain"),
    "bmp_weblink": _bmp("weblink"),
    "bmp_tradeflow_weighted": _bmp("tradeflow", 4, unit=False, eps=0.1),
    "bmp_power_table": _bmp("docline", power="table"),
    "bmp_bisected_start": _bmp("docline", initial="recursive_bisection"),
    "bmp_distributed": bmp_distributed,
    "bmp_invariants": bmp_invariants,
    "lanes_feasible": lanes_feasible,
    "hierarchy_stats": hierarchy,
    "control_runs": control_runs,
    "improvement_tbl": lambda s, d: _r(C.improvement(control_runs(s, d), "hash"), "improvement"),
    "relative_tbl": lambda s, d: _r(C.relative(control_runs(s, d), "hash"), "relative"),
    "ratio_tbl": lambda s, d: _r(C.ratio_to_max(control_runs(s, d)), "ratio"),
    "profile_tbl": lambda s, d: _r(C.performance_profile(control_runs(s, d), [1.0, 1.05, 1.25, 2.0, 10.0]), "share"),
    "geomean_tbl": lambda s, d: _r(C.aggregate_runs(control_runs(s, d).withColumn("seed", F.lit(0))), "geomean"),
    "wins_tbl": lambda s, d: _r(C.win_table(control_runs(s, d)), "pct"),
    "paper_k32_check": paper_k32_check,
    "paper_k32_geomeans": paper_k32_geomeans,
}

# ---------------------------------------------------------------- SQL twins

_H = mix31_sql("CAST({} AS BIGINT)", 0, "duckdb")


def _hash_sql(col: str) -> str:
    return _H.replace("{}", col)


_D = graph_cte("docline")
_HP = "p AS (SELECT pos, CAST(" + _hash_sql("pos") + " % {k} AS INTEGER) AS block FROM v)"
_RANGE = f"p AS (SELECT pos, CAST(pos * {K} // (SELECT count(*) FROM v) AS INTEGER) AS block FROM v)"
_CUT = "x AS (SELECT g.*, a.block AS bi, b.block AS bj FROM g JOIN p a ON g.src = a.pos JOIN p b ON g.dst = b.pos)"
_SIDES = "y AS (SELECT src AS pos, bi AS own, bj AS other FROM x WHERE bi <> bj UNION ALL SELECT dst, bj, bi FROM x WHERE bi <> bj)"
_CLASS = f"c AS (SELECT src // {DELTA} AS batch_id, src AS pos, dst AS other, 'intra' AS class, weight AS w FROM g WHERE src // {DELTA} = dst // {DELTA} UNION ALL SELECT src // {DELTA}, src, dst, 'forward', weight FROM g WHERE src // {DELTA} <> dst // {DELTA} UNION ALL SELECT dst // {DELTA}, dst, src, 'backward', weight FROM g WHERE src // {DELTA} <> dst // {DELTA})"
_LOCAL = f"pos - batch_id * {DELTA}"
_SIZE = f"least({DELTA}, (SELECT count(*) FROM v) - batch_id * {DELTA})"
_INSIDE = f"SELECT batch_id, {_LOCAL} AS a, other - batch_id * {DELTA} AS b, w FROM c WHERE class = 'intra'"
_BACK = "SELECT batch_id, c.pos - batch_id * %d AS a, %s + p.block AS b, w FROM c JOIN p ON c.other = p.pos WHERE class {}" % (DELTA, _SIZE)
_REPS = "f AS (SELECT * FROM c WHERE class = 'forward'), r AS (SELECT batch_id, other AS ghost_pos, arg_min(pos, " + mix31_sql("CAST(other * 1000003 + pos AS BIGINT)", SEED, "duckdb") + " * 1000000 + pos) AS rep FROM f GROUP BY 1, 2)"
_GHOST = f"SELECT f.batch_id, rep - f.batch_id * {DELTA}, pos - f.batch_id * {DELTA}, w / 2 FROM f JOIN r ON f.batch_id = r.batch_id AND f.other = r.ghost_pos"
_MERGED = "SELECT batch_id, CAST(least(a, b) AS INTEGER) AS a, CAST(greatest(a, b) AS INTEGER) AS b, sum(w) AS w FROM u WHERE a <> b GROUP BY 1, 2, 3"
_HALF = "h AS (SELECT src, dst, weight FROM g UNION ALL SELECT dst, src, weight FROM g)"
_LOADS = "ld AS (SELECT block, CAST(count(*) AS DOUBLE) AS load FROM p GROUP BY block)"
_SCALE = "sc AS (SELECT 1.5 * (sqrt(CAST({k} AS DOUBLE)) * (SELECT count(*) FROM g) / ((SELECT count(*) FROM v) * sqrt(CAST((SELECT count(*) FROM v) AS DOUBLE)))) AS q)"
_CONN = "cn AS (SELECT h.src AS pos, p.block, sum(weight) AS conn FROM h JOIN p ON h.dst = p.pos GROUP BY 1, 2)"


def _lp_sql(rounds: int) -> str:
    steps = ["l0 AS (SELECT pos, pos AS label FROM v)"]
    for i in range(rounds):
        steps.append(f"t{i} AS (SELECT h.src AS pos, l.label, sum(weight) AS s FROM h JOIN l{i} l ON h.dst = l.pos GROUP BY 1, 2)")
        steps.append(f"l{i + 1} AS (SELECT pos, label FROM (SELECT *, row_number() OVER (PARTITION BY pos ORDER BY s DESC, label) AS r FROM t{i}) WHERE r = 1)")
    return f"WITH {_D}, {_HALF}, {', '.join(steps)} SELECT pos, label FROM l{rounds}"


def greedy_sql(cte: str, k: int, objective: str = "penalty_gain", passes: int = 1, eps: str = "1.03", weight: str = "1.0") -> str:
    """One-vertex greedy as a recursive query that carries all blocks and loads; a later pass takes a vertex out first."""
    score = "z_conn - c * (q * sqrt(loads[i + 1]))" if objective == "penalty_gain" else "z_conn * (1 - loads[i + 1] / lmax)"

    def one(name: str, start: str, near: str, own: str) -> str:
        conn = "coalesce(list_sum(list_transform(list_filter(ns, lambda y: blocks[y.o + 1] = i), lambda y: y.w)), 0)"
        pick = f"list_sort(list_filter(list_transform(range({k}), lambda i: {{'s': -({score.replace('z_conn', conn)}), 'l': loads[i + 1], 'i': i}}), lambda z: z.l + c <= lmax))[1].i"
        return f"""{name}(pos, blocks, loads) AS ({start} UNION ALL
  SELECT pos + 1, list_concat(list_concat(blocks[1:pos + 1], [x]), blocks[pos + 3:]), list_transform(range({k}), lambda i: loads[i + 1] + CASE WHEN i = x THEN c ELSE 0.0 END)
  FROM (SELECT pos, blocks, loads, c, CAST({pick} AS INTEGER) AS x FROM (
    SELECT {name}.pos, blocks, {own} AS loads, nw.w AS c, coalesce(nb.ns, []) AS ns, sc.q, lim.lmax FROM sc, lim, {name} JOIN nw ON nw.pos = {name}.pos + 1 LEFT JOIN {near} nb ON nb.pos = {name}.pos + 1)))"""

    zero = f"SELECT CAST(-1 AS BIGINT), CAST(list_transform(range((SELECT count(*) FROM v)), lambda i: -1) AS INTEGER[]), CAST(list_transform(range({k}), lambda i: 0.0) AS DOUBLE[])"
    parts = [one("s1", zero, "back", "loads")]
    for i in range(2, passes + 1):
        parts.append(one(f"s{i}", f"SELECT CAST(-1 AS BIGINT), blocks, loads FROM s{i - 1} WHERE pos = (SELECT count(*) - 1 FROM v)", "allnb", f"list_transform(range({k}), lambda i: loads[i + 1] - CASE WHEN i = blocks[s{i}.pos + 2] THEN nw.w ELSE 0.0 END)"))
    return f"""WITH RECURSIVE {cte}, {_SCALE.format(k=k)}, nw AS (SELECT pos, CAST({weight} AS DOUBLE) AS w FROM v), lim AS (SELECT CAST(ceil(CAST({eps} AS DECIMAL(9, 4)) * CAST(sum(w) AS BIGINT) / {k}) AS DOUBLE) AS lmax FROM nw), {_HALF},
allnb AS (SELECT src AS pos, list({{'o': dst, 'w': weight}} ORDER BY dst) AS ns FROM h GROUP BY src), back AS (SELECT dst AS pos, list({{'o': src, 'w': weight}} ORDER BY src) AS ns FROM g GROUP BY dst),
{', '.join(parts)}
SELECT CAST(i AS BIGINT) AS pos, blocks[i + 1] AS block FROM (SELECT blocks, unnest(range(len(blocks))) AS i FROM s{passes} WHERE pos = (SELECT count(*) - 1 FROM v))"""


_TRADE = graph_cte("tradeflow").replace("CAST(1 AS DOUBLE) AS weight", "e.weight AS weight")
_TINY = f"{_D.replace(' v AS', ' v0 AS').replace('JOIN v ', 'JOIN v0 ').replace(' g AS', ' g0 AS')}, v AS (SELECT pos // 8 AS pos, count(*) AS size FROM v0 GROUP BY 1), g AS (SELECT least(src // 8, dst // 8) AS src, greatest(src // 8, dst // 8) AS dst, sum(weight) AS weight FROM g0 WHERE src // 8 <> dst // 8 GROUP BY 1, 2)"


def _runs_sql(ks=_KS) -> str:
    parts = []
    for name in _GRAPHS:
        e = f"(SELECT g.*, k.k, (SELECT count(*) FROM v) AS n FROM g, (VALUES {', '.join(f'({k})' for k in ks)}) k(k))"
        one = lambda alg, test: f"SELECT '{alg}' AS alg, '{name}' AS graph, k, CAST(count(*) FILTER (WHERE {test}) AS DOUBLE) AS score FROM {e} GROUP BY k"  # noqa: B023, E731
        parts.append("(WITH " + graph_cte(name) + " " + " UNION ALL ".join([one("hash", f"{_hash_sql('src')} % k <> {_hash_sql('dst')} % k"), one("round_robin", "src % k <> dst % k"), one("range", "src * k // n <> dst * k // n")]) + ")")
    return " UNION ALL ".join(parts)


_RUNS = f"WITH runs AS ({_runs_sql()})"
_RUNS32 = f"WITH t AS ({_runs_sql((32,))})"
_VARIANTS = ", ".join(f"('{g}', '{x}', true, true, true, true, true)" for g in ("docline", "fkforest", "rgg", "convchain") for x in ("extended", "basic", "restreamed", "internal", "discount"))

#: Buffers of the twins: an eighth of the vertices, 64 at least.
_EIGHTH = "greatest(64, n // 8)"

ORACLES = {
    "cut_hash_by_k": " UNION ALL ".join(
        f"(WITH {graph_cte(n)} SELECT '{n}' AS graph, k.k, count(*) FILTER (WHERE {_hash_sql('src')} % k <> {_hash_sql('dst')} % k) AS cut, count(*) AS m, round(100 * count(*) FILTER (WHERE {_hash_sql('src')} % k <> {_hash_sql('dst')} % k) / count(*), 6) AS cut_pct FROM g, (VALUES (2), (4), (8), (16), (32)) k(k) GROUP BY k.k)"
        for n in ("docline", "fkforest", "userprop")
    ),
    "balance_hash": f"WITH {graph_cte('fkforest')}, {_HP.format(k=8)}, l AS (SELECT block, count(*) AS n FROM p GROUP BY 1), t AS (SELECT count(*) AS n FROM v) SELECT CAST(max(l.n) AS DOUBLE) AS max_load, round(max(l.n) / (any_value(t.n) / 8) - 1, 6) AS imbalance, CAST(ceil(CAST(1.03 AS DECIMAL(5, 2)) * any_value(t.n) / 8) AS DOUBLE) AS lmax, max(l.n) <= ceil(CAST(1.03 AS DECIMAL(5, 2)) * any_value(t.n) / 8) AS feasible FROM l, t",
    "block_load_hash": f"WITH {graph_cte('fkforest')}, {_HP.format(k=8)} SELECT block, CAST(count(*) AS DOUBLE) AS load FROM p GROUP BY 1",
    "quotient_hash": f"WITH {_D}, {_HP.format(k=8)}, {_CUT} SELECT least(bi, bj) AS bi, greatest(bi, bj) AS bj, sum(weight) AS w, count(*) AS cnt FROM x WHERE bi <> bj GROUP BY 1, 2",
    "boundary_hash": f"WITH {_D}, {_HP.format(k=2)}, {_CUT}, {_SIDES} SELECT DISTINCT pos, own AS block FROM y",
    "comm_volume_hash": f"WITH {_D}, {_HP.format(k=8)}, {_CUT}, {_SIDES} SELECT CAST(coalesce(sum(n), 0) AS BIGINT) AS volume FROM (SELECT pos, count(DISTINCT other) AS n FROM y GROUP BY pos)",
    "fragmentation_hash": f"WITH RECURSIVE {_D}, {_HP.format(k=4)}, {_CUT}, z AS (SELECT src AS a, dst AS b FROM x WHERE bi = bj UNION ALL SELECT dst, src FROM x WHERE bi = bj), reach(pos, r) AS (SELECT pos, pos FROM v UNION SELECT reach.pos, z.b FROM reach JOIN z ON reach.r = z.a), lab AS (SELECT pos, min(r) AS label FROM reach GROUP BY pos), sz AS (SELECT block, label, count(*) AS n FROM lab JOIN p USING (pos) GROUP BY 1, 2) SELECT block, count(*) AS pieces, max(n) AS largest FROM sz GROUP BY block",
    "cut_controls": f"WITH {_D}, t AS (SELECT count(*) AS n FROM v) SELECT 'range' AS alg, count(*) FILTER (WHERE src * 8 // t.n <> dst * 8 // t.n) AS cut_edges, round(100 * count(*) FILTER (WHERE src * 8 // t.n <> dst * 8 // t.n) / count(*), 6) AS cut_pct FROM g, t UNION ALL SELECT 'round_robin', count(*) FILTER (WHERE src % 8 <> dst % 8), round(100 * count(*) FILTER (WHERE src % 8 <> dst % 8) / count(*), 6) FROM g",
    "model_basic": f"WITH {_D}, {_RANGE}, {_CLASS}, u AS ({_INSIDE} UNION ALL {_BACK.format(chr(61) + chr(39) + 'backward' + chr(39))}) {_MERGED}",
    "model_extended": f"WITH {_D}, {_RANGE}, {_CLASS}, {_REPS}, u AS ({_INSIDE} UNION ALL {_BACK.format(chr(61) + chr(39) + 'backward' + chr(39))} UNION ALL {_GHOST}) {_MERGED}",
    "model_restream": f"WITH {_D}, {_RANGE}, {_CLASS}, u AS ({_INSIDE} UNION ALL {_BACK.format('<>' + chr(39) + 'intra' + chr(39))}) {_MERGED}",
    "model_nodes": f"WITH {_D}, {_RANGE}, {_CLASS}, {_REPS}, gw AS (SELECT batch_id, rep, CAST(count(*) AS DOUBLE) AS w FROM r GROUP BY 1, 2) SELECT pos // {DELTA} AS batch_id, CAST(pos % {DELTA} AS INTEGER) AS local, 1 + coalesce(w, 0) AS weight, CAST(NULL AS INTEGER) AS fixed_block FROM v LEFT JOIN gw ON gw.rep = v.pos UNION ALL SELECT batch_id, CAST({_SIZE} + block AS INTEGER), CAST((SELECT count(*) FROM p WHERE p.block = b.block AND p.pos < batch_id * {DELTA}) AS DOUBLE), block FROM (SELECT DISTINCT pos // {DELTA} AS batch_id FROM v WHERE pos >= {DELTA}), (SELECT CAST(unnest(range({K})) AS INTEGER) AS block) b",
    "ghost_reps": f"WITH {_D}, {_CLASS}, {_REPS} SELECT batch_id, ghost_pos, rep FROM r",
    "contract_once": f"WITH {_D} SELECT least(src // 4, dst // 4) AS src, greatest(src // 4, dst // 4) AS dst, sum(weight) AS weight FROM g WHERE src // 4 <> dst // 4 GROUP BY 1, 2",
    "gain_table": f"WITH {_D}, {_RANGE}, {_HALF}, {_LOADS}, {_SCALE.format(k=K)}, {_CONN} SELECT pos, block, conn, round(conn - (SELECT q FROM sc) * sqrt(load), 6) AS gain FROM cn JOIN ld USING (block)",
    "gain_additivity": f"WITH {_D}, {_RANGE}, {_HALF}, {_LOADS}, {_SCALE.format(k=K)}, {_CONN}, mg AS (SELECT pos // 4 AS coarse, block, sum(conn) AS conn FROM cn GROUP BY 1, 2), sz AS (SELECT pos // 4 AS coarse, count(*) AS c FROM v GROUP BY 1), hm AS (SELECT DISTINCT pos // 4 AS coarse, block FROM p) SELECT coarse, block, round(conn - c * ((SELECT q FROM sc) * sqrt(load)), 6) AS merged, true AS additive FROM mg JOIN sz USING (coarse) JOIN ld USING (block) ANTI JOIN hm USING (coarse, block)",
    "lp_sync_round": _lp_sql(1),
    "lp_sync_rounds3": _lp_sql(3),
    "refine_sync_round": f"WITH {_D}, {_RANGE}, {_HALF}, {_LOADS}, {_SCALE.format(k=K)}, {_CONN}, s AS (SELECT cn.pos, cn.block, p.block AS now, conn, load - CASE WHEN cn.block = p.block THEN 1 ELSE 0 END AS l FROM cn JOIN ld USING (block) JOIN p ON p.pos = cn.pos), o AS (SELECT *, row_number() OVER (PARTITION BY pos ORDER BY round(conn - (SELECT q FROM sc) * sqrt(l), 9) DESC, block) AS r FROM s WHERE l + 1 <= ceil(CAST(1.2 AS DECIMAL(5, 2)) * (SELECT count(*) FROM v) / {K})) SELECT pos, now AS block, block AS target FROM o WHERE r = 1",
    "pgg_docline": greedy_sql(_D, 8),
    "cdg_docline": greedy_sql(_D, 8, "capacity_discount"),
    "pgg2_docline": greedy_sql(_D, 8, passes=2),
    "cdg2_docline": greedy_sql(_D, 8, "capacity_discount", 2),
    "pgg_tradeflow": greedy_sql(_TRADE, 4),
    "bmp_delta1_docline": greedy_sql(_D, 8),
    "initial_tiny": greedy_sql(_TINY, K, eps="1.5", weight="size"),
    "bmp_invariants": f"SELECT * FROM (VALUES {_VARIANTS}) t(graph, variant, covers, in_range, feasible, loads_add_up, cut_twice)",
    "bmp_docline": multilevel_sql(_D, 8, _EIGHTH),
    "bmp_docline_basic": multilevel_sql(_D, 8, _EIGHTH, "basic"),
    "bmp_docline_internal": multilevel_sql(_D, 8, "n"),
    "bmp_docline_discount": multilevel_sql(_D, 8, _EIGHTH, objective="capacity_discount"),
    "bmp_docline_lowest_ties": multilevel_sql(_D, 8, "n", tie="lowest"),
    "bmp_docline_restreamed": multilevel_sql(_D, 8, _EIGHTH, after=multilevel_sql(_D, 8, _EIGHTH)),
    "bmp_docline_driver_loop": multilevel_sql(_D, 8, _EIGHTH),
    "bmp_docline_k4": multilevel_sql(_D, 4, _EIGHTH, x=2, refine=2, rounds=3),
    "lanes_feasible": "SELECT true AS feasible, true AS covers",
    "bmp_docline_budget": "SELECT true AS within, true AS feasible, true AS covers",
    "control_runs": f"{_RUNS} SELECT * FROM runs",
    "improvement_tbl": f"{_RUNS} SELECT a.alg, graph, k, round((b.score / a.score - 1) * 100, 6) AS improvement FROM runs a JOIN runs b USING (graph, k) WHERE b.alg = 'hash'",
    "relative_tbl": f"{_RUNS} SELECT a.alg, graph, k, round(a.score / b.score, 6) AS relative FROM runs a JOIN runs b USING (graph, k) WHERE b.alg = 'hash'",
    "ratio_tbl": f"{_RUNS} SELECT alg, graph, k, round(score / max(score) OVER (PARTITION BY graph, k), 6) AS ratio FROM runs",
    "profile_tbl": f"{_RUNS}, n AS (SELECT *, score / min(score) OVER (PARTITION BY graph, k) AS r FROM runs) SELECT alg, tau, round(count(*) FILTER (WHERE r <= tau) / count(*), 6) AS share FROM n, (VALUES (CAST(1.0 AS DOUBLE)), (1.05), (1.25), (2.0), (10.0)) t(tau) GROUP BY 1, 2",
    "geomean_tbl": f"{_RUNS} SELECT alg, k, round(exp(avg(ln(greatest(score, 1.0)))), 6) AS geomean, bool_or(score < 1) AS floored FROM runs GROUP BY 1, 2",
    "wins_tbl": f"{_RUNS}, n AS (SELECT *, rank() OVER (PARTITION BY graph, k ORDER BY score) AS r FROM runs) SELECT alg, count(*) FILTER (WHERE r = 1) AS wins, round(100 * count(*) FILTER (WHERE r = 1) / count(*), 6) AS pct FROM n GROUP BY alg",
    "paper_k32_check": f"{_RUNS32} SELECT a.alg AS setup, b.alg AS other, count(*) FILTER (WHERE a.score < b.score) AS wins, count(*) AS graphs FROM t a JOIN t b USING (graph) WHERE a.alg IN ('range', 'round_robin') AND b.alg NOT IN ('range', 'round_robin') GROUP BY 1, 2",
    "paper_k32_geomeans": f"{_RUNS32} SELECT alg, round(exp(avg(ln(greatest(score, 1.0)))), 4) AS geomean FROM t GROUP BY alg",
}
