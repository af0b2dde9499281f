"""Cases of a review: what failed on large tables or odd inputs."""

import pytest
from pyspark.sql import functions as F

from cutstream import queries_method, queries_relational
from cutstream.operators import compare as C
from cutstream.operators import measures as M
from cutstream.operators import stream_order as S
from cutstream.params import PartitionParams
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph
from cutstream.sources import graphs as G


def test_a_pass_without_cut_edges_has_a_change(spark):
    runs = spark.createDataFrame([("g", 2, i + 1, c, 0.1) for i, c in enumerate((4.0, 0.0, 0.0))], "graph string, k int, pass int, cut double, seconds double")
    assert [r.gained for r in C.pass_trace(runs).orderBy("pass").collect()] == [None, pytest.approx(300), 0.0]


def test_only_hubs_have_several_rows_in_the_vertex_stream(spark):
    edges = spark.createDataFrame([(0, i, 1.0) for i in range(1, 9)] + [(1, 8, 1.0)], "src long, dst long, weight double")
    g = Graph.from_edges(edges)
    rows = {(r.pos, r.chunk): r.degree for r in S.adjacency(g, 4).collect()}
    assert sorted(k[0] for k in rows) == [0, 0, 0, *range(1, 9)] and rows[(1, 0)] == rows[(8, 0)] == 2
    assert sorted(n for (pos, _), n in rows.items() if pos == 0) == [1, 3, 4]
    assert S.adjacency(g, None).where("pos = 0").first().degree == 8


def test_invariants_reach_the_driver_as_tables(spark, monkeypatch):
    from cutstream.functions.python_udfs import explain_text

    g = Graph.from_edges(spark.createDataFrame([(i, i + 1, 1.0) for i in range(64)], "src long, dst long, weight double"))
    monkeypatch.setattr(queries_method.Graph, "load", lambda s, d, name: g)
    monkeypatch.setattr(E, "partition_buffered", lambda g, p: E.PartitionResult(E.place_range(g, p.k), {}))
    out = queries_method.bmp_invariants(spark, "")
    assert out.count() == 20 and all(r.covers and r.cut_twice and r.loads_add_up for r in out.collect())
    assert "Join" not in explain_text(out)


def test_pairs_by_tiles_are_those_of_groups(spark):
    rows = [(g, (g * 7 + 3 * i) % 23) for g in range(9) for i in range(8)] + [(1, 4), (None, 2), (2, None)]
    df = spark.createDataFrame(rows, "g long, x long")
    slow = G.clean(G.pairs_within(df, "g", "x"))
    for tile_rows in (10, 1000):
        fast = G.pair_counts(df, "g", "x", tile_rows)
        assert sorted(map(tuple, fast.collect())) == sorted(map(tuple, slow.collect()))


def test_pairs_are_not_shuffled(spark, sf):
    from cutstream.functions.python_udfs import explain_text

    text = explain_text(queries_relational.QUERIES["op_self_join_pairs"](spark, sf))
    assert "MapInArrow" in text and "Generate posexplode" not in text


@pytest.mark.parametrize("name", ["g_grid", "g_er", "g_chords", "g_rgg", "g_rgg_random", "op_filter_loops", "op_join_range"])
def test_generated_graphs_come_from_a_table(spark, tmp_path, name):
    from cutstream import catalog

    def rows(n):
        d = f"{tmp_path}/{n}"
        spark.range(n).select(F.col("id").alias("c_custkey"), (F.col("id") * 37 % 9000).cast("double").alias("c_acctbal")).write.parquet(f"{d}/customer.parquet")
        spark.range(n).select(F.col("id").alias("o_orderkey"), (F.col("id") * 3 % n).alias("o_custkey")).write.parquet(f"{d}/orders.parquet")
        return [tuple(r) for r in catalog.queries()[name](spark, d).collect()]

    assert rows(40) != rows(90)


def test_large_assignments_are_not_broadcast(spark, monkeypatch):
    from cutstream.functions.python_udfs import explain_text

    g = Graph.from_edges(spark.createDataFrame([(i, i + 1, 1.0) for i in range(64)], "src long, dst long, weight double"))
    assert "BroadcastHashJoin" in explain_text(M.attach_blocks(g.edges, E.place_hash(g, 4), "broadcast", g.n))
    monkeypatch.setattr(M, "BROADCAST_VERTICES", 10)
    out = M.attach_blocks(g.edges, E.place_hash(g, 4), "broadcast", g.n)
    assert "BroadcastHashJoin" not in explain_text(out) and out.count() == 64


def test_nearest_of_many_copies(spark, tmp_path):
    vectors = [[1.0, 0.0], [1.0, 0.001], [0.0, 1.0]]
    rows = [(i, vectors[i % 2] if i < 40 else vectors[2], 0) for i in range(42)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(3).write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {}
    for r in G.knn(spark, str(tmp_path), rows=5).collect():
        got.setdefault(r.a, []).append(r.b)
    assert sorted(got[10]) == [0, 1, 2] and sorted(got[0]) == [1, 2, 3]
    assert 41 in got[40] and all(len(x) == 3 for x in got.values())


@pytest.mark.parametrize("lanes", [1, 2])
def test_runs_of_small_buffers_place_as_steps_do(spark, monkeypatch, lanes):
    g = Graph.load(spark, "", "chords")
    p = PartitionParams(k=4, delta=96, engine="lanes", lanes=lanes)
    got = []
    for size in (1, 500, 1 << 15):  # a job a step, several steps a job, all in one
        monkeypatch.setattr(E, "RUN_VERTICES", size)
        got.append(sorted(tuple(r) for r in E.partition_buffered(g, p).assignment.collect()))
    assert len(got[0]) == g.n and got[0] == got[1] == got[2]


def test_micro_batches_of_several_buffers(spark, tmp_path):
    from cutstream.streaming import live

    g = Graph.load(spark, "", "chords")
    p = PartitionParams(k=4, delta=96)
    expected = sorted(map(tuple, E.partition_buffered(g, p).assignment.select("pos", "block").collect()))
    files = live.write_vertex_files(g, p.delta, f"{tmp_path}/in", 500)
    assert files == 3  # five buffers each
    out = live.partition_stream(spark, live.stream_vertices(spark, f"{tmp_path}/in"), g.n, g.m, p, f"{tmp_path}/mark")
    assert sorted(map(tuple, out.select("pos", "block").collect())) == expected


def test_a_large_model_takes_little_memory():
    import tracemalloc

    import numpy as np

    from cutstream.params import lmax
    from cutstream.plans import kernel as K

    n = 100_000
    a = np.arange(n - 1)
    p, most = PartitionParams(k=8), lmax(n, 8, 0.03)
    block = np.arange(n) * 8 // n
    tracemalloc.start()
    levels, maps = K.coarsen(K.Level.of(np.ones(n), a, a + 1, np.ones(n - 1)), p.with_(coarsen_rounds=1), most)
    conn = K.connections(n, a, block[a + 1], np.ones(n - 1), 8)
    found, fits = K.multilevel(levels, maps, conn, K.Blocks(p, 0.01, most), p.with_(refine_rounds=1))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert fits and len(found) == n and peak < 300 * n


def test_models_travel_in_small_parts(monkeypatch):
    import numpy as np

    from cutstream.plans import kernel as K

    a = np.arange(999)
    model = (5, np.ones(1000, np.uint8), [K.Level.of(np.ones(1000), a, a + 1, np.full(999, 0.5))], [], (np.zeros(1001, np.int64), a[:0], a[:0]), a[:0])
    monkeypatch.setattr(E, "CHUNK", 1000)
    parts = list(E.packed(model))
    assert len(parts) == parts[0][1] > 10 and all(len(x) <= 1000 for *_, x in parts)
    start, true, (level,), *_ = E.unpacked(b"".join(x for *_, x in parts))
    assert start == 5 and true.dtype == np.float64 and level.adj.tolist() == model[2][0].adj.tolist() and level.w.dtype == np.float32


def test_cells_of_a_large_graph_run_one_at_a_time(spark, monkeypatch):
    import time

    from cutstream import workloads as W

    g = Graph.from_edges(spark.createDataFrame([(i, i + 1, 1.0) for i in range(8)], "src long, dst long, weight double"))
    running, most = [], []

    def slow(g, p):
        running.append(1)
        most.append(len(running))
        time.sleep(0.5)
        running.pop()
        return E.place_range(g, p.k)

    monkeypatch.setitem(W.METHODS, "pgg", slow)
    monkeypatch.setattr(W, "LARGE_GRAPH", 1)
    assert W.run_cells(spark, [(g, "pgg", "pgg", PartitionParams(k=2))] * 3).count() == 3 and max(most) == 1


@pytest.mark.parametrize("objective", ["penalty_gain", "capacity_discount"])
@pytest.mark.parametrize("tie", ["random", "lowest"])
def test_loops_in_java_and_in_python_are_the_same(monkeypatch, tie, objective):
    import numpy as np

    from cutstream.params import alpha, lmax
    from cutstream.plans import kernel as K
    from cutstream.plans import loops

    if loops.classes() is None:
        pytest.skip("no Java compiler")
    r = np.random.default_rng(7)
    n, m, k = 300, 900, 5
    a, b, w = r.integers(0, n, m), r.integers(0, n, m), r.choice([0.5, 1.0, 300.5], m)
    ends, near = np.sort(r.integers(0, n, 200)), r.integers(-1, k, 200)
    p, within = PartitionParams(k=k, tie=tie, objective=objective), r.integers(0, k, n) if tie == "lowest" else None

    def run(large):
        monkeypatch.setattr(loops, "LARGE", large)
        levels, maps = K.coarsen(K.Level.of(np.ones(n), a, b, w), p, lmax(n, k, 0.03), within)
        state = K.Blocks(p, alpha(n, m, k, 1.5), lmax(n, k, 0.03))
        block, fits = K.multilevel(levels, maps, K.connections(n, ends, near, np.ones(200), k), state, p, within)
        return [[x.tolist() for x in (y.weight, y.ptr, y.adj, y.w)] for y in levels], [x.tolist() for x in maps], block.tolist(), fits, state.load, state.penalty

    assert run(0) == run(1 << 60)


def test_greedies_in_java_and_in_python_are_the_same(spark, monkeypatch):
    from cutstream.plans import kernel as K
    from cutstream.plans import loops

    if loops.classes() is None:
        pytest.skip("no Java compiler")
    g = Graph.load(spark, "", "chords")
    for blocks, p in ((K.Blocks, PartitionParams(k=5)), (K.AllBlocks, PartitionParams(k=5)), (K.Blocks, PartitionParams(k=5, objective="capacity_discount"))):
        got = []
        for worth in (True, False):
            monkeypatch.setattr(loops, "worth", lambda size, worth=worth: worth)
            one = E.place_greedy(g, p, blocks=blocks).cache()
            got += [sorted(map(tuple, x.collect())) for x in (one, E.place_greedy(g, p, one, blocks))]
        assert len(got[0]) == g.n and got[:2] == got[2:]


def test_rows_of_a_model_are_sorted_by_one_number(spark):
    from cutstream.functions.python_udfs import explain_text

    g = Graph.load(spark, "", "grid")
    buffers = E.Buffers(128)
    text = explain_text(E.coarsen_rows(E.buffer_rows(g, buffers), PartitionParams(k=4), buffers, 300.0, False, 8, g.n))
    assert g.whole and "shiftleft" in text


def test_a_greedy_runs_beside_a_model(spark, monkeypatch):
    import threading

    from cutstream import workloads as W

    g = Graph.from_edges(spark.createDataFrame([(i, i + 1, 1.0) for i in range(8)], "src long, dst long, weight double"))
    both = threading.Barrier(2, timeout=60)

    def meet(g, p):
        both.wait()
        return E.place_range(g, p.k)

    for name in ("pgg", "bmp"):
        monkeypatch.setitem(W.METHODS, name, meet)
    monkeypatch.setattr(W, "LARGE_GRAPH", 1)
    assert [r.alg for r in W.run_cells(spark, [(g, x, x, PartitionParams(k=2)) for x in ("bmp", "bmp", "pgg", "pgg")]).collect()] == ["bmp", "bmp", "pgg", "pgg"]


def test_one_large_graph_is_measured_beside_the_next_placement(spark, monkeypatch):
    import threading

    from cutstream import workloads as W

    g = Graph.from_edges(spark.createDataFrame([(i, i + 1, 1.0) for i in range(64)], "src long, dst long, weight double"))
    threads = set()

    def placed(g, p):
        threads.add(threading.get_ident())
        return E.PartitionResult(E.place_range(g, p.k), {})

    monkeypatch.setattr(queries_method.Graph, "load", lambda s, d, name: g)
    monkeypatch.setattr(E, "partition_buffered", placed)
    monkeypatch.setattr(W, "LARGE_GRAPH", 1)
    assert queries_method.bmp_invariants(spark, "").count() == 20 and len(threads) == 2


def test_both_placements_of_the_application_are_made_at_once(spark, sf, monkeypatch):
    import threading

    from cutstream import workloads as W

    both = threading.Barrier(2, timeout=60)
    for name in ("hp", "bmp"):
        monkeypatch.setitem(W.METHODS, name, lambda g, p: both.wait() * 0 or E.place_range(g, p.k))
    rows = W.application(spark, sf).collect()
    assert [r.alg for r in rows] == ["hp", "bmp"] and rows[0][1:] == rows[1][1:]
