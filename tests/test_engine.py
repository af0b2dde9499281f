"""Engines: limiting cases, agreement, order of methods, determinism, edge cases."""

import pytest
from pyspark.sql import functions as F

from cutstream.operators import measures as M
from cutstream.params import PartitionParams
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph
from cutstream.sources import graphs as G


def blocks(df):
    return [r.block for r in df.orderBy("pos").collect()]


def graph_of(spark, pairs, extra=None):
    e = G.clean(spark.createDataFrame([(a, b, 1.0) for a, b in pairs], "a long, b long, weight double"))
    return Graph.from_edges(e, extra=spark.createDataFrame([(x,) for x in extra], "key long") if extra else None)


@pytest.fixture(scope="module")
def rgg(spark):
    return Graph.load(spark, "", "rgg")


@pytest.fixture(scope="module")
def grid(spark):
    return Graph.load(spark, "", "grid")


def cut(g, df):
    return M.edge_cut(g.edges, df, g.n).first()["cut"]


def test_one_vertex_buffers_are_the_one_pass_greedy(rgg):
    p = PartitionParams(k=4, delta=1, model="basic", order="natural")
    small = Graph(rgg.nodes.where("pos < 200"), rgg.edges.where("dst < 200"), 200, rgg.edges.where("dst < 200").count(), 200.0, 0.0)
    assert blocks(E.partition_buffered(small, p).assignment) == blocks(E.place_penalty_gain(small, p))


def test_whole_graph_in_one_buffer_has_no_ghosts(grid):
    p = PartitionParams(k=8, delta=None)
    assert blocks(E.partition_buffered(grid, p).assignment) == blocks(E.partition_buffered(grid, p.with_(model="basic")).assignment)


def test_methods_keep_their_order_on_structured_graphs(rgg, grid):
    for g in (rgg, grid):
        p = PartitionParams(k=8, delta=256)
        by = {n: cut(g, f) for n, f in (("hp", E.place_hash(g, 8)), ("pgg", E.place_penalty_gain(g, p)), ("int", E.partition_buffered(g, p.with_(delta=None)).assignment))}
        assert by["int"] < by["pgg"] < by["hp"]


def test_ghosts_help_on_the_tree(spark, sf):
    g = Graph.load(spark, sf, "fkforest")
    p = PartitionParams(k=8, delta=g.n // 8)
    assert cut(g, E.partition_buffered(g, p).assignment) < 0.5 * cut(g, E.place_penalty_gain(g, p))


def test_restreaming_does_not_lose(rgg):
    got = [cut(rgg, r.assignment) for r in E.pass_results(rgg, PartitionParams(k=8, delta=128), 3)]
    assert got[-1] <= got[0]


def test_all_feasible_and_complete(rgg):
    p = PartitionParams(k=8, delta=200)
    for df in (E.place_penalty_gain(rgg, p), E.place_capacity_discount(rgg, p), E.partition_buffered(rgg, p).assignment, E.partition_buffered(rgg, p.with_(engine="lanes", lanes=3)).assignment):
        assert M.balance(rgg.nodes, df, 8, p.eps, rgg.n).first()["feasible"]
        assert df.select("pos").distinct().count() == df.count() == rgg.n


def test_same_result_for_any_number_of_partitions(spark, grid):
    p = PartitionParams(k=4, delta=100)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    seen = []
    for n in ("1", "7"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        seen.append(blocks(E.partition_buffered(grid, p).assignment))
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert seen[0] == seen[1]


@pytest.mark.parametrize("k", [1, 3, 12])
def test_small_graphs(spark, k):
    g = graph_of(spark, [(0, 1), (1, 2), (2, 0), (5, 9)], extra=[3, 4])
    for p in (PartitionParams(k=k, delta=2), PartitionParams(k=k, delta=100, model="basic"), PartitionParams(k=k, delta=3, passes=2)):
        out = E.partition_buffered(g, p).assignment
        assert out.count() == 7 and out.where(f"block < 0 or block >= {k}").count() == 0


def test_no_edges_and_no_vertices(spark):
    none = spark.createDataFrame([], "src long, dst long, weight double")
    g = Graph.from_edges(none)
    assert g.n == 0 and E.partition_buffered(g, PartitionParams(k=2)).assignment.count() == 0
    lone = Graph.from_edges(none, extra=spark.createDataFrame([(7,)], "key long"))
    assert blocks(E.partition_buffered(lone, PartitionParams(k=2)).assignment) == [0]


def test_cleaning(spark):
    raw = spark.createDataFrame([(1, 2, 1.0), (2, 1, 2.0), (3, 3, 1.0), (None, 4, 1.0)], "a long, b long, weight double")
    assert [tuple(r) for r in G.clean(raw).collect()] == [(1, 2, 3.0)]


def test_weighted_vertices(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    g = Graph.from_edges(G.edges(spark, sf, "docline"), weights=docs.select(F.col("doc_id").alias("key"), F.col("n_chars").cast("double").alias("weight")))
    out = E.partition_buffered(g, PartitionParams(k=3, eps=0.3, delta=20, alpha_basis="weight")).assignment
    assert out.count() == g.n


def test_plans(spark, sf):
    from cutstream.functions.python_udfs import explain_text

    text = explain_text(G.clean(G.copurchase(spark, sf)))
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in text and "CartesianProduct" not in text
    g = Graph.load(spark, sf, "docline")
    assert "BroadcastHashJoin" in explain_text(M.attach_blocks(g.edges, E.place_hash(g, 4), vertices=g.n))
    assert "BroadcastHashJoin" not in explain_text(M.attach_blocks(g.edges, E.place_hash(g, 4), "merge"))


def test_distributed_coarsening(rgg):
    from cutstream.plans.distributed import partition_distributed

    p = PartitionParams(k=8, delta=256)
    out = partition_distributed(rgg, p, 200).assignment
    assert out.select("pos").distinct().count() == rgg.n and cut(rgg, out) < cut(rgg, E.place_penalty_gain(rgg, p))
