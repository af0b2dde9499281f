"""Comparison measures on a table small enough to do by hand; files, Python functions."""

import pytest
from pyspark.sql import functions as F

from cutstream.functions import python_udfs
from cutstream.operators import compare as C
from cutstream.operators import measures as M
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph
from cutstream.sources import files


@pytest.fixture(scope="module")
def toy(spark):
    return spark.createDataFrame([("a", "g", 2, 10.0), ("b", "g", 2, 20.0), ("a", "h", 2, 8.0), ("b", "h", 2, 4.0), ("a", "g", 4, 30.0), ("b", "g", 4, 30.0)], "alg string, graph string, k int, score double")


def test_by_hand(toy):
    gained = {(r.alg, r.graph, r.k): r.improvement for r in C.improvement(toy, "b").collect()}
    assert gained[("a", "g", 2)] == pytest.approx(100) and gained[("a", "h", 2)] == pytest.approx(-50)
    assert {(r.alg, r.graph, r.k): r.ratio for r in C.ratio_to_max(toy).collect()}[("a", "g", 2)] == 0.5
    share = {(r.alg, r.tau): r.share for r in C.performance_profile(toy, [1.0, 2.0]).collect()}
    assert share[("a", 1.0)] == pytest.approx(2 / 3) and share[("b", 2.0)] == 1
    assert {r.alg: r.wins for r in C.win_table(toy).collect()} == {"a": 2, "b": 2}
    mean = {(r.alg, r.k): r.geomean for r in C.aggregate_runs(toy.withColumn("seed", F.lit(1))).collect()}
    assert mean[("a", 2)] == pytest.approx(80**0.5)


def test_published_geometric_means(spark):
    got = {r.alg: r.g for r in C.published_k32(spark).groupBy("alg").agg(F.exp(F.avg(F.log("score"))).alias("g")).collect()}
    for alg, value in (("bmp_int", 7.73), ("bmp_32k", 13.49), ("pgg2", 20.64), ("pgg", 24.75), ("cdg", 24.00), ("hp", 94.36)):
        assert got[alg] == pytest.approx(value, abs=0.01)


def test_files(spark, sf, tmp_path):
    g = Graph.load(spark, sf, "docline")
    files.write_edge_list(g.edges, f"{tmp_path}/edges")
    back = files.read_edge_list(spark, f"{tmp_path}/edges", "csv")
    assert back.count() == g.m and back.agg(F.sum("a"), F.sum("b")).first() == g.edges.agg(F.sum("src"), F.sum("dst")).first()
    (tmp_path / "t.txt").write_text("# c\n1 2\n2 3 0.5\n")
    assert sorted(map(tuple, files.read_edge_list(spark, f"{tmp_path}/t.txt", "text").collect())) == [(1, 2, 1.0), (2, 3, 0.5)]
    files.write_adjacency_text(g, f"{tmp_path}/a.graph")
    adj = files.read_adjacency_text(spark, f"{tmp_path}/a.graph", split=200)
    assert adj.count() == g.n and adj.rdd.getNumPartitions() > 1
    assert adj.select("pos", F.explode("nbrs").alias("o")).where("pos < o").exceptAll(g.edges.select("src", "dst")).count() == 0
    out = E.place_hash(g, 4)
    files.write_assignment(out, f"{tmp_path}/out")
    assert spark.read.parquet(f"{tmp_path}/out").count() == g.n
    files.write_by_block(g.nodes.select("key"), out.join(g.nodes, "pos").select("key", "block"), "key", f"{tmp_path}/blocks", 4)
    assert spark.read.parquet(f"{tmp_path}/blocks").where("block = 1").count() == out.where("block = 1").count()


def test_python_functions(spark):
    python_udfs.register(spark)
    assert spark.sql("SELECT round(geometric_mean(x), 6) FROM VALUES (2D), (8D) t(x)").first()[0] == 4
    assert spark.sql("SELECT round(imbalance(x), 6) FROM VALUES (1D), (3D) t(x)").first()[0] == 0.5
    assert spark.sql("SELECT round(cosine(a, b), 6) FROM VALUES (array(1D, 0D), array(1D, 1D)) t(a, b)").first()[0] == 0.707107
    assert sorted(map(tuple, spark.sql("SELECT * FROM adjacency_lines(4L, '1 3')").collect())) == [(4, 0), (4, 2)]
    assert len(spark.sql("SELECT * FROM neighbour_pairs(array(1L, 2L, 3L), 10)").collect()) == 3
    assert spark.sql("SELECT capacity(9L, 2, 0.03BD)").first()[0] == 5
    assert spark.sql("SELECT round(gain(2D, 1D, 4D, 0.5D), 6)").first()[0] == 0.5


def test_messages_of_two_hops(spark):
    # a path 0-1-2-3 over blocks 0, 0, 1, 2: foreign blocks are 0, 1, 2, 1 and degrees 1, 2, 2, 1
    edges = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0), (2, 3, 1.0)], "src long, dst long, weight double")
    placed = spark.createDataFrame([(0, 0), (1, 0), (2, 1), (3, 2)], "pos long, block int")
    r = M.query_messages(edges, placed).first()
    assert (r.one_hop, r.two_hop) == (4, 1 * 3 + 2 * 3 + 1 * 2)
    r = M.query_messages(edges.limit(0), placed).first()
    assert (r.one_hop, r.two_hop) == (0, 0)
