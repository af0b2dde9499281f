"""Measures of a partition: cut, balance, quotient graph, boundary, communication, fragments."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutstream.params import lmax
from cutstream.scratch import materialise

#: Vertices up to which an assignment is broadcast to the edges (12 bytes each); beyond, the join shuffles.
BROADCAST_VERTICES = 2_000_000


def attach_blocks(edges: DataFrame, assignment: DataFrame, hint: str | None = None, vertices: int | None = None) -> DataFrame:
    """edges with bi, bj: the blocks of their ends. A hint forces a join strategy; vertices, if known and few, broadcasts.

    What has more vertices than a driver can hold is joined by a shuffle, whatever the hint.
    """
    side = lambda name, block: assignment.select(F.col("pos").alias(name), F.col("block").alias(block))
    a, b = side("src", "bi"), side("dst", "bj")
    if hint is None and vertices is not None and vertices <= BROADCAST_VERTICES:
        hint = "broadcast"
    if hint == "broadcast" and vertices is not None and vertices > BROADCAST_VERTICES:
        hint = "shuffle_merge"
    if hint:
        a, b = a.hint(hint), b.hint(hint)
    return edges.join(a, "src").join(b, "dst")


def edge_cut(edges: DataFrame, assignment: DataFrame, vertices: int | None = None) -> DataFrame:
    """cut (weight), cut_edges, m (edges), total (weight), cut_pct."""
    cut = F.col("bi") != F.col("bj")
    out = attach_blocks(edges, assignment, vertices=vertices).agg(F.coalesce(F.sum(F.when(cut, F.col("weight"))), F.lit(0.0)).alias("cut"), F.count_if(cut).alias("cut_edges"), F.count("*").alias("m"), F.coalesce(F.sum("weight"), F.lit(0.0)).alias("total"))
    return out.withColumn("cut_pct", F.when(F.col("total") > 0, 100 * F.col("cut") / F.col("total")).otherwise(0.0))


def block_load(nodes: DataFrame, assignment: DataFrame) -> DataFrame:
    return nodes.join(assignment.select("pos", "block"), "pos").groupBy("block").agg(F.sum("weight").alias("load"))


def balance(nodes: DataFrame, assignment: DataFrame, k: int, eps: float, total: float) -> DataFrame:
    """max_load, imbalance over the mean, lmax, feasible."""
    most = lmax(total, k, eps)
    return block_load(nodes, assignment).agg(F.max("load").alias("max_load")).select("max_load", (F.col("max_load") / F.lit(total / k) - 1).alias("imbalance"), F.lit(most).alias("lmax"), (F.col("max_load") <= most).alias("feasible"))


def summary(g, assignment: DataFrame, k: int, eps: float) -> DataFrame:
    """Cut and balance in one row."""
    return edge_cut(g.edges, assignment, g.n).crossJoin(balance(g.nodes, assignment, k, eps, g.node_weight))


def quotient(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Edges of the block graph: bi < bj, weight and count."""
    cut = attach_blocks(edges, assignment).where("bi <> bj")
    return cut.groupBy(F.least("bi", "bj").alias("bi"), F.greatest("bi", "bj").alias("bj")).agg(F.sum("weight").alias("w"), F.count("*").alias("cnt"))


def boundary(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Vertices with a neighbour in another block, and their blocks."""
    cut = attach_blocks(edges, assignment).where("bi <> bj")
    return cut.select(F.explode(F.array(F.struct(F.col("src").alias("pos"), F.col("bi").alias("block")), F.struct(F.col("dst").alias("pos"), F.col("bj").alias("block")))).alias("x")).select("x.*").distinct()


def foreign_blocks(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """(pos, foreign): distinct other blocks next to each vertex that has any."""
    cut = attach_blocks(edges, assignment).where("bi <> bj")
    sides = cut.select(F.explode(F.array(F.struct(F.col("src").alias("pos"), F.col("bj").alias("block")), F.struct(F.col("dst").alias("pos"), F.col("bi").alias("block")))).alias("x")).select("x.*")
    return sides.groupBy("pos").agg(F.countDistinct("block").alias("foreign"))


def comm_volume(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    return foreign_blocks(edges, assignment).agg(F.coalesce(F.sum("foreign"), F.lit(0)).alias("volume"))


def query_messages(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Messages between blocks if each vertex looks up its neighbours (one_hop), and theirs as well (two_hop).

    A vertex asks each other block that holds a neighbour once; every neighbour then asks in the same way.
    """
    degree = edges.select(F.explode(F.array("src", "dst")).alias("pos")).groupBy("pos").agg(F.count("*").alias("degree"))
    f = foreign_blocks(edges, assignment).join(degree, "pos")
    total = lambda x: F.coalesce(F.sum(x), F.lit(0)).cast("long")
    return f.agg(total("foreign").alias("one_hop"), total(F.col("foreign") * (F.col("degree") + 1)).alias("two_hop"))


def fragmentation(edges: DataFrame, nodes: DataFrame, assignment: DataFrame) -> DataFrame:
    """pieces and largest piece of each block: smallest labels spread along edges inside blocks, a table each round."""
    inside = attach_blocks(edges, assignment).where("bi = bj").select("src", "dst")
    both = materialise(inside.unionByName(inside.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), "inside")
    label = materialise(nodes.select("pos", F.col("pos").alias("label")), "label")
    while True:
        near = both.join(label.select(F.col("pos").alias("dst"), "label"), "dst").groupBy("src").agg(F.min("label").alias("near"))
        step = label.join(near, F.col("pos") == F.col("src"), "left").select("pos", F.least("label", F.coalesce("near", "label")).alias("label"))
        # Pointer jumping: a label's own label is at least as small, so long chains halve each round.
        hop = step.select(F.col("pos").alias("label"), F.col("label").alias("hop"))
        after = materialise(step.join(hop, "label").select("pos", F.col("hop").alias("label")), "label")
        same = label.agg(F.sum("label")).first() == after.agg(F.sum("label")).first()
        label = after
        if same:
            break
    sizes = label.join(assignment.select("pos", "block"), "pos").groupBy("block", "label").agg(F.count("*").alias("n"))
    return sizes.groupBy("block").agg(F.count("*").alias("pieces"), F.max("n").alias("largest"))


def hierarchy_stats(coarse: DataFrame) -> DataFrame:
    """Vertices and edges of each buffer's levels and the shrink factor, from the coarsening stage's table."""
    rows = coarse.select("batch", F.posexplode(F.split("stats", ",")).alias("level", "x")).select("batch", "level", F.split("x", ":")[0].cast("long").alias("vertices"), F.split("x", ":")[1].cast("long").alias("edges"))
    return rows.withColumn("shrink", F.round(F.lag("vertices").over(Window.partitionBy("batch").orderBy("level")) / F.col("vertices"), 6))
