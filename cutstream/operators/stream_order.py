"""The vertex stream and its buffers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutstream.plans.graph import Graph, dense_positions


def adjacency(g: Graph, hub_cap: int | None = 100_000) -> DataFrame:
    """The vertex stream: pos, weight, chunk, degree (of the chunk), nbrs (sorted structs).

    A vertex of more than hub_cap neighbours is dealt to chunks of hub_cap at most, any other one is a single row.
    """
    half = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("pos"), F.col("dst").alias("nbr"), "weight"), F.struct(F.col("dst").alias("pos"), F.col("src").alias("nbr"), "weight"))).alias("x")).select("x.*")
    if hub_cap is None:
        chunked = half.withColumn("chunk", F.lit(0).cast("long"))
    else:
        hubs = degrees(g.edges).where(F.col("degree") > hub_cap).select("pos", F.lit(True).alias("hub"))
        chunked = half.join(hubs, "pos", "left").withColumn("chunk", F.when(F.col("hub"), F.floor(F.col("nbr") / hub_cap)).otherwise(0))
    lists = chunked.groupBy("pos", "chunk").agg(F.array_sort(F.collect_list(F.struct(F.col("nbr").alias("pos"), F.col("weight").alias("w")))).alias("nbrs"))
    return g.nodes.select("pos", "weight").join(lists, "pos", "left").select("pos", "weight", F.coalesce("chunk", F.lit(0)).alias("chunk"), F.coalesce(F.size("nbrs"), F.lit(0)).alias("degree"), "nbrs")


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("pos")).groupBy("pos").agg(F.count("*").alias("degree"))


def assign_batches(nodes: DataFrame, delta: int) -> DataFrame:
    """Buffers of delta vertices."""
    return nodes.withColumn("batch_id", F.floor(F.col("pos") / delta).cast("long"))


def assign_batches_by_budget(g: Graph, budget: int, slice_rows: int = 1 << 16) -> DataFrame:
    """Buffers that close when sum(1 + degree) passes a multiple of the budget: a two-level prefix sum over position slices."""
    cost = g.nodes.select("pos").join(degrees(g.edges), "pos", "left").select("pos", (F.lit(1) + F.coalesce("degree", F.lit(0))).alias("cost")).withColumn("slice", F.floor(F.col("pos") / slice_rows))
    totals = cost.groupBy("slice").agg(F.sum("cost").alias("total"))
    before = totals.select("slice", (F.sum("total").over(Window.orderBy("slice")) - F.col("total")).alias("before"))  # a row for each slice
    inside = F.sum("cost").over(Window.partitionBy("slice").orderBy("pos"))
    return cost.withColumn("inside", inside).join(F.broadcast(before), "slice").select("pos", "cost", F.floor((F.col("before") + F.col("inside") - F.col("cost")) / budget).cast("long").alias("batch_id"))


def classify_edges(edges: DataFrame, delta: int) -> DataFrame:
    """Each edge as its ends' buffers see it: inside, to a later buffer (forward), to an earlier one (backward)."""
    b = lambda x: F.floor(F.col(x) / delta).cast("long")
    e = edges.withColumn("ba", b("src")).withColumn("bb", b("dst"))
    row = lambda batch, pos, other, ob, kind: F.struct(F.col(batch).alias("batch_id"), F.col(pos).alias("pos"), F.col(other).alias("other"), F.col(ob).alias("other_batch"), F.lit(kind).alias("class"), F.col("weight").alias("w"))
    return e.select(F.explode(F.when(F.col("ba") == F.col("bb"), F.array(row("ba", "src", "dst", "bb", "intra"))).otherwise(F.array(row("ba", "src", "dst", "bb", "forward"), row("bb", "dst", "src", "ba", "backward")))).alias("x")).select("x.*")


__all__ = ["adjacency", "assign_batches", "assign_batches_by_budget", "classify_edges", "degrees", "dense_positions"]
