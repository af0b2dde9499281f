"""A graph ready for streaming: vertices numbered in stream order, edges between positions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.scratch import materialise
from cutstream.sources import graphs as G


def dense_positions(keys: DataFrame, columns: list, tag: str = "positions") -> DataFrame:
    """keys(key, ...) with a dense pos in the order of columns: a range sort, a count for each partition, offsets."""
    ordered = materialise(keys.orderBy(*columns).withColumn("mid", F.monotonically_increasing_id()), tag)
    part = F.shiftright("mid", 33)
    total, offsets = 0, []
    for r in sorted(ordered.groupBy(part.alias("p")).count().collect(), key=lambda r: r.p):  # a row for each partition
        offsets += [F.lit(r.p), F.lit(total)]
        total += r["count"]
    if not offsets:
        return ordered.withColumn("pos", F.lit(0).cast("long")).drop("mid")
    return ordered.withColumn("pos", (F.element_at(F.create_map(*offsets), part) + F.col("mid").bitwiseAND((1 << 33) - 1)).cast("long")).drop("mid")


@dataclass
class Graph:
    """nodes(pos, key, weight), edges(src, dst, weight) with src < dst in positions; sizes are known.

    whole: weights of edges are known to be whole numbers, whose sums are the same in any order.
    """

    nodes: DataFrame
    edges: DataFrame
    n: int
    m: int
    node_weight: float
    edge_weight: float
    name: str = ""
    whole: bool = False

    @classmethod
    def from_edges(cls, edges: DataFrame, extra: DataFrame | None = None, order: str = "natural", seed: int = 42, weights: DataFrame | None = None, name: str = "") -> Graph:
        """From clean edges over keys. extra(key): vertices that may have no edge. weights(key, weight): else 1."""
        edges = materialise(edges, "clean")  # both the vertices and the edges are made of them
        ends = edges.select(F.explode(F.array("src", "dst")).alias("key"))
        if order == "degree":
            keys = ends.groupBy("key").agg(F.count("*").alias("degree"))
        else:
            keys = ends.distinct().withColumn("degree", F.lit(0).cast("long"))
        if extra is not None:
            keys = keys.unionByName(extra.select("key", F.lit(0).cast("long").alias("degree"))).groupBy("key").agg(F.max("degree").alias("degree"))
        numbered = dense_positions(keys, G.column_of_order(order, F.col("degree"), F.col("key"), seed)).drop("degree")
        numbered = numbered.join(weights, "key", "left").withColumn("weight", F.coalesce("weight", F.lit(1.0))) if weights is not None else numbered.withColumn("weight", F.lit(1.0))
        nodes = materialise(numbered.select("pos", "key", "weight"), "nodes")
        a, b = nodes.select(F.col("key").alias("src"), F.col("pos").alias("pa")), nodes.select(F.col("key").alias("dst"), F.col("pos").alias("pb"))
        placed = materialise(edges.join(a, "src").join(b, "dst").select(F.least("pa", "pb").alias("src"), F.greatest("pa", "pb").alias("dst"), "weight"), "edges")
        n, cv = nodes.agg(F.count("*"), F.coalesce(F.sum("weight"), F.lit(0.0))).first()
        m, we, whole = placed.agg(F.count("*"), F.coalesce(F.sum("weight"), F.lit(0.0)), F.coalesce(F.bool_and(F.col("weight") == F.floor("weight")), F.lit(False))).first()
        return cls(nodes, placed, n, m, cv, we, name, whole)

    @classmethod
    def load(cls, spark: SparkSession, sf_dir: str, name: str, unit: bool = True, order: str = "natural", seed: int = 42) -> Graph:
        return cls.from_edges(G.edges(spark, sf_dir, name, unit), order=order, seed=seed, name=name)

    def partition(self, params) -> DataFrame:
        from cutstream.plans.engine import partition_buffered

        return partition_buffered(self, params).assignment

    def metrics(self, assignment: DataFrame, k: int, eps: float = 0.03) -> DataFrame:
        from cutstream.operators.measures import summary

        return summary(self, assignment, k, eps)

    def restream(self, assignment: DataFrame, params) -> DataFrame:
        from cutstream.plans.engine import repartition_buffered

        return repartition_buffered(self, assignment, params).assignment
