"""Registry of the partitioning queries and of their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream import queries_graph, queries_method, queries_relational, queries_streaming, workloads

Query = Callable[[SparkSession, str], DataFrame]
_PARTS = (queries_graph, queries_method, queries_relational, queries_streaming, workloads)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Load of each block with the cut, for the buffered multilevel partitioner on documents that share lines."""
    from cutstream.operators import measures
    from cutstream.params import PartitionParams
    from cutstream.plans.engine import partition_buffered
    from cutstream.plans.graph import Graph

    g = Graph.load(spark, sf_dir, "docline", unit=True)
    out = partition_buffered(g, PartitionParams(k=8, delta=64)).assignment
    cut = measures.edge_cut(g.edges, out, g.n).select("cut", F.round("cut_pct", 4).alias("cut_pct"))
    return measures.block_load(g.nodes, out).crossJoin(F.broadcast(cut)).orderBy("block")


def queries() -> dict[str, Query]:
    return {name: q for part in _PARTS for name, q in part.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {name: sql for part in _PARTS for name, sql in part.ORACLES.items()}
