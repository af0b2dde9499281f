"""Multilevel partitioning of a graph that no single task should coarsen: clusters and contraction as DataFrame rounds.

Synchronous, size-bounded label propagation and contraction shrink the graph until it fits one task; that small weighted
graph is partitioned there; blocks are joined back level by level, and a replayed pass over buffers refines the result.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from cutstream.operators.models import contract, lp_cluster_distributed
from cutstream.params import PartitionParams, lmax
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph
from cutstream.scratch import materialise

#: Vertices that one task may take.
TASK_VERTICES = 1 << 20


def partition_distributed(g: Graph, p: PartitionParams, limit: int = TASK_VERTICES, refine: bool = True) -> E.PartitionResult:
    """assignment of g; limit: vertices of the coarse graph that a single task partitions."""
    most = lmax(g.node_weight, p.k, p.eps)
    level, maps = g, []
    while level.n > limit:
        labels = lp_cluster_distributed(level.nodes, level.edges, p.coarsen_rounds, max(1.0, most / p.cluster_factor), p.seed + len(maps))
        sizes = level.nodes.join(labels, "pos").groupBy(F.col("label").alias("key")).agg(F.sum("weight").alias("weight"))
        joined = contract(level.edges, labels.select(F.col("pos").alias("fine"), F.col("label").alias("coarse")))
        coarse = Graph.from_edges(joined, extra=sizes.select("key"), weights=sizes)
        if coarse.n > 0.95 * level.n:
            break
        maps.append(materialise(labels.join(coarse.nodes.select(F.col("key").alias("label"), F.col("pos").alias("coarse")), "label").select("pos", "coarse"), "level-map"))
        level = coarse
    out = E.partition_buffered(level, p.with_(delta=None, passes=1, engine="fold", alpha=E.scale_of(g, p)[0] if p.alpha is None else p.alpha))
    blocks = out.assignment
    for m in reversed(maps):
        blocks = materialise(m.join(blocks.select(F.col("pos").alias("coarse"), "block", "batch_id", "fits"), "coarse").select("pos", "block", "batch_id", "fits"), "assignment")
    if refine and maps:
        return E.repartition_buffered(g, blocks, p)
    return E.PartitionResult(blocks, out.seconds)
