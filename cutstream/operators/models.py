"""Set-based forms of the buffer models, contraction, gains, and the synchronous clustering and refinement rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutstream.functions.columns import mix31, penalty_expr
from cutstream.operators.stream_order import classify_edges


def _merged(edges: DataFrame) -> DataFrame:
    """Model edges (batch_id, a < b, w): parallel ones summed, loops dropped."""
    return edges.where("a <> b").groupBy("batch_id", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum("w").alias("w"))


def _size(n: int, delta: int):
    """Vertices of a row's buffer."""
    return F.least(F.lit(delta), F.lit(n) - F.col("batch_id") * delta)


def model_basic(edges: DataFrame, assignment: DataFrame, n: int, delta: int) -> DataFrame:
    """Edges of each buffer's basic model: inside edges by local number, and those to the earlier vertices' blocks.

    A block's artificial vertex is number size + block. Edges to later vertices are left out.
    """
    c = classify_edges(edges, delta)
    local = (F.col("pos") - F.col("batch_id") * delta).cast("int").alias("a")
    inside = c.where("class = 'intra'").select("batch_id", local, (F.col("other") - F.col("batch_id") * delta).cast("int").alias("b"), "w")
    back = c.where("class = 'backward'").join(assignment.select(F.col("pos").alias("other"), "block"), "other").select("batch_id", local, (_size(n, delta) + F.col("block")).cast("int").alias("b"), "w")
    return _merged(inside.unionByName(back))


def ghost_representatives(edges: DataFrame, delta: int, seed: int) -> DataFrame:
    """(batch_id, ghost_pos, rep): of a later vertex's neighbours in the buffer, the one with the smallest keyed number."""
    fwd = classify_edges(edges, delta).where("class = 'forward'")
    pick = F.struct(mix31("other * 1000003 + pos", seed), F.col("pos"))
    return fwd.groupBy("batch_id", F.col("other").alias("ghost_pos")).agg(F.min(pick).getField("pos").alias("rep"))


def model_extended(edges: DataFrame, assignment: DataFrame, n: int, delta: int, seed: int) -> DataFrame:
    """The basic model plus, at half weight, edges between a ghost's representative and its other neighbours here."""
    fwd = classify_edges(edges, delta).where("class = 'forward'").select("batch_id", F.col("other").alias("ghost_pos"), "pos", "w")
    ghost = fwd.join(ghost_representatives(edges, delta, seed), ["batch_id", "ghost_pos"]).select("batch_id", (F.col("rep") - F.col("batch_id") * delta).cast("int").alias("a"), (F.col("pos") - F.col("batch_id") * delta).cast("int").alias("b"), (F.col("w") / 2).alias("w"))
    return _merged(model_basic(edges, assignment, n, delta).unionByName(ghost))


def model_nodes(nodes: DataFrame, edges: DataFrame, assignment: DataFrame, n: int, delta: int, k: int, seed: int | None) -> DataFrame:
    """(batch_id, local, weight, fixed_block): buffer vertices (with the ghosts they stand for, if seed is given) and the
    blocks' artificial vertices with the loads of all earlier buffers; none of these in the first buffer."""
    own = nodes.select(F.floor(F.col("pos") / delta).cast("long").alias("batch_id"), "pos", "weight")
    if seed is not None:
        ghosts = ghost_representatives(edges, delta, seed).join(nodes.select(F.col("pos").alias("ghost_pos"), F.col("weight").alias("gw")), "ghost_pos").groupBy("batch_id", F.col("rep").alias("pos")).agg(F.sum("gw").alias("gw"))
        own = own.join(ghosts, ["batch_id", "pos"], "left").select("batch_id", "pos", (F.col("weight") + F.coalesce("gw", F.lit(0.0))).alias("weight"))
    mutable = own.select("batch_id", (F.col("pos") - F.col("batch_id") * delta).cast("int").alias("local"), "weight", F.lit(None).cast("int").alias("fixed_block"))
    spark = nodes.sparkSession
    per = nodes.join(assignment.select("pos", "block"), "pos").groupBy(F.floor(F.col("pos") / delta).cast("long").alias("batch_id"), "block").agg(F.sum("weight").alias("load"))
    grid = spark.range(1, max(1, -(-n // delta))).select(F.col("id").alias("batch_id")).crossJoin(spark.range(k).select(F.col("id").cast("int").alias("block")))
    load = F.sum("load").over(Window.partitionBy("block").orderBy("batch_id").rowsBetween(Window.unboundedPreceding, -1))
    every = spark.range(max(1, -(-n // delta))).select(F.col("id").alias("batch_id")).crossJoin(spark.range(k).select(F.col("id").cast("int").alias("block"))).join(per, ["batch_id", "block"], "left").select("batch_id", "block", F.coalesce(load, F.lit(0.0)).alias("weight"))
    fixed = grid.join(every, ["batch_id", "block"]).select("batch_id", (_size(n, delta) + F.col("block")).cast("int").alias("local"), "weight", F.col("block").alias("fixed_block"))
    return mutable.unionByName(fixed)


def model_restream(edges: DataFrame, assignment: DataFrame, n: int, delta: int) -> DataFrame:
    """Edges of each buffer's model in a later pass: inside edges, and those to the blocks of all vertices outside."""
    c = classify_edges(edges, delta)
    local = (F.col("pos") - F.col("batch_id") * delta).cast("int").alias("a")
    inside = c.where("class = 'intra'").select("batch_id", local, (F.col("other") - F.col("batch_id") * delta).cast("int").alias("b"), "w")
    out = c.where("class <> 'intra'").join(assignment.select(F.col("pos").alias("other"), "block"), "other").select("batch_id", local, (_size(n, delta) + F.col("block")).cast("int").alias("b"), "w")
    return _merged(inside.unionByName(out))


def contract(edges: DataFrame, level_map: DataFrame) -> DataFrame:
    """Coarse edges (src, dst, weight) under level_map(fine, coarse)."""
    m = lambda x, y: level_map.select(F.col("fine").alias(x), F.col("coarse").alias(y))
    up = edges.join(m("src", "ca"), "src").join(m("dst", "cb"), "dst").where("ca <> cb")
    return up.groupBy(F.least("ca", "cb").alias("src"), F.greatest("ca", "cb").alias("dst")).agg(F.sum("weight").alias("weight"))


def connections(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """(pos, block, conn): each vertex's edge weight to each adjacent block."""
    half = edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    return half.join(assignment.select(F.col("pos").alias("dst"), "block"), "dst").groupBy(F.col("src").alias("pos"), "block").agg(F.sum("weight").alias("conn"))


def gain_table(edges: DataFrame, nodes: DataFrame, assignment: DataFrame, alpha: float) -> DataFrame:
    """(pos, block, conn, gain) for all adjacent blocks at the loads of the assignment."""
    loads = nodes.join(assignment.select("pos", "block"), "pos").groupBy("block").agg(F.sum("weight").alias("load"))
    return connections(edges, assignment).join(F.broadcast(loads), "block").join(nodes.select("pos", "weight"), "pos").select("pos", "block", "conn", (F.col("conn") - F.col("weight") * penalty_expr(F.col("load"), alpha)).alias("gain"))


def gain_additivity(edges: DataFrame, nodes: DataFrame, assignment: DataFrame, level_map: DataFrame, alpha: float) -> DataFrame:
    """(coarse, block, merged, members): gain of a contracted cluster and the sum of its members' gains at the same loads,
    for clusters without a member in the block."""
    loads = nodes.join(assignment.select("pos", "block"), "pos").groupBy("block").agg(F.sum("weight").alias("load"))
    up = level_map.select(F.col("fine").alias("pos"), "coarse")
    home = assignment.select("pos", "block").join(up, "pos").select("coarse", "block").distinct()
    conn = connections(edges, assignment).join(up, "pos")
    size = nodes.join(up, "pos").groupBy("coarse").agg(F.sum("weight").alias("c"))
    merged = conn.groupBy("coarse", "block").agg(F.sum("conn").alias("conn")).join(size, "coarse").join(F.broadcast(loads), "block").join(home, ["coarse", "block"], "left_anti")
    merged = merged.select("coarse", "block", (F.col("conn") - F.col("c") * penalty_expr(F.col("load"), alpha)).alias("merged"))
    full = merged.select("coarse", "block").join(up, "coarse").join(connections(edges, assignment), ["pos", "block"], "left").join(nodes.select("pos", "weight"), "pos").join(F.broadcast(loads), "block")
    members = full.groupBy("coarse", "block").agg(F.sum(F.coalesce("conn", F.lit(0.0)) - F.col("weight") * penalty_expr(F.col("load"), alpha)).alias("members"))
    return merged.join(members, ["coarse", "block"])


def lp_sync_round(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One synchronous round: every vertex takes the strongest label next to it, the lowest of equals."""
    half = edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    votes = half.join(labels.select(F.col("pos").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("pos"), "label").agg(F.sum("weight").alias("v"))
    best = votes.groupBy("pos").agg(F.max(F.struct("v", (-F.col("label")).alias("x"))).getField("x").alias("x"))
    return labels.join(best, "pos", "left").select("pos", F.coalesce(-F.col("x"), F.col("label")).alias("label"))


def lp_cluster_distributed(nodes: DataFrame, edges: DataFrame, rounds: int, most: float, seed: int) -> DataFrame:
    """Size-bounded clusters by synchronous rounds: a keyed half of the vertices asks for its best label; a cluster admits
    requests by strength while its weight fits. (pos, label), a table for each round."""
    from cutstream.scratch import materialise

    labels = materialise(nodes.select("pos", "weight", F.col("pos").alias("label")), "labels")
    half = edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    for r in range(rounds):
        votes = half.join(labels.select(F.col("pos").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("pos"), "label").agg(F.sum("weight").alias("v"))
        best = votes.groupBy("pos").agg(F.max(F.struct("v", (-F.col("label")).alias("x"))).alias("b")).select("pos", F.col("b.v").alias("v"), (-F.col("b.x")).alias("want"))
        ask = labels.join(best, "pos").where((F.col("want") != F.col("label")) & (F.pmod(F.xxhash64("pos", F.lit(seed + r)), F.lit(2)) == 0))
        size = labels.groupBy(F.col("label").alias("want")).agg(F.sum("weight").alias("size"))
        running = F.sum("weight").over(Window.partitionBy("want").orderBy(F.desc("v"), "pos").rowsBetween(Window.unboundedPreceding, 0))
        admitted = ask.join(size, "want").withColumn("after", F.col("size") + running).where(F.col("after") <= most).select("pos", "want")
        labels = materialise(labels.join(admitted, "pos", "left").select("pos", "weight", F.coalesce("want", "label").alias("label")), "labels")
    return labels.select("pos", "label")


def refine_sync_round(edges: DataFrame, nodes: DataFrame, assignment: DataFrame, alpha: float, most: float) -> DataFrame:
    """(pos, block, target): the best move of each vertex to an adjacent block with room, seen at the present loads; ties
    to the lower block; the vertex itself is out of its own block's load."""
    loads = nodes.join(assignment.select("pos", "block"), "pos").groupBy("block").agg(F.sum("weight").alias("load"))
    own = nodes.join(assignment.select("pos", F.col("block").alias("now")), "pos").select("pos", "weight", "now")
    cand = connections(edges, assignment).join(own, "pos").join(F.broadcast(loads), "block")
    load = F.when(F.col("block") == F.col("now"), F.col("load") - F.col("weight")).otherwise(F.col("load"))
    scored = cand.withColumn("free", load + F.col("weight") <= most).where("free").withColumn("gain", F.round(F.col("conn") - F.col("weight") * penalty_expr(load, alpha), 9))
    best = scored.groupBy("pos").agg(F.max(F.struct("gain", (-F.col("block")).alias("x"))).alias("b"))
    return own.join(best, "pos").select("pos", F.col("now").alias("block"), (-F.col("b.x")).cast("int").alias("target"))
