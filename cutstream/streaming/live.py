"""Live vertex streams: a micro-batch is one buffer or several whole ones, placed one after another; and the windowed and stateful operators around it.

The size of the whole graph must be declared (capacity and penalty scale need it). Each epoch writes its own partition of
the assignment, overwriting what an interrupted run of the same epoch left, so a restart changes nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from cutstream import scratch
from cutstream.params import PartitionParams, alpha, lmax
from cutstream.plans import engine as E
from cutstream.plans.graph import Graph

VERTEX = "pos long, weight double, batch long, nbrs array<struct<pos: long, w: double>>"


def write_vertex_files(g: Graph, delta: int, uri: str, vertices: int = E.RUN_VERTICES) -> int:
    """The vertex stream in files of whole buffers, of that many vertices at most (one buffer at least), in buffer order
    (later files are newer)."""
    half = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("pos"), F.col("dst").alias("nbr"), "weight"), F.struct(F.col("dst").alias("pos"), F.col("src").alias("nbr"), "weight"))).alias("x")).select("x.*")
    lists = half.groupBy("pos").agg(F.array_sort(F.collect_list(F.struct(F.col("nbr").alias("pos"), F.col("weight").alias("w")))).alias("nbrs"))
    rows = scratch.materialise(g.nodes.select("pos", "weight").join(lists, "pos", "left").select("pos", "weight", F.floor(F.col("pos") / delta).cast("long").alias("batch"), F.coalesce("nbrs", F.array().cast("array<struct<pos: long, w: double>>")).alias("nbrs")), "stream")
    each = max(1, vertices // delta)
    count = -(-g.n // (delta * each))
    for i in range(count):
        rows.where(F.col("batch").between(i * each, (i + 1) * each - 1)).coalesce(1).write.mode("append").parquet(uri)
    return count


def stream_vertices(spark: SparkSession, uri: str, max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(VERTEX).option("maxFilesPerTrigger", max_files).parquet(uri)


def partition_stream(spark: SparkSession, vertices: DataFrame, n: int, m: int, p: PartitionParams, checkpoint: str) -> DataFrame:
    """Run the stream to its end with foreachBatch; the assignment read back from the sink."""
    at, delta = scratch.path(spark, "live"), p.delta
    scale, most = p.alpha if p.alpha is not None else alpha(n, m, p.k, p.gamma), lmax(n, p.k, p.eps)
    kind = E.ASSIGNMENT + ", weight double"
    spark.createDataFrame([], kind).write.mode("append").parquet(at)

    def buffer(rows: DataFrame, epoch: int) -> None:
        s = rows.sparkSession
        own = scratch.materialise(rows, "buffer")
        low, high = own.agg(F.min("batch"), F.max("batch")).first()
        if low is None:
            return
        first, of = low * delta, F.floor(F.col("b") / F.lit(delta))
        half = own.select(F.col("batch"), F.col("pos").alias("a"), F.explode("nbrs").alias("x")).select("batch", "a", F.col("x.pos").alias("b"), F.col("x.w").alias("w"), F.lit(1.0).alias("c"))
        inside = half.where((of == F.col("batch")) & (F.col("a") < F.col("b"))).select("batch", F.lit(E.INTRA).alias("kind"), "a", "b", "w", "c")
        later = half.where(of > F.col("batch")).select("batch", F.lit(E.LATER).alias("kind"), "a", "b", "w", "c")
        earlier = half.where((of < F.col("batch")) & (F.col("b") >= first)).select("batch", F.lit(E.PLACED).alias("kind"), "a", "b", "w", "c")
        nodes = own.select("batch", F.lit(E.NODE).alias("kind"), F.col("pos").alias("a"), F.lit(-1).cast("long").alias("b"), F.lit(0.0).alias("w"), F.col("weight").alias("c"))
        parts = max(1, min(high - low + 1, int(s.conf.get("spark.sql.shuffle.partitions"))))
        coarse = E.coarsen_rows(nodes.unionByName(inside).unionByName(later).unionByName(earlier), p, E.Buffers(delta), most, False, parts)
        done = s.read.schema(kind).parquet(at).where(F.col("batch_id") < low)
        loads = np.zeros(p.k)
        for r in done.groupBy("block").agg(F.sum("weight").alias("c")).collect():  # k rows
            loads[r.block] = r.c
        conn = half.where(F.col("b") < first).join(done.select(F.col("pos").alias("b"), "block"), "b").groupBy("batch", "a", "block").agg(F.sum("w").alias("w"))
        placed = scratch.materialise(E.place_run(coarse, conn, first, loads, p.with_(lanes=1), scale, most, True), "placed")
        placed.write.mode("overwrite").parquet(f"{at}/batch={low}")

    query = vertices.writeStream.foreachBatch(buffer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(kind).option("recursiveFileLookup", "true").parquet(at).select("pos", "block", "batch_id", "fits")


def _events(spark: SparkSession, d: str) -> DataFrame:
    schema = spark.read.parquet(f"{d}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{d}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str) -> DataFrame:
    """Run a stream to its end; its last result table (complete) or all its rows (append, update) from a shared folder."""
    spark = df.sparkSession
    at, mark = scratch.path(spark, "sink"), scratch.path(spark, "mark")
    schema = df.schema

    def sink(rows: DataFrame, epoch: int) -> None:
        rows.write.mode("overwrite").parquet(at if mode == "complete" else f"{at}/epoch={epoch}")

    df.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(at)


def tumbling(spark: SparkSession, d: str) -> DataFrame:
    w = _events(spark, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users"))
    return drained(w.select(F.unix_micros("w.start").alias("start"), "event_type", "n"), "complete")


def sliding(spark: SparkSession, d: str) -> DataFrame:
    w = _events(spark, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select(F.unix_micros("w.start").alias("start"), "n"), "complete")


def sessions(spark: SparkSession, d: str) -> DataFrame:
    w = _events(spark, d).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(w.select(F.unix_micros("w.start").alias("start"), "user_id", "n"), "complete")


def deduplicated(spark: SparkSession, d: str) -> DataFrame:
    """Vertices that arrive again inside the watermark are dropped."""
    one = _events(spark, d).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return drained(one.select("user_id", "event_type"), "append")


def lane_buffers(spark: SparkSession, d: str, lanes: int = 4, size: int = 500) -> DataFrame:
    """A stateful operator: each lane holds vertices until its buffer is full, then hands on a buffer."""

    def fill(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held, flushed = state.get if state.exists else (0, 0)
        out = []
        for f in frames:
            held += len(f)
            while held >= size:
                out.append((int(key[0]), flushed, size))
                held, flushed = held - size, flushed + 1
        state.update((held, flushed))
        yield pd.DataFrame(out, columns=["lane", "flush", "rows"])

    rows = _events(spark, d).select((F.col("user_id") % lanes).cast("long").alias("lane"), "event_id")
    return drained(rows.groupBy("lane").applyInPandasWithState(fill, "lane long, flush long, rows long", "held long, flushed long", "append", GroupStateTimeout.NoTimeout), "append")
