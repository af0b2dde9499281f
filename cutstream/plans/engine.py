"""Engines of the buffered multilevel partitioner and of the one-pass greedy methods.

Coarsening of a buffer never looks at blocks (artificial vertices are invisible to it, later neighbours need only the stream
order), so all buffers are modelled and coarsened at once, a group for each buffer, in a parallel stage. Only the choice of
blocks is sequential: one ordered task folds the coarsened buffers (`fold`), holding a block number for each vertex and k
loads, or the driver runs one job for each step of `lanes` buffers against a snapshot in tables (`driver_loop`, `lanes`).
"""

from __future__ import annotations

import ctypes
import gc
import pickle
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutstream import scratch
from cutstream.functions.columns import cut_number
from cutstream.params import PartitionParams, alpha, lmax
from cutstream.plans import kernel, loops
from cutstream.plans.graph import Graph
from cutstream.scratch import materialise

ASSIGNMENT = "pos long, block int, batch_id long, fits boolean"
#: Kinds of a buffer's rows: vertices, edges inside, edges to later vertices, edges to vertices outside that have blocks.
NODE, INTRA, LATER, PLACED = range(4)
ROWS = 1 << 16
#: Bytes of a part of a serialised model: what a worker, the Arrow batch and Parquet's page hold at once.
CHUNK = 1 << 22
#: Parquet looks at the size of what it holds after each such row, not after a hundred, and a reader's batch is a small row group.
LARGE_ROWS = {"parquet.block.size": 1 << 23, "parquet.page.size.row.check.min": 1, "parquet.page.size.row.check.max": 1}
#: Vertices of small buffers that one job of the driver loop or one micro-batch places, buffer after buffer.
RUN_VERTICES = 1 << 15


@dataclass
class PartitionResult:
    """assignment(pos, block, batch_id, fits), materialised; seconds by phase."""

    assignment: DataFrame
    seconds: dict[str, float]


@dataclass(frozen=True)
class Buffers:
    """Buffers of delta vertices, or from each of the cut positions on (and from 0)."""

    delta: int
    cuts: tuple[int, ...] = ()

    def column(self, position: str):
        return cut_number(position, self.cuts).cast("long") if self.cuts else F.floor(F.col(position) / F.lit(self.delta)).cast("long")

    def first(self, batch: int) -> int:
        return (0, *self.cuts)[batch] if self.cuts else batch * self.delta

    def count(self, n: int) -> int:
        return len(self.cuts) + 1 if self.cuts else -(-n // self.delta)


def buffers_of(g: Graph, p: PartitionParams) -> Buffers:
    """Buffers as the parameters say: by count, or by space (one position a buffer comes to the driver)."""
    if p.budget is None:
        return Buffers(p.delta or max(1, g.n))
    from cutstream.operators.stream_order import assign_batches_by_budget

    found = assign_batches_by_budget(g, p.budget).groupBy("batch_id").agg(F.min("pos").alias("first")).collect()
    return Buffers(max(1, g.n), tuple(sorted(r.first for r in found))[1:])


def scale_of(g: Graph, p: PartitionParams) -> tuple[float, float]:
    """(alpha, largest load) of a graph."""
    n, m = (g.n, g.m) if p.alpha_basis == "count" else (g.node_weight, g.edge_weight)
    return (p.alpha if p.alpha is not None else alpha(n, m, p.k, p.gamma)), lmax(g.node_weight, p.k, p.eps)


def slices(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[tuple[int, pa.RecordBatch]]:
    """Rows of a sorted stream, cut where the key changes."""
    for b in batches:
        if not b.num_rows:
            continue
        col = b.column(key).to_numpy()
        edges = [0, *(np.flatnonzero(col[1:] != col[:-1]) + 1).tolist(), len(col)]
        for lo, hi in zip(edges[:-1], edges[1:], strict=True):
            yield int(col[lo]), b.slice(lo, hi - lo)


def runs(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[tuple[int, pa.Table]]:
    """Rows of a sorted stream, one run of equal keys at a time."""
    for x, own in groupby(slices(batches, key), lambda s: s[0]):
        yield x, pa.Table.from_batches([b for _, b in own])


def columns_by_kind(parts: Iterator[pa.RecordBatch], first: int) -> dict[tuple[int, str], np.ndarray]:
    """(kind, column) of a buffer's rows, sorted by kind and a, in small types as they come: vertices of the buffer, which begins
    at position `first`, by their number in it."""
    out: dict[tuple[int, str], tuple[list[np.ndarray], list[np.ndarray]]] = {(k, c): ([], []) for k, cs in ((NODE, "bc"), (INTRA, "abw"), (LATER, "abwc"), (PLACED, "abw")) for c in cs}
    for t in parts:
        kind = t.column("kind").to_numpy()
        for k in kind[np.flatnonzero(np.concatenate([[True], kind[1:] != kind[:-1]]))].tolist():
            lo, hi = np.searchsorted(kind, [k, k + 1]).tolist()
            for c in (c for i, c in out if i == k):
                x = t.column(c).to_numpy()[lo:hi]
                if c in "wc":
                    x = kernel.compact(x)
                else:
                    x = x - first if c == "a" or k == INTRA else x
                    x = x.astype(np.int32) if x.max() < 1 << 31 else x
                joined, small = out[k, c]
                small.append(x)
                if len(small) == 256:  # else memory is left in pieces that are not given back
                    joined.append(np.concatenate(small))
                    small.clear()
    of = {x: np.concatenate([*y, *z, np.zeros(0, np.uint8 if x[1] in "wc" else np.int32)]) for x in list(out) for y, z in [out.pop(x)]}
    for k in (INTRA, LATER, PLACED):
        if of[k, "w"].dtype != np.uint8:  # else sums do not depend on the order of a vertex's edges
            order = np.lexsort((of[k, "b"], of[k, "a"]))
            for c in (c for i, c in of if i == k):
                of[k, c] = of[k, c][order]
    return of


def packed(model: tuple) -> Iterator[tuple[int, int, bytes]]:
    """A model as (part, parts, bytes) of at most CHUNK bytes; its arrays are not copied as a whole."""
    views: list[pickle.PickleBuffer] = []
    head = pickle.dumps(model, protocol=5, buffer_callback=views.append)
    views = [v.raw() for v in views]
    head = pickle.dumps((head, [v.nbytes for v in views]))
    sides = [memoryview(len(head).to_bytes(8, "little") + head), *views]
    parts = -(-sum(v.nbytes for v in sides) // CHUNK)
    part, held = 0, bytearray()
    for v in sides:
        at = 0
        while at < v.nbytes:
            more = min(CHUNK - len(held), v.nbytes - at)
            held += v[at : at + more]
            at += more
            if len(held) == CHUNK:
                yield part, parts, bytes(held)
                part, held = part + 1, bytearray()
    if held:
        yield part, parts, bytes(held)


def unpacked(held: bytes | bytearray) -> tuple:
    """The model of joined parts, over their bytes; the true vertex weights as doubles."""
    view = memoryview(held)
    at = 8 + int.from_bytes(view[:8], "little")
    head, sizes = pickle.loads(view[8:at])
    ends = np.cumsum([at, *sizes]).tolist()
    start, true, *more = pickle.loads(head, buffers=[view[lo:hi] for lo, hi in zip(ends[:-1], ends[1:], strict=True)])
    return start, true.astype(np.float64), *more


def buffer_rows(g: Graph, buffers: Buffers, previous: DataFrame | None = None) -> DataFrame:
    """Everything a buffer's model needs, (batch, kind, a, b, w, c): an edge's row goes to at most two buffers.

    c is the vertex weight of NODE rows and of the later end of LATER rows; previous gives NODE rows a block in b.
    """
    batch = buffers.column
    edges = g.edges.withColumn("ba", batch("src")).withColumn("bb", batch("dst"))
    weighted = g.node_weight != g.n
    if weighted:
        edges = edges.join(g.nodes.select(F.col("pos").alias("dst"), F.col("weight").alias("c")), "dst")
    else:
        edges = edges.withColumn("c", F.lit(1.0))
    inside = F.struct(F.col("ba").alias("batch"), F.lit(INTRA).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("weight").alias("w"), "c")
    later = F.struct(F.col("ba").alias("batch"), F.lit(LATER if previous is None else PLACED).alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("weight").alias("w"), "c")
    placed = F.struct(F.col("bb").alias("batch"), F.lit(PLACED).alias("kind"), F.col("dst").alias("a"), F.col("src").alias("b"), F.col("weight").alias("w"), "c")
    sides = edges.select(F.explode(F.when(F.col("ba") == F.col("bb"), F.array(inside)).otherwise(F.array(later, placed))).alias("x")).select("x.*")
    nodes = g.nodes.withColumn("block", F.lit(-1).cast("long")) if previous is None else g.nodes.join(previous.select("pos", F.col("block").cast("long").alias("block")), "pos")
    return sides.unionByName(nodes.select(batch("pos").alias("batch"), F.lit(NODE).alias("kind"), F.col("pos").alias("a"), F.col("block").alias("b"), F.lit(0.0).alias("w"), F.col("weight").alias("c")))


def fold_ghosts(a: np.ndarray, ghost: np.ndarray, w: np.ndarray, c: np.ndarray, first: int, weight: np.ndarray, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Merge each later neighbour into one of its buffer neighbours, the one whose keyed number is smallest.

    a: local ends, ghost: positions of the later ends. Returns vertex weights with the ghosts' and the extra edges, halved.
    """
    if not len(a):
        return weight, a, a, w
    key = kernel.mix31(ghost.astype(np.int64) * 1_000_003 + (a + first), seed)
    order = np.lexsort((a, key, ghost))
    a, ghost, w, c = a[order], ghost[order], w[order], c[order]
    start = np.flatnonzero(np.concatenate([[True], ghost[1:] != ghost[:-1]]))
    rep = a[start][np.cumsum(np.concatenate([[True], ghost[1:] != ghost[:-1]])) - 1]
    weight = weight + np.bincount(a[start], c[start], minlength=len(weight))
    other = rep != a
    return weight, rep[other], a[other], w[other] * 0.5


def coarsen_rows(rows: DataFrame, p: PartitionParams, buffers: Buffers, most: float, again: bool, parts: int, n: int | None = None) -> DataFrame:
    """(batch, part, parts, blob, stats, weight of the model) from the rows of buffer_rows: one group of rows is one buffer's
    whole model. A model is dealt to parts of at most CHUNK bytes; stats and weight stand on the first."""
    extended = p.model == "extended" and not again

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, own in groupby(slices(batches, "batch"), lambda s: s[0]):
            first = buffers.first(batch)
            of = columns_by_kind((b for _, b in own), first)
            true, before = of.pop((NODE, "c")), of.pop((NODE, "b"))
            before = before if again else before[:0].copy()
            ea, eb, ew, weight = (*(of.pop((INTRA, c)) for c in "abw"), true)
            if extended:
                weight, ga, gb, gw = fold_ghosts(*(of.pop((LATER, c)) for c in "abwc"), first, true, p.seed)
                ea, eb, ew = np.concatenate([ea, ga]), np.concatenate([eb, gb]), np.concatenate([ew, gw])
                del ga, gb, gw
            total = float(weight.sum(dtype=np.float64))
            fine = kernel.Level.of(weight, ea, eb, ew)
            del ea, eb, ew, weight
            starts = np.zeros(len(true) + 1, np.int32 if len(of[PLACED, "a"]) < 1 << 31 else np.int64)
            for lo in range(0, len(starts), kernel.SORTED):
                starts[lo : lo + kernel.SORTED] = np.searchsorted(of[PLACED, "a"], np.arange(lo, min(lo + kernel.SORTED, len(starts)), dtype=np.int32))
            del of[PLACED, "a"]
            levels, maps = kernel.coarsen(fine, p, most, before if again else None)
            sizes = ",".join(f"{x.n}:{len(x.adj) // 2}" for x in levels)
            model = (first, true, levels, maps, (starts, of.pop((PLACED, "b")), of.pop((PLACED, "w"))), before)
            del fine, levels, maps
            for i, chunks, blob in packed(model):  # a row each, so that no Arrow column holds more than a part
                yield pa.RecordBatch.from_arrays([pa.array([batch], pa.int64()), pa.array([i], pa.int32()), pa.array([chunks], pa.int32()), pa.array([blob], pa.binary()), pa.array([None if i else sizes], pa.string()), pa.array([None if i else total], pa.float64())], ["batch", "part", "parts", "blob", "stats", "weight"])
            del model

    # As one number, which Spark sorts by its digits, if the n vertices are known and it has not too many; else by comparisons.
    bits = n.bit_length() if n else 63
    key = F.shiftleft(F.col("batch") * 4 + F.col("kind"), bits) + F.col("a") if n and (4 * buffers.count(n)).bit_length() + bits < 63 else F.struct("batch", "kind", "a")
    dealt = rows.repartitionById(parts, F.pmod(F.col("batch"), F.lit(parts)).cast("int")) if parts > 1 else rows.repartition(1)
    return dealt.sortWithinPartitions(key).mapInArrow(run, "batch long, part int, parts int, blob binary, stats string, weight double")


def coarsened(g: Graph, p: PartitionParams, previous: DataFrame | None = None, buffers: Buffers | None = None) -> DataFrame:
    """Each buffer's model, its coarser levels, and its edges to placed vertices; all buffers at once, written once."""
    buffers, (_, most) = buffers or buffers_of(g, p), scale_of(g, p)
    parts = max(1, min(buffers.count(g.n), int(g.nodes.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    return materialise(coarsen_rows(buffer_rows(g, buffers, previous), p, buffers, most, previous is not None, parts, g.n), "coarse", **LARGE_ROWS)


def near_placed(starts: np.ndarray, b: np.ndarray, w: np.ndarray, block_of: np.ndarray, k: int) -> kernel.Connections:
    """Connections by edges to placed vertices: u has b[starts[u]:starts[u + 1]], some vertices at a time."""
    out = []
    for lo, hi in kernel.windows(starts, kernel.SORTED):
        s, e = int(starts[lo]), int(starts[hi])
        a = np.repeat(np.arange(hi - lo, dtype=np.int32), np.diff(starts[lo : hi + 1]))
        out.append(kernel.connections(hi - lo, a, block_of[b[s:e]], w[s:e], k))
    return kernel.Connections.joined(out)


def place_buffer(blob: bytes | bytearray, state: kernel.Blocks, block_of: np.ndarray, p: PartitionParams, first: int = 0) -> tuple[int, np.ndarray, bool]:
    """Choose a buffer's blocks given all earlier ones in block_of; state takes the true weights. (first, blocks, fits)."""
    start, true, levels, maps, placed, before = unpacked(blob)
    conn = near_placed(*placed, block_of, p.k)
    again = len(before) and before[0] >= 0
    if again:
        state.add_all(before, -true)
    model = kernel.Blocks(p, state.alpha, state.most, state.load)
    block, fits = kernel.multilevel(levels, maps, conn, model, p, before if again else None)
    state.add_all(block, true)
    return start, block, fits


def _assigned(start: int, block: np.ndarray, batch: int, fits: bool) -> Iterator[pa.RecordBatch]:
    for lo in range(0, len(block), ROWS):
        own = block[lo : lo + ROWS]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(start + lo, start + lo + len(own))), pa.array(own, pa.int32()), pa.array(np.full(len(own), batch)), pa.array([fits] * len(own))], ["pos", "block", "batch_id", "fits"])


def _resident(line: str) -> int:
    """Bytes of a line of the process's status; 0 where the system has none."""
    try:
        with open("/proc/self/status", encoding="ascii") as f:
            return next((1024 * int(x.split()[1]) for x in f if x.startswith(line)), 0)
    except OSError:
        return 0


def _release_free_memory() -> None:
    """Free memory of earlier tasks goes back to the system, or a reused worker would seem to need none."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # not the GNU allocator


def probed(run: Callable) -> Callable:
    """run without its rows: one row of the bytes its worker took above its start at most, and of the rows it made."""

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _release_free_memory()
        try:
            with open("/proc/self/clear_refs", "w", encoding="ascii") as f:
                f.write("5")  # workers are reused: forget the peak of earlier tasks
        except OSError:
            pass  # the peak may then be an earlier task's
        before = _resident("VmRSS")
        count = sum(b.num_rows for b in run(batches))
        yield pa.RecordBatch.from_arrays([pa.array([max(0, _resident("VmHWM") - before)], pa.int64()), pa.array([count], pa.int64())], ["peak_bytes", "count"])

    return measure


def _ordered_task(rows: DataFrame, order: tuple[str, ...], run: Callable, probe: bool) -> DataFrame:
    one = rows.repartition(1).sortWithinPartitions(*map(F.expr, order))
    return one.mapInArrow(probed(run), "peak_bytes long, count long") if probe else one.mapInArrow(run, ASSIGNMENT)


def _packed(previous: DataFrame) -> DataFrame:
    """An assignment as rows that a fold reads first: batch -1, blobs of (positions, blocks, weights)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int64()), pa.array([pickle.dumps((b.column("pos").to_numpy(), b.column("block").to_numpy(), b.column("weight").to_numpy()))], pa.binary())], ["batch", "blob"])

    return previous.mapInArrow(run, "batch long, blob binary")


def fold(g: Graph, p: PartitionParams, coarse: DataFrame, previous: DataFrame | None = None, probe: bool = False) -> DataFrame:
    """One ordered task over the coarsened buffers. Its state is 4 bytes a vertex and k loads; probe: its memory instead of its rows."""
    scale, most = scale_of(g, p)
    n = g.n
    rows = coarse.select("batch", "part", "parts", "blob")
    if previous is not None:
        one = _packed(previous.join(g.nodes.select("pos", "weight"), "pos").select("pos", "block", "weight"))
        rows = one.select("batch", F.lit(0).alias("part"), F.lit(1).alias("parts"), "blob").unionByName(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block_of, state, held, count = np.full(n, -1, np.int32), kernel.Blocks(p, scale, most), bytearray(), 0
        for b in batches:
            for batch, parts, blob in zip(*(b.column(x) for x in ("batch", "parts", "blob")), strict=True):
                batch, parts, blob = batch.as_py(), parts.as_py(), blob.as_buffer()
                if batch < 0:
                    pos, block, weight = pickle.loads(blob)
                    block_of[pos] = block
                    state.add_all(block, weight)
                    continue
                held += blob
                count += 1
                if count < parts:
                    continue
                start, block, fits = place_buffer(held, state, block_of, p)
                held, count = bytearray(), 0
                block_of[start : start + len(block)] = block
                yield from _assigned(start, block, batch, fits)

    return _ordered_task(rows, ("batch", "part"), run, probe)


def driver_loop(g: Graph, p: PartitionParams, coarse: DataFrame, buffers: Buffers) -> DataFrame:
    """One job for each step of `lanes` buffers, or for a run of steps where buffers are small; assignment and loads live in tables.

    A lane sees the snapshot before its step, so edges between the step's buffers count for nothing in it, and each lane has
    an equal share of each block's free room, so no block overflows; p.lanes = 1 gives the same result as the fold.
    Decisions are pushed forward: a step's new blocks meet the edges that leave its own buffers (a partition of its own), and
    what later buffers need of them, summed by block, is appended to those buffers' partitions. So a step reads its own
    partitions only, and each edge is read and shuffled once a pass.
    """
    spark = g.nodes.sparkSession
    scale, most = scale_of(g, p)
    count = buffers.count(g.n)
    weight = {r.batch: r.weight for r in coarse.where("part = 0").select("batch", "weight").collect()}  # a number for each buffer
    at, pushed, forward = scratch.path(spark, "assigned"), scratch.path(spark, "pushed"), scratch.path(spark, "forward")
    loads = np.zeros(p.k)
    kind, near = ASSIGNMENT + ", weight double", "batch long, a long, block int, w double"
    leaving = g.edges.select(buffers.column("src").alias("source"), F.col("src").alias("pos"), buffers.column("dst").alias("target"), F.col("dst").alias("a"), F.col("weight").alias("w")).where("source < target")
    width = max(1, RUN_VERTICES * count // max(1, g.n) // p.lanes) * p.lanes  # buffers of a job
    turn = lambda x: F.floor(F.col(x) / F.lit(width)).cast("long")
    leaving.withColumn("turn", turn("source")).repartition("turn").write.partitionBy("turn").parquet(forward)
    edges = spark.read.schema("source long, pos long, target long, a long, w double, turn long").parquet(forward) if count > 1 else None
    low = 0
    while low < count:
        lanes, many = min(p.lanes, count - low), width > p.lanes
        while not many and lanes > 1 and no_room(most, loads, lanes, [weight[b] for b in range(low, low + lanes)]):
            lanes -= 1
        high = min(low + width, count) - 1 if many else low + lanes - 1
        known = [x for t in range(low // width, high // width + 1) if scratch.exists(spark, x := f"{pushed}/turn={t}")]
        conn = spark.read.schema(near).parquet(*known).where(F.col("batch").between(low, high)).groupBy("batch", "a", "block").agg(F.sum("w").alias("w")) if known else None
        own = coarse.where(F.col("batch").between(low, high))
        placed = place_run(own, conn, buffers.first(low), loads, p, scale, most, high == count - 1) if many else place_step(own, conn, loads, lanes, p, scale, most)
        placed.write.parquet(f"{at}/step={low}")
        done = spark.read.schema(kind).parquet(f"{at}/step={low}")
        sums = done.groupBy("block").agg(F.sum("weight").alias("c"), F.max("batch_id").alias("last")).collect()  # k rows
        high = max(r["last"] for r in sums)  # a run leaves an unfinished step to the next
        for r in sums:
            loads[r.block] += r.c
        if high + 1 < count:
            out = edges.where(F.col("turn").between(low // width, high // width) & F.col("source").between(low, high) & (F.col("target") > high)).join(done.select("pos", "block"), "pos")
            out = out.groupBy("target", "a", "block").agg(F.sum("w").alias("w"))
            out.select(F.col("target").alias("batch"), "a", "block", "w", turn("target").alias("turn")).write.mode("append").partitionBy("turn").parquet(pushed)
        low = high + 1
    if not count:
        return spark.createDataFrame([], ASSIGNMENT)
    return spark.read.schema(kind).option("recursiveFileLookup", "true").parquet(at).select("pos", "block", "batch_id", "fits")


def no_room(most: float, loads: np.ndarray, lanes: int, weights: list[float]) -> bool:
    """Whether a lane's share of the free room would not hold its model, ghosts included."""
    return np.floor(np.maximum(most - loads, 0) / lanes).sum() < max(weights)


def place_run(coarse: DataFrame, conn: DataFrame | None, first: int, loads: np.ndarray, p: PartitionParams, scale: float, most: float, final: bool) -> DataFrame:
    """Blocks of many small buffers, step after step of p.lanes buffers in one ordered task, as place_step gives them one by one.

    conn(batch, a, block, w): edges to vertices placed before the run, which begins at position first; edges to earlier
    buffers of the run come with the models. Unless final, buffers that make no whole step are left out.
    """
    rows = coarse.select("batch", F.lit(-1).cast("long").alias("a"), F.col("part").alias("block"), F.coalesce("weight", F.lit(0.0)).alias("w"), "blob")
    if conn is not None:
        rows = rows.unionByName(conn.withColumn("blob", F.lit(None).cast("binary")))
    before = loads.copy()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, block_of, waiting = before.copy(), np.zeros(0, np.int64), []  # block_of: from first on, without gaps

        def step() -> Iterator[pa.RecordBatch]:
            nonlocal now, block_of
            lanes = min(p.lanes, len(waiting))
            while lanes > 1 and no_room(most, now, lanes, [x[1] for x in waiting[:lanes]]):
                lanes -= 1
            out = []
            for batch, _, (start, true, levels, maps, (starts, b, w), _), far in waiting[:lanes]:
                a = np.repeat(np.arange(len(true)), np.diff(starts))
                inside = (b >= first) & (b < first + len(block_of))
                both = (np.concatenate(x) for x in zip(far, (a[inside], block_of[b[inside] - first], w[inside]), strict=True))
                near = kernel.connections(len(true), *both, p.k)
                block, fits = kernel.multilevel(levels, maps, near, _Lane(p, scale, most, now, lanes), p)
                out.append((start, block, batch, fits, true))
            del waiting[:lanes]
            block_of = np.concatenate([block_of, *(x[1] for x in out)])
            now = now + sum(np.bincount(x[1], x[4], p.k) for x in out)
            for start, block, batch, fits, true in out:
                for rows, weight in zip(_assigned(start, block, batch, fits), (true[i : i + ROWS] for i in range(0, len(true), ROWS)), strict=True):
                    yield rows.append_column("weight", pa.array(weight))

        for batch, t in runs(batches, "batch"):
            model = unpacked(b"".join(x for x in t.column("blob").to_pylist() if x is not None))
            a, block, w = (t.column(c).to_numpy() for c in ("a", "block", "w"))
            other = a >= 0
            waiting.append((batch, float(w[~other].sum()), model, (a[other] - model[0], block[other], w[other])))
            if len(waiting) >= p.lanes:
                yield from step()
        while waiting and (final or len(waiting) >= p.lanes):
            yield from step()

    return rows.repartition(1).sortWithinPartitions("batch", "a", "block").mapInArrow(run, ASSIGNMENT + ", weight double")


def place_step(coarse: DataFrame, conn: DataFrame | None, loads: np.ndarray, lanes: int, p: PartitionParams, scale: float, most: float) -> DataFrame:
    """Blocks of a step's buffers, a group each: coarse(batch, part, blob), conn(batch, a, block, w) to placed vertices."""
    rows = coarse.select("batch", F.lit(-1).cast("long").alias("a"), F.col("part").alias("block"), F.lit(0.0).alias("w"), "blob")
    if conn is not None:
        rows = rows.unionByName(conn.withColumn("blob", F.lit(None).cast("binary")))
    now = loads.copy()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, t in runs(batches, "batch"):
            blob = b"".join(x for x in t.column("blob").to_pylist() if x is not None)
            start, true, levels, maps, _, _ = unpacked(blob)
            a, block, w = (t.column(c).to_numpy() for c in ("a", "block", "w"))
            other = a >= 0
            near = kernel.connections(len(true), a[other] - start, block[other], w[other], p.k)
            block, fits = kernel.multilevel(levels, maps, near, _Lane(p, scale, most, now, lanes), p)
            for out, weight in zip(_assigned(start, block, batch, fits), (true[i : i + ROWS] for i in range(0, len(true), ROWS)), strict=True):
                yield out.append_column("weight", pa.array(weight))

    return rows.repartition(lanes, "batch").sortWithinPartitions("batch", "a", "block").mapInArrow(run, ASSIGNMENT + ", weight double")


class _Lane(kernel.Blocks):
    """Blocks as one of several lanes sees them: its share of the free room, its own additions counted for all lanes."""

    whole = False

    def __init__(self, p: PartitionParams, scale: float, most: float, loads: np.ndarray, lanes: int):
        super().__init__(p, scale, most, loads)
        self.base, self.lanes, self.real = loads.tolist(), lanes, loads.tolist()
        room = np.floor(np.maximum(most - loads, 0) / lanes) if lanes > 1 else most - loads
        self.most_real = (loads + room).tolist()

    def add(self, i: int, c: float) -> None:
        self.real[i] += c
        super().add(i, self.base[i] + self.lanes * (self.real[i] - self.base[i]) - self.load[i])

    def best_of_all(self, conn: dict[int, float], c: float) -> int:
        """As above, but each block has a room of its own, so all are looked at."""
        best, score = -1, 0.0
        for i in range(self.p.k):
            if self.real[i] + c <= self.most_real[i]:
                s = self.score(conn.get(i, 0.0), c, i)
                if best < 0 or s > score or (s == score and self.load[i] < self.load[best]):
                    best, score = i, s
        return best


def partition_buffered(g: Graph, p: PartitionParams) -> PartitionResult:
    """Buffered multilevel partitioning, p.passes passes."""
    if p.engine == "distributed":
        from cutstream.plans.distributed import partition_distributed

        return partition_distributed(g, p)
    began = time.time()
    buffers = buffers_of(g, p)
    coarse = coarsened(g, p, buffers=buffers)
    middle = time.time()
    out = materialise(fold(g, p, coarse) if p.engine == "fold" else driver_loop(g, p if p.engine == "lanes" else p.with_(lanes=1), coarse, buffers), "assignment")
    seconds = {"coarsen": middle - began, "place": time.time() - middle}
    for _ in range(1, p.passes):
        again = repartition_buffered(g, out, p)
        out = again.assignment
        seconds = {k: seconds[k] + again.seconds[k] for k in seconds}
    return PartitionResult(out, seconds)


def repartition_buffered(g: Graph, assignment: DataFrame, p: PartitionParams) -> PartitionResult:
    """One more pass: clusters stay inside blocks, all outside vertices have blocks, local search from where they are."""
    began = time.time()
    coarse = coarsened(g, p, assignment)
    middle = time.time()
    out = materialise(fold(g, p, coarse, assignment), "assignment")
    return PartitionResult(out, {"coarsen": middle - began, "place": time.time() - middle})


def pass_results(g: Graph, p: PartitionParams, passes: int) -> list[PartitionResult]:
    """The result after each pass."""
    out = [partition_buffered(g, p.with_(passes=1))]
    for _ in range(1, passes):
        out.append(repartition_buffered(g, out[-1].assignment, p))
    return out


def half_edges(g: Graph) -> DataFrame:
    """The vertex stream as flat rows: (pos, -1, weight) for the vertex, then (pos, neighbour, weight) in order."""
    half = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("pos"), F.col("dst").alias("nbr"), "weight"), F.struct(F.col("dst").alias("pos"), F.col("src").alias("nbr"), "weight"))).alias("x")).select("x.*")
    return g.nodes.select("pos", F.lit(-1).cast("long").alias("nbr"), "weight").unionByName(half)


def place_greedy(g: Graph, p: PartitionParams, previous: DataFrame | None = None, blocks: type[kernel.Blocks] = kernel.Blocks, probe: bool = False) -> DataFrame:
    """One pass of a one-vertex-at-a-time greedy in one ordered task; previous: blocks of the pass before.

    blocks: kernel.AllBlocks scores all k blocks for each vertex, with the same result; probe: memory instead of rows.
    """
    scale, most = scale_of(g, p)
    n, size = g.n, g.n + g.m
    # In the first pass only earlier neighbours have blocks, so each edge goes to its later end alone.
    first = g.nodes.select("pos", F.lit(-1).cast("long").alias("nbr"), "weight").unionByName(g.edges.select(F.col("dst").alias("pos"), F.col("src").alias("nbr"), "weight"))
    rows = (first if previous is None else half_edges(g)).select("pos", "nbr", "weight", F.lit(-1).alias("block"))
    if previous is not None:
        rows = rows.unionByName(previous.join(g.nodes.select("pos", "weight"), "pos").select(F.lit(-1).cast("long").alias("pos"), F.col("pos").alias("nbr"), "weight", "block"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = blocks(p, scale, most)
        if loops.known(state) and n < 1 << 31 and loops.worth(size):
            with loops.Greedy(state, n) as own:
                for b in batches:
                    yield from _greedy_arrays(*own.rows(*(b.column(x).to_numpy() for x in ("pos", "nbr", "weight", "block"))))
                yield from _greedy_arrays(*own.rows())
            return
        block_of = [-1] * n
        out: list[tuple[int, int, bool]] = []
        u, c, conn = -1, 0.0, {}

        def place() -> None:
            if block_of[u] >= 0:
                state.add(block_of[u], -c)
            i = state.best_of_all(conn, c)
            fits = i >= 0
            if not fits:
                i = int(np.argmin(state.load))
            state.add(i, c)
            block_of[u] = i
            out.append((u, i, fits))

        for b in batches:
            for pos, v, w, i in zip(*(b.column(x).to_pylist() for x in ("pos", "nbr", "weight", "block")), strict=True):
                if pos < 0:
                    block_of[v] = i
                    state.add(i, w)
                elif v < 0:
                    if u >= 0:
                        place()
                    u, c, conn = pos, w, {}
                elif (i := block_of[v]) >= 0:
                    conn[i] = conn.get(i, 0.0) + w
            if len(out) >= ROWS:
                yield _greedy_rows(out)
                out.clear()
        if u >= 0:
            place()
        if out:
            yield _greedy_rows(out)

    return _ordered_task(rows, ("pos * 2 + int(nbr >= 0)",) if g.whole else ("pos", "nbr"), run, probe)


def _greedy_rows(out: list[tuple[int, int, bool]]) -> pa.RecordBatch:
    pos, block, fits = zip(*out, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(pos, pa.int64()), pa.array(block, pa.int32()), pa.array(pos, pa.int64()), pa.array(fits)], ["pos", "block", "batch_id", "fits"])


def _greedy_arrays(pos: np.ndarray, block: np.ndarray, fits: np.ndarray) -> Iterator[pa.RecordBatch]:
    if len(pos):
        yield pa.RecordBatch.from_arrays([pa.array(pos), pa.array(block, pa.int32()), pa.array(pos), pa.array(fits)], ["pos", "block", "batch_id", "fits"])


def greedy(g: Graph, p: PartitionParams) -> PartitionResult:
    """Penalty-gain or capacity-discount greedy by p.objective, p.passes passes."""
    began = time.time()
    out = materialise(place_greedy(g, p), "assignment")
    for _ in range(1, p.passes):
        out = materialise(place_greedy(g, p, out), "assignment")
    return PartitionResult(out, {"coarsen": 0.0, "place": time.time() - began})


def place_penalty_gain(g: Graph, p: PartitionParams) -> DataFrame:
    return greedy(g, p.with_(objective="penalty_gain")).assignment


def place_capacity_discount(g: Graph, p: PartitionParams) -> DataFrame:
    return greedy(g, p.with_(objective="capacity_discount")).assignment


def place_hash(g: Graph, k: int, seed: int = 0) -> DataFrame:
    """Hash placement; a map over the vertices."""
    from cutstream.functions.columns import mix31

    return g.nodes.select("pos", (mix31("pos", seed) % k).cast("int").alias("block"), F.lit(0).cast("long").alias("batch_id"), F.lit(True).alias("fits"))


def place_round_robin(g: Graph, k: int) -> DataFrame:
    return g.nodes.select("pos", (F.col("pos") % k).cast("int").alias("block"), F.lit(0).cast("long").alias("batch_id"), F.lit(True).alias("fits"))


def place_range(g: Graph, k: int) -> DataFrame:
    return g.nodes.select("pos", F.floor(F.col("pos") * k / F.lit(max(1, g.n))).cast("int").alias("block"), F.lit(0).cast("long").alias("batch_id"), F.lit(True).alias("fits"))


def partition_offline(g: Graph, p: PartitionParams, seeds: tuple[int, ...] = (1, 2, 3), passes: int = 10) -> DataFrame:
    """Context yardstick: the whole graph in one model, many passes, the best of several seeds."""
    from cutstream.operators.measures import edge_cut

    best, least = None, None
    for seed in seeds:
        out = partition_buffered(g, p.with_(delta=None, seed=seed, passes=passes)).assignment
        cut = edge_cut(g.edges, out).first()["cut"]
        if least is None or cut < least:
            best, least = out, cut
    return best
