"""Helpers shared by the training-data operators: shared scratch tables, text batches and vectorised hashing."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_MASK = (1 << 64) - 1
#: Bytes of text handled at once by the vectorised kernels; a longer document is one batch by itself.
BATCH_BYTES = 1 << 18


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors see: spark.checkpoint.dir, or a temporary one where it is unset (tests).

    A temporary folder is this machine's own, so it is refused unless the master is local.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="cutstream-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found.rstrip("/")


def scratch_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def materialise(spark: SparkSession, df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and read it back, so that no later job depends on an executor's memory or lineage."""
    path = scratch_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a scratch path through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def ordered_cuts(df: DataFrame, key: str) -> list[int]:
    """Ascending cut points that deal an integer key to about four buckets a shuffle partition, whatever its range.

    They are approximate quantiles over all rows (a bounded summary per task, merged), so an outlying id moves no other row.
    """
    buckets = 4 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    shares = [i / buckets for i in range(1, buckets)]
    found = df.agg(F.percentile_approx(F.col(key).cast("long"), shares, 20 * buckets)).first()[0]
    return sorted(set(found or ()))


def bucket_column(key: str, cuts: list[int]):
    """Number of cut points at or below a key, by a binary search in the plan; null keys go to bucket -1, before all others."""
    if not cuts:
        return F.when(F.col(key).isNull(), F.lit(-1)).otherwise(F.lit(0))
    table = F.from_json(F.lit(str(cuts)), "array<bigint>")
    low, high = F.lit(0), F.lit(len(cuts))
    start = F.struct(low.alias("lo"), high.alias("hi"))

    def halve(at, _):
        middle = F.shiftright(at["lo"] + at["hi"], 1)
        below = F.get(table, middle) <= F.col(key)
        open_ = at["lo"] < at["hi"]
        return F.struct(F.when(open_ & below, middle + 1).otherwise(at["lo"]).alias("lo"), F.when(open_ & ~below, middle).otherwise(at["hi"]).alias("hi"))

    steps = F.array(*[F.lit(0)] * len(cuts).bit_length())
    return F.when(F.col(key).isNull(), F.lit(-1)).otherwise(F.aggregate(steps, start, halve, lambda at: at["lo"]))


# ---------------------------------------------------------------- vectorised hashing


def mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser (splitmix64), elementwise."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def table64(seed: int, n: int = 256) -> np.ndarray:
    """n pseudo-random 64-bit values made from a seed."""
    with np.errstate(over="ignore"):
        return mix(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))


_BYTES = table64(11)
_POWER = 0x2545F4914F6CDD1D
_INVERSE = pow(_POWER, -1, 1 << 64)
_POWERS: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> list[np.ndarray]:
    if len(_POWERS[0]) < n:
        n = max(n, 1 << 19)
        for k, m in enumerate((_POWER, _INVERSE)):
            x = np.full(n, m, np.uint64)
            x[0] = 1
            _POWERS[k] = np.multiply.accumulate(x)
    return _POWERS


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts with a space after each, and where each begins (one more entry: the end)."""
    data = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
    starts = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=starts[1:])
    return data, starts


def words_of(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes other than ASCII white space."""
    space = _SPACE[data]
    edge = np.flatnonzero(space[1:] != space[:-1]) + 1
    if len(data) and not space[0]:
        edge = np.concatenate([[0], edge])
    if len(edge) % 2:
        edge = np.concatenate([edge, [len(data)]])
    return edge[0::2], edge[1::2]


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word: a polynomial over byte values, taken from one running sum, then mixed."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    up, down = _powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTES[data] * up[: len(data)], out=total[1:])
    return mix((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def batched(batches: Iterable[pa.RecordBatch], column: str = "text", size: int = BATCH_BYTES) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Slices of Arrow batches with about `size` bytes of text each; null texts are empty. Only a slice becomes strings."""
    for batch in batches:
        n = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        total, begin = np.cumsum(n), 0
        while begin < len(n):
            end = max(begin + 1, int(np.searchsorted(total, (total[begin - 1] if begin else 0) + size, "right")))
            part = batch.slice(begin, end - begin)
            yield part, [t or "" for t in part.column(column).to_pylist()]
            begin = end
    trim()


def trim() -> None:
    """Give freed memory back to the system: Python workers live on after a task and would keep its peak."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only where the C library has it
        ctypes.CDLL(None).malloc_trim(0)


def utf8(text: str) -> bytes:
    return text.encode("utf-8", "surrogatepass")


def connected(spark: SparkSession, links: DataFrame, tag: str = "components") -> DataFrame:
    """Smallest id reachable from each linked id: links(a, b) -> (id, root), by alternating large and small stars.

    Each round is written to the shared folder; the number of rounds grows with the logarithm of the longest chain.
    """
    edges = materialise(spark, links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), tag)
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").where("u <> v").distinct()
        after = materialise(spark, small, tag)
        same = edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first() == after.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        edges = after
        if same:
            return edges.select(F.col("u").alias("id"), F.col("v").alias("root"))


#: Rows of a few small columns that may be broadcast; beyond it the join shuffles.
BROADCAST_ROWS = 500_000


def bounded_broadcast(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint where a count proves it small, else df as it is. df should be materialised."""
    return F.broadcast(df) if df.count() <= rows else df
