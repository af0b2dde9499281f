"""Token-id files: flat unsigned integers, 64-bit document offsets and ids, memory-mapped on reading.

A data set is a folder of shards in ascending doc_id order. Shard s has `s.bin` (the ids of its documents one after
another, unsigned 16-bit where the vocabulary fits, else 32-bit, little-endian), `s.idx` (unsigned 64-bit offsets, one
more than documents, in ids from the shard's start) and `s.doc` (signed 64-bit doc_ids). A shard's base, the ids of all
shards before it, is a prefix sum over the shards' totals, so shards are written at once and independently.

Null text: no ids but the end id. Null doc_id: before all others, read back as null. Equal doc_ids: in the order of their
texts. Files go to the shared folder through a temporary name and an atomic rename, so a task that runs twice is harmless.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator
from urllib.parse import unquote, urlparse

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.llm.common import batched, bucket_column, ordered_cuts, scratch_path
from cutstream.llm.tokens import default_vocabulary, encoder

END_ID = 2
_NULL = np.iinfo(np.int64).min
_READ_DOCS = 4096


def local_path(uri: str) -> str:
    """A shared folder as tasks open it. Only mounted (file:) folders can be memory-mapped."""
    p = urlparse(uri)
    if p.scheme not in ("", "file"):
        raise ValueError(f"token files need a shared mounted folder, not {uri}")
    return unquote(p.path)


class _Shard:
    def __init__(self, folder: str, bucket: int, dtype: np.dtype):
        self.base = os.path.join(folder, f"{bucket + 1:09d}")
        self.mark = f".{TaskContext.get().taskAttemptId()}.part"
        self.bucket, self.dtype, self.total, self.ids, self.offsets = bucket, dtype, 0, [], [0]
        self.out = open(self.base + ".bin" + self.mark, "wb")

    def add(self, ids: np.ndarray, ends: np.ndarray, doc_ids: list[int | None]) -> None:
        self.out.write(ids.astype(self.dtype).tobytes())
        self.offsets += (self.total + ends).tolist()
        self.total += len(ids)
        self.ids += [_NULL if x is None else x for x in doc_ids]

    def close(self) -> tuple[int, int, int]:
        self.out.close()
        for name, x in ((".idx", np.array(self.offsets, "<u8")), (".doc", np.array(self.ids, "<i8"))):
            with open(self.base + name + self.mark, "wb") as f:
                f.write(x.tobytes())
        for name in (".bin", ".idx", ".doc"):
            os.replace(self.base + name + self.mark, self.base + name)
        return self.bucket, len(self.ids), self.total


def write(spark: SparkSession, docs: DataFrame, uri: str, vocabulary: str, end_id: int = END_ID, dtype: str = "<u2") -> list[tuple[int, int, int, int]]:
    """Write docs as shards; returns (shard, documents, ids, base) in order, a few numbers for each shard."""
    folder, kind = local_path(uri), np.dtype(dtype)
    os.makedirs(folder, exist_ok=True)
    cuts = ordered_cuts(docs, "doc_id")
    dealt = docs.select("doc_id", "text", bucket_column("doc_id", cuts).alias("bucket"))
    sorted_ = dealt.repartition("bucket").sortWithinPartitions("bucket", "doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, shard, done = encoder(vocabulary), None, []
        os.makedirs(folder, exist_ok=True)
        for rows, texts in batched(batches):
            flat, ends = tool.ids(texts)
            n = np.diff(ends, prepend=0)
            out = np.full(len(flat) + len(texts), end_id, np.uint32)
            out[np.arange(len(flat)) + np.repeat(np.arange(len(texts)), n)] = flat
            ends = ends + np.arange(1, len(texts) + 1)
            if out.max() > np.iinfo(kind).max:
                raise ValueError(f"an id does not fit {kind}")
            bucket, ids = rows.column("bucket").to_numpy(), rows.column("doc_id").to_pylist()
            edges = [0, *(np.flatnonzero(bucket[1:] != bucket[:-1]) + 1).tolist(), len(bucket)]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                if shard is None or shard.bucket != bucket[a]:
                    if shard:
                        done.append(shard.close())
                    shard = _Shard(folder, int(bucket[a]), kind)
                first = int(ends[a - 1]) if a else 0
                shard.add(out[first : int(ends[b - 1])], ends[a:b] - first, ids[a:b])
        if shard:
            done.append(shard.close())
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in done], pa.int64()) for i in range(3)], ["shard", "docs", "ids"])

    made = sorted(tuple(r) for r in sorted_.mapInArrow(run, "shard long, docs long, ids long").collect())
    bases = np.concatenate([[0], np.cumsum([x[2] for x in made])[:-1]]) if made else []
    return [(*x, int(b)) for x, b in zip(made, bases, strict=True)]


def read(spark: SparkSession, uri: str, shards: list[tuple[int, int, int, int]], dtype: str = "<u2") -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the memory-mapped files."""
    folder, kind = local_path(uri), np.dtype(dtype)
    listed = spark.createDataFrame(shards, "shard long, docs long, ids long, base long")
    listed = listed.repartition(max(1, min(len(shards), 4 * spark.sparkContext.defaultParallelism)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, docs, ids, base in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                at = os.path.join(folder, f"{shard + 1:09d}")
                flat = np.memmap(at + ".bin", kind, "r")
                offsets, names = np.memmap(at + ".idx", "<u8", "r"), np.memmap(at + ".doc", "<i8", "r")
                if len(flat) != ids or len(names) != docs or int(offsets[-1]) != ids:
                    raise ValueError(f"{at} is not whole")
                for a in range(0, docs, _READ_DOCS):
                    o = offsets[a : a + _READ_DOCS + 1].astype(np.int64)
                    crc = [zlib.crc32(flat[x:y].astype("<u4").tobytes()) for x, y in zip(o[:-1].tolist(), o[1:].tolist(), strict=True)]
                    own = np.array(names[a : a + _READ_DOCS])
                    yield pa.RecordBatch.from_arrays([pa.array(own, mask=own == _NULL), pa.array(o[:-1] + base), pa.array(np.diff(o)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return listed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Offsets of every document, read back from the files."""
    uri = scratch_path(spark, "token-files")
    return read(spark, uri, write(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), uri, default_vocabulary()))
