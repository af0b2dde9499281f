"""Harmonic packing of token ids into fixed sequences, independently in every task, without a shuffle.

Lengths fall into reciprocal-capacity classes: class j holds lengths above capacity / (j + 1) and up to capacity / j, for
j from 1 to capacity, and a bin of class j always takes exactly j documents. Of a document longer than a sequence, whole
sequences are cut off first; what is left (the rest of its length by the capacity) is classified.

A full bin of class j still has a gap of less than capacity - j capacity / (j + 1) ids. As documents may be cut freely, one
document at a time is the filler of a task: gaps are filled with pieces of it in the order in which bins become full, and
when it is used up the next document becomes the filler. So bins have no padding, all documents but the fillers stay in
one piece (plus the whole sequences cut off), and a task holds at most one open bin of each class and the few full ones
that wait for a filler. At a task's end the open bins' pieces run on from sequence to sequence; the ids of the last one are
split by the binary digits of their number into sequences whose length is a power of two, which need no padding either.

A null text is an empty one: it yields only its end id. Repeated rows are packed as separate documents. Extra columns
are ignored. Sequence ids are unique: the partition's number in the high bits, a running number in the low ones.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from cutstream.llm.common import batched
from cutstream.llm.tokens import default_vocabulary, encoder

CAPACITY = 2048
END_ID = 1
_NAMES = ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


class Piece:
    """Ids start to start + len(raw) / 4 of a document."""

    __slots__ = ("doc_id", "raw", "start", "total")

    def __init__(self, doc_id: int | None, start: int, raw: bytes, total: int):
        self.doc_id, self.start, self.raw, self.total = doc_id, start, raw, total

    def __len__(self) -> int:
        return len(self.raw) // 4

    def split(self, n: int) -> tuple[Piece, Piece]:
        return Piece(self.doc_id, self.start, self.raw[: 4 * n], self.total), Piece(self.doc_id, self.start + n, self.raw[4 * n :], self.total)


class Bins:
    """One task's bins. add and close return rows of pieces whose sequences are complete."""

    def __init__(self, capacity: int, first_id: int):
        self.capacity, self.next_id = capacity, first_id
        self.open: dict[int, list[Piece]] = {}
        self.waiting: list[tuple[list[Piece], int]] = []  # full bins, the first of which gets the filler, and their gaps
        self.filler: Piece | None = None

    def _emit(self, pieces: list[Piece]) -> list[tuple]:
        out, offset = [], 0
        for p in pieces:
            out.append((p.doc_id, p.start, len(p), zlib.crc32(p.raw), p.total, self.next_id, offset))
            offset += len(p)
        self.next_id += 1
        return out

    def whole(self, piece: Piece) -> list[tuple]:
        """A piece that fills a sequence by itself."""
        return self._emit([piece])

    def add(self, piece: Piece) -> list[tuple]:
        """piece: a document, or what whole sequences leave of it; at most capacity ids."""
        if self.filler is None:
            self.filler = piece
            return self._fill()
        j = self.capacity // len(piece)
        held = self.open.setdefault(j, [])
        held.append(piece)
        if len(held) < j:
            return []
        del self.open[j]
        self.waiting.append((held, self.capacity - sum(map(len, held))))
        return self._fill()

    def _fill(self) -> list[tuple]:
        out = []
        while self.waiting and (self.filler is not None or not self.waiting[0][1]):
            held, gap = self.waiting[0]
            if gap:
                n = min(gap, len(self.filler))
                own, rest = self.filler.split(n)
                held.append(own)
                gap -= n
                self.filler = rest if len(rest) else None
            if gap:
                self.waiting[0] = (held, gap)
            else:
                out += self._emit(held)
                self.waiting.pop(0)
        return out

    def close(self) -> list[tuple]:
        queue = [p for held, _ in self.waiting for p in held] + ([self.filler] if self.filler else []) + [p for _, held in sorted(self.open.items()) for p in held]
        self.open, self.waiting, self.filler = {}, [], None
        left = sum(map(len, queue))
        queue.reverse()
        out = []
        while left:
            room = self.capacity if left >= self.capacity else 1 << (left.bit_length() - 1)
            left -= room
            held = []
            while room:
                p = queue.pop()
                if len(p) > room:
                    p, rest = p.split(room)
                    queue.append(rest)
                held.append(p)
                room -= len(p)
            out += self._emit(held)
        return out


def pack(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset. capacity: a power of two."""
    if capacity & (capacity - 1):
        raise ValueError("capacity must be a power of two")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, bins = encoder(vocabulary), Bins(capacity, TaskContext.get().partitionId() << 33)

        def rows_out(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], list(_NAMES))

        for rows, texts in batched(batches):
            flat, ends = tool.ids(texts)
            raw = flat.astype("<u4")
            out, begin = [], 0
            for doc_id, end in zip(rows.column("doc_id").to_pylist(), ends.tolist(), strict=True):
                ids = raw[begin:end].tobytes() + end_id.to_bytes(4, "little")
                rest, begin = Piece(doc_id, 0, ids, len(ids) // 4), end
                while len(rest) > capacity:
                    whole, rest = rest.split(capacity)
                    out += bins.whole(whole)
                out += bins.add(rest)
            if out:
                yield rows_out(out)
        if out := bins.close():
            yield rows_out(out)

    return docs.select("doc_id", "text").mapInArrow(run, ", ".join(f"{x} long" for x in _NAMES))


def padding(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Sequences, their ids and padding: none at a length that is a power of two, else up to capacity."""
    from pyspark.sql import functions as F

    full = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.bit_count("n") == 1, 0).otherwise(F.lit(capacity) - F.col("n"))
    return full.agg(F.count("*").alias("sequences"), F.sum("n").alias("ids"), F.sum(pad).alias("padding"))


def op5_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences of 2,048 ids."""
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), default_vocabulary())


__all__ = ["Bins", "Piece", "op5_harmonic_packing", "pack", "padding"]
