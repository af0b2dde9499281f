"""Document fingerprints by locally consistent parsing.

A text is parsed bottom-up. On each level, runs of one symbol become a symbol of their own; deterministic coin tossing
(the lowest bit in which a symbol differs from its left neighbour, and that bit's value, a few times over) leaves labels
of a small alphabet of which neighbours differ; a phrase begins at each local maximum; its name is a hash of the names in
it. Whether a phrase begins at a place depends on a few neighbours only, so equal substrings get the same phrases in their
interior whatever surrounds them and wherever they begin. The names of all levels from a base level up, the highest of at
most `BASE` with at least `ENOUGH` names, are the text's set; its fingerprint is the `KEEP` smallest of their hashes in
hex, and the likeness of two fingerprints is the bottom-k estimate of the sets' Jaccard similarity (exact for small sets).

Null text: an empty one, with an empty fingerprint; two empty fingerprints have likeness 1, one empty has 0.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.llm.common import _powers, batched, bucket_column, mix, ordered_cuts, table64, utf8

BASE, ENOUGH, KEEP = 3, 8, 64
_NAME = table64(29)
#: Place of the lowest set bit of a byte (8 for none).
_LOWEST = np.array([8] + [(i & -i).bit_length() - 1 for i in range(1, 256)], np.uint8)


def _toss(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """One round of coin tossing on byte labels; a text's first symbol differs from its (missing) neighbour in bit 0."""
    left = np.empty_like(x)
    left[1:] = x[:-1]
    left[starts] = x[starts] ^ 1
    at = _LOWEST[x ^ left]
    return (at << 1) | ((x >> at) & 1)


def _toss_wide(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The first round on 64-bit names."""
    left = np.empty_like(x)
    left[1:] = x[:-1]
    left[starts] = x[starts] ^ np.uint64(1)
    d = x ^ left
    d &= ~d + np.uint64(1)
    at = ((d.astype(np.float64).view(np.uint64) >> np.uint64(52)) - np.uint64(1023)) & np.uint64(63)
    return ((at << np.uint64(1)) | ((x >> at) & np.uint64(1))).astype(np.uint8)


def _level(symbols: np.ndarray, names: np.ndarray | None, starts: np.ndarray, level: int) -> tuple[np.ndarray, np.ndarray]:
    """Names and starts of the next level. symbols: bytes on level 0 (names None), else the names. No text is empty."""
    new = np.empty(len(symbols), bool)
    new[1:] = symbols[1:] != symbols[:-1]
    new[starts] = True
    at = np.flatnonzero(new)
    run = np.diff(at, append=len(symbols))
    symbols = symbols[at]
    starts = np.searchsorted(at, starts)
    wide = _NAME[symbols] if names is None else symbols.copy()
    long_ = np.flatnonzero(run > 1)
    wide[long_] = mix(wide[long_] + run[long_].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))

    label = _toss(symbols, starts) if names is None else _toss(_toss_wide(symbols, starts), starts)
    label = _toss(_toss(label, starts), starts)
    begin = np.zeros(len(label), bool)
    begin[1:-1] = (label[1:-1] > label[:-2]) & (label[1:-1] >= label[2:])
    # No phrase begins at a text's second symbol, whose left is too short, or its last, whose right is another text.
    begin[(starts + 1)[starts + 1 < len(begin)]] = False
    begin[np.append(starts[1:], len(begin)) - 1] = False
    begin[starts] = True
    phrase = np.flatnonzero(begin)
    ends = np.append(phrase[1:], len(label))
    up, down = _powers(len(label) + 1)
    total = np.zeros(len(label) + 1, np.uint64)
    np.cumsum(wide * up[: len(label)], out=total[1:])
    made = mix((total[ends] - total[phrase]) * down[phrase] + (ends - phrase).astype(np.uint64) * np.uint64(0xD1B54A32D192ED03) + np.uint64(level))
    return made, np.searchsorted(phrase, starts)


def phrase_names(texts: list[bytes]) -> list[list[np.ndarray]]:
    """For each text, the names on each level from 1 up, until one is left."""
    out: list[list[np.ndarray]] = [[] for _ in texts]
    live = [i for i, t in enumerate(texts) if t]
    if not live:
        return out
    symbols = np.frombuffer(b"".join(texts[i] for i in live), np.uint8)
    starts = np.cumsum([0, *(len(texts[i]) for i in live[:-1])])
    names, level = None, 0
    while live:
        names, starts = _level(symbols, names, starts, level)
        level += 1
        edges = [*starts.tolist(), len(names)]
        keep, parts = [], []
        for i, a, b in zip(live, edges[:-1], edges[1:], strict=True):
            out[i].append(names[a:b])
            if b - a > 1:
                keep.append(i)
                parts.append(names[a:b])
        if len(keep) < len(live):
            names = np.concatenate(parts) if parts else names[:0]
            starts = np.cumsum([0, *(len(p) for p in parts[:-1])])
        live, symbols = keep, names
    return out


def bottom(levels: list[np.ndarray]) -> np.ndarray:
    """The smallest 32-bit hashes of a text's set of phrase names."""
    if not levels:
        return np.zeros(0, np.uint32)
    base = next((i for i in range(min(BASE, len(levels)) - 1, 0, -1) if len(levels[i]) >= ENOUGH), 0)
    flat = np.concatenate(levels[base:]) >> np.uint64(32)
    if len(flat) > 4 * KEEP:  # copies may hide among the smallest, so take some more first
        some = np.unique(np.partition(flat, 2 * KEEP)[: 2 * KEEP])
        if len(some) >= KEEP:
            return some[:KEEP].astype(np.uint32)
    return np.unique(flat)[:KEEP].astype(np.uint32)


def to_text(fp: np.ndarray) -> str:
    return fp.astype(">u4").tobytes().hex()


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    union = np.union1d(a, b)[:KEEP]
    return float((np.isin(union, a, assume_unique=True) & np.isin(union, b, assume_unique=True)).sum()) / len(union)


def fingerprints(texts: list[str]) -> list[np.ndarray]:
    return [bottom(x) for x in phrase_names([utf8(t) for t in texts])]


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint) of every row; map-only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            yield pa.RecordBatch.from_arrays([rows.column("doc_id").cast(pa.int64()), pa.array([to_text(f) for f in fingerprints(texts)])], ["doc_id", "fingerprint"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, fingerprint string")


def edited(text: str, following: str) -> str:
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def with_edits(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Fingerprints of each text, of its edit by the next text in doc_id order, and their likenesses.

    Rows are dealt to buckets of the id order; a bucket's first row also goes, as a guest, to the bucket before it (the
    first bucket's to the last), so each task has its rows' followers. Rows of equal doc_id follow in text order, null
    ids come first. The text is shuffled once.
    """
    cuts = ordered_cuts(docs, "doc_id")
    dealt = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", bucket_column("doc_id", cuts).alias("bucket"))
    heads = sorted(dealt.groupBy("bucket").agg(F.min("doc_id").alias("head")).collect(), key=lambda r: r.bucket)
    guests = spark.createDataFrame([(r.head, heads[i - 1].bucket) for i, r in enumerate(heads)], "head long, before int")
    twice = F.array(F.struct("bucket", F.lit(False).alias("guest")), F.struct(F.col("before").alias("bucket"), F.lit(True).alias("guest")))
    rows = dealt.join(F.broadcast(guests), F.expr("doc_id <=> head"), "left").select("doc_id", "text", F.explode(F.when(F.col("before").isNull(), F.slice(twice, 1, 1)).otherwise(twice)).alias("x")).select("x.bucket", "x.guest", "doc_id", "text")
    ordered = rows.repartition("bucket").sortWithinPartitions("bucket", "guest", "doc_id", "text")
    names = ("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []  # at most one row, whose follower is still to come: (bucket, guest, doc_id, text, fingerprint)
        for batch, texts in batched(batches):
            head = list(zip(*(batch.column(x).to_pylist() for x in ("bucket", "guest", "doc_id")), texts, strict=True))
            known = [*held, *head]
            pairs = [(a, b) for a, b in zip(known[:-1], known[1:], strict=True) if not a[1] and a[0] == b[0]]
            changed = [edited(a[3], b[3]) for a, b in pairs]
            made = fingerprints([*texts, *changed])
            full = [*held, *((*x, f) for x, f in zip(head, made[: len(texts)], strict=True))]
            held, out, k = full[-1:], [], len(texts)
            for a, b in zip(full[:-1], full[1:], strict=True):
                if not a[1] and a[0] == b[0]:
                    out.append((a[2], len(a[3]), hashlib.sha256(utf8(changed[k - len(texts)])).hexdigest(), to_text(a[4]), to_text(made[k]), likeness(a[4], made[k]), likeness(a[4], b[4])))
                    k += 1
            if out:
                kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], list(names))

    return ordered.mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def op3_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of every document and of its edited text."""
    return with_edits(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"))
