"""WARC archives of pages with a Zstandard dictionary: written in every task, then read back.

Each archive is one file: a skippable frame (magic 0x184D2A5D) that holds the dictionary, then one frame a record. The
dictionary is built from a bounded sample of the records to be archived (those of `SAMPLE` pages whose ids hash lowest). Of the
records whose payloads are equal and of at least `least` bytes, those of the largest page_id are responses; the others
are revisits that name it and carry no payload. Each record has its payload's length and SHA-1, checked on reading.

Null html: an empty payload. Null url: a record without target. A null page_id never is the largest; where all ids of equal
payloads are null, all are responses. Rows that repeat the largest page_id are all responses. Files go to the shared folder
under a temporary name and are renamed when whole, so a task that runs twice is harmless.
"""

from __future__ import annotations

import base64
import hashlib
import io
import os
import struct
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.llm.common import bounded_broadcast, materialise, scratch_path
from cutstream.llm.token_files import local_path

SKIPPABLE = 0x184D2A5D
SAMPLE, DICTIONARY_BYTES, LEVEL = 800, 1 << 16, 3
FILE_BYTES = 1 << 30
DATE = "2024-01-01T00:00:00Z"
REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def sha1_base32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def train(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A dictionary of at most `size` bytes; where too little is there to train on, the samples' own beginning bytes."""
    full = [p for p in samples if p]
    try:
        return zstandard.train_dictionary(size, full).as_bytes()
    except (zstandard.ZstdError, ValueError):
        return b"".join(full)[:size]


def record(kind: str, page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if kind == "revisit" else http + payload
    fields = [("WARC-Type", kind), ("WARC-Record-ID", f"<urn:page:{'' if page_id is None else page_id}>"), ("WARC-Date", DATE), ("WARC-Payload-Digest", f"sha1:{digest}"), ("Payload-Length", str(len(payload)))]
    if url:
        fields.append(("WARC-Target-URI", " ".join(url.split())))
    if kind == "revisit":
        fields += [("WARC-Profile", REVISIT), ("WARC-Refers-To", f"<urn:page:{refers_to}>")]
    fields += [("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    return ("WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields) + "\r\n").encode() + block + b"\r\n\r\n"


class Archive:
    """One file: dictionary frame first, then a frame a record; visible under its name once closed."""

    def __init__(self, path: str, dictionary: bytes):
        self.path, self.mark = path, f"{path}.{TaskContext.get().taskAttemptId() if TaskContext.get() else 0}.part"
        self.out = open(self.mark, "wb")
        self.out.write(struct.pack("<II", SKIPPABLE, len(dictionary)) + dictionary)
        self.tool = zstandard.ZstdCompressor(level=LEVEL, dict_data=_dictionary(dictionary), write_content_size=True)

    def add(self, raw: bytes) -> None:
        self.out.write(self.tool.compress(raw))

    def close(self) -> str:
        self.out.close()
        os.replace(self.mark, self.path)
        return self.path


def _dictionary(raw: bytes) -> zstandard.ZstdCompressionDict | None:
    if not raw:
        return None
    trained = raw[:4] == b"\x37\xa4\x30\xec"
    return zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_FULLDICT if trained else zstandard.DICT_TYPE_RAWCONTENT)


def records(path: str) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of each record of an archive, in order."""
    with open(path, "rb") as f:
        magic, size = struct.unpack("<II", f.read(8))
        if magic != SKIPPABLE:
            raise ValueError(f"{path} does not begin with a dictionary frame")
        tool = zstandard.ZstdDecompressor(dict_data=_dictionary(f.read(size)))
        with io.BufferedReader(tool.stream_reader(f, read_across_frames=True), 1 << 20) as text:
            while line := text.readline():
                if line != b"WARC/1.1\r\n":
                    raise ValueError(f"{path}: a record does not begin where it should")
                fields = {}
                while (line := text.readline()) != b"\r\n":
                    k, _, v = line.decode().rstrip("\r\n").partition(": ")
                    fields[k] = v
                block = text.read(int(fields["Content-Length"]))
                if text.read(4) != b"\r\n\r\n":
                    raise ValueError(f"{path}: a record does not end where it should")
                yield fields, block


def write(spark: SparkSession, pages: DataFrame, uri: str, least: int = 0) -> DataFrame:
    """Write the archives; returns (path, records) of each file, materialised."""
    folder = local_path(uri)
    os.makedirs(folder, exist_ok=True)
    page = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"))
    keys = page.select("page_id", F.sha1(F.col("html").cast("binary")).alias("sha"), F.octet_length("html").alias("n"))
    shared = materialise(spark, keys.where(F.col("n") >= least).groupBy("sha", "n").agg(F.max("page_id").alias("first"), F.count("*").alias("m")).where("m > 1 and first is not null").select(F.col("sha").alias("same"), "first"), "payloads")
    n = page.count()
    pick = F.pmod(F.xxhash64("page_id", F.lit("dictionary")), F.lit(1 << 40))
    near = page.where(pick < F.lit(int((1 << 40) * min(1.0, 1.5 * SAMPLE / max(1, n))))).select(pick.alias("u"), "page_id", "url", "html").limit(2 * SAMPLE).collect()
    samples = [(r.page_id, r.url, r.html.encode("utf-8", "surrogatepass")) for r in sorted(near, key=lambda r: (r.u, r.html))[:SAMPLE]]
    dictionary = spark.sparkContext.broadcast(train([record("response", i, url, p, sha1_base32(p), None) for i, url, p in samples]))
    named = page.withColumn("sha", F.sha1(F.col("html").cast("binary"))).join(bounded_broadcast(shared), F.expr("sha = same"), "left")
    rows = named.select("page_id", "url", "html", F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first")).alias("refers_to"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.makedirs(folder, exist_ok=True)
        part, archive, count, size, done = TaskContext.get().partitionId(), None, 0, 0, []
        for batch in batches:
            for page_id, url, html, refers_to in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if archive is None:
                    archive, count, size = Archive(os.path.join(folder, f"part-{part:06d}-{len(done):04d}.warc.zst"), dictionary.value), 0, 0
                payload = html.encode("utf-8", "surrogatepass")
                raw = record("response" if refers_to is None else "revisit", page_id, url, payload, sha1_base32(payload), refers_to)
                archive.add(raw)
                count, size = count + 1, size + len(raw)
                if size >= FILE_BYTES:
                    done.append((archive.close(), count))
                    archive = None
        if archive:
            done.append((archive.close(), count))
        yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in done], pa.string()), pa.array([x[1] for x in done], pa.int64())], ["path", "records"])

    return materialise(spark, rows.mapInArrow(run, "path string, records long"), "archives")


def read(files: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of every record, payloads checked."""

    def number(uri: str) -> int | None:
        x = uri.removeprefix("<urn:page:").removesuffix(">")
        return int(x) if x else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())

        def batch_of(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

        for batch in batches:
            for path, expected in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                out, n = [], 0
                for fields, block in records(path):
                    digest, kind = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"]
                    payload = block.partition(b"\r\n\r\n")[2]
                    if kind == "response" and (sha1_base32(payload) != digest or len(payload) != int(fields["Payload-Length"])):
                        raise ValueError(f"{path}: a payload does not have its digest")
                    out.append((number(fields["WARC-Record-ID"]), int(fields["Payload-Length"]), digest, kind, number(fields["WARC-Refers-To"]) if kind == "revisit" else None))
                    n += 1
                    if len(out) == 4096:
                        yield batch_of(out)
                        out = []
                if n != expected:
                    raise ValueError(f"{path} has {n} records, not {expected}")
                if out:
                    yield batch_of(out)

    spread = files.repartition(max(1, 4 * files.sparkSession.sparkContext.defaultParallelism))
    return spread.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def op8_warc_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page's record, read back from the archives."""
    return read(write(spark, spark.read.parquet(f"{sf_dir}/pages.parquet"), scratch_path(spark, "warc")))


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, strlen(h) AS n, sha1(h) AS x FROM p),
m AS (SELECT *, max(page_id) OVER (PARTITION BY x, n) AS first FROM d)
SELECT page_id, n AS payload_bytes,
  array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST((CAST('0x' || substr(x, CAST(1 + 10 * (i // 8) AS BIGINT), 10) AS BIGINT) >> CAST(35 - 5 * (i % 8) AS INTEGER)) & 31 AS INTEGER), 1)), '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to
FROM m
"""
