"""Edge lists and vertex-stream text files, and sinks for assignments."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv", sep: str = " ") -> DataFrame:
    """Raw edges (a, b, weight) from csv, json or plain text (gzipped too); a missing weight is 1, comment lines go."""
    if fmt == "json":
        raw = spark.read.schema("a long, b long, weight double").json(path)
    elif fmt == "csv":
        raw = spark.read.schema("a long, b long, weight double").option("sep", sep).option("comment", "#").option("mode", "DROPMALFORMED").csv(path)
    else:
        part = F.split(F.trim("value"), r"\s+")
        raw = spark.read.text(path).where(~F.col("value").rlike("^[#%]") & (F.trim("value") != "")).select(part[0].cast("long").alias("a"), part[1].cast("long").alias("b"), F.try_element_at(part, F.lit(3)).cast("double").alias("weight"))
    return raw.withColumn("weight", F.coalesce("weight", F.lit(1.0)))


def write_edge_list(edges: DataFrame, path: str, sep: str = " ") -> None:
    edges.select("src", "dst", "weight").write.mode("overwrite").option("sep", sep).option("compression", "gzip").csv(path)


class _Slice(InputPartition):
    def __init__(self, path: str, begin: int, end: int, line: int):
        self.path, self.begin, self.end, self.line = path, begin, end, line


class AdjacencyReader(DataSourceReader):
    """Splits a file at line ends every `split` bytes; a slice knows the number of its first vertex."""

    def __init__(self, options: dict):
        self.path, self.split = options["path"], int(options.get("split", 32 << 20))

    def partitions(self) -> list[_Slice]:
        out, line, begin = [], 0, 0
        with open(self.path, "rb") as f:
            f.readline()  # the header
            begin = at = f.tell()
            first = 0
            for raw in f:
                at += len(raw)
                line += 1
                if at - begin >= self.split:
                    out.append(_Slice(self.path, begin, at, first))
                    begin, first = at, line
            if at > begin:
                out.append(_Slice(self.path, begin, at, first))
        return out

    def read(self, partition: _Slice) -> Iterator[tuple]:
        with open(partition.path, "rb") as f:
            f.seek(partition.begin)
            pos = partition.line
            while f.tell() < partition.end:
                numbers = [int(x) - 1 for x in f.readline().split()]
                yield pos, numbers
                pos += 1


class AdjacencyText(DataSource):
    """spark.read.format("adjacency"): header `n m`, then for each vertex a line of its neighbours, counted from 1.

    The path must be on a folder that driver and executors mount.
    """

    @classmethod
    def name(cls) -> str:
        return "adjacency"

    def schema(self) -> str:
        return "pos long, nbrs array<long>"

    def reader(self, schema: StructType) -> AdjacencyReader:
        return AdjacencyReader(self.options)


def read_adjacency_text(spark: SparkSession, path: str, split: int = 32 << 20) -> DataFrame:
    spark.dataSource.register(AdjacencyText)
    return spark.read.format("adjacency").option("split", split).load(path)


def write_adjacency_text(g, path: str) -> None:
    """One text file in position order, for exchange with other tools; a single ordered task writes it."""
    half = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("pos"), F.col("dst").alias("o")), F.struct(F.col("dst").alias("pos"), F.col("src").alias("o")))).alias("x")).select("x.*")
    lists = half.groupBy("pos").agg(F.array_join(F.transform(F.array_sort(F.collect_list("o")), lambda x: (x + 1).cast("string")), " ").alias("line"))
    rows = g.nodes.select("pos").join(lists, "pos", "left").orderBy("pos").select(F.coalesce("line", F.lit("")).alias("line"))
    with open(path, "w", encoding="ascii") as f:
        f.write(f"{g.n} {g.m}\n")
        for r in rows.toLocalIterator():
            f.write(r.line + "\n")


def write_assignment(df: DataFrame, path: str) -> None:
    """Assignment by pass and buffer, so that one buffer's blocks are one folder."""
    df.withColumn("pass", F.lit(1)).write.mode("overwrite").partitionBy("pass", "batch_id").parquet(path)


def write_by_block(data: DataFrame, assignment: DataFrame, key: str, path: str, k: int) -> None:
    """Rows stored by the block of their key's vertex: data(key, ...), assignment(key, block)."""
    data.join(assignment, key).repartition(k, "block").sortWithinPartitions("block", key).write.mode("overwrite").partitionBy("block").parquet(path)
