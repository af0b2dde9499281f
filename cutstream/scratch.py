"""Tables written to the folder that driver and executors share, so that no job leans on long lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local"):  # a temporary folder is this machine's own
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="cutstream-")
        spark.conf.set("spark.checkpoint.dir", found)
    return found.rstrip("/")


def path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, tag: str, **options) -> DataFrame:
    """Write df once, with options of the writer, and read it back."""
    spark = df.sparkSession
    at = path(spark, tag)
    df.write.options(**options).parquet(at)
    return spark.read.schema(df.schema).parquet(at)


def exists(spark: SparkSession, at: str) -> bool:
    """Whether a path is there, through Spark's own file system layer."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(at)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)
