"""Corpus pipeline of five stages: language, near duplicates, benchmark leaks, secrets, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept; all but the last return the
columns of documents. run() writes each stage's rows as Parquet to the shared folder and rereads them for the next.
Null texts: rejected by the language stage. Defaults of each stage: see the operators' modules in cutstream.llm.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cutstream.llm import decontaminate, language, ngram_join, packing, secrets
from cutstream.llm.common import documents, materialise
from cutstream.llm.tokens import default_vocabulary


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the language model rejects go. It learns from the training fold of the stage's own input."""
    return language.keep_identified(spark, docs, docs.where(~language.held_out()))


def join_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: shingles of five words, Jaccard of 0.8 or more."""
    return ngram_join.one_of_each(spark, docs, 5, 80)


def remove_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain a benchmark item go."""
    return decontaminate.clean(spark, docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; every document stays."""
    return secrets.redact(spark, docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents, packed into sequences."""
    return packing.pack(docs, default_vocabulary())


STAGES = [
    ("language_id", identify_language),
    ("ngram_jaccard_join", join_near_copies),
    ("benchmark_decontamination", remove_leaks),
    ("secret_scan", redact_secrets),
    ("packing", pack_sequences),
]

#: SQL cannot express the language model, the network or the tokenizer.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = materialise(spark, stage(spark, docs, sf_dir), f"stage-{name}")
    return materialise(spark, STAGES[-1][1](spark, docs, sf_dir), "stage-packing")
