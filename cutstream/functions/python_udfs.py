"""Python-side functions: cosine, geometric mean and imbalance aggregates, and table functions on adjacency lines."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StructType


@pandas_udf(DoubleType())
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.stack(a.to_list()).astype(float), np.stack(b.to_list()).astype(float)
    return pd.Series((x * y).sum(1) / np.maximum(np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1), 1e-300))


@pandas_udf(DoubleType())
def geometric_mean(x: pd.Series) -> float:
    """Values below 1 count as 1, as a cut of no edge does in comparisons."""
    return float(np.exp(np.log(np.maximum(x.to_numpy(float), 1.0)).mean()))


@pandas_udf(DoubleType())
def imbalance(loads: pd.Series) -> float:
    return float(loads.max() / loads.mean() - 1)


@udtf(returnType=StructType().add("pos", LongType()).add("nbr", LongType()))
class AdjacencyLines:
    """Half-edges of one adjacency line: adjacency_lines(pos, text), neighbours counted from 1."""

    def eval(self, pos: int, text: str) -> Iterator[tuple]:
        for x in (text or "").split():
            yield pos, int(x) - 1


@udtf(returnType=StructType().add("a", LongType()).add("b", LongType()))
class NeighbourPairs:
    """All pairs of a sorted list of at most `cap` members: neighbour_pairs(list, cap)."""

    def eval(self, members: list, cap: int) -> Iterator[tuple]:
        own = sorted(set(members or []))
        if len(own) <= cap:
            for i, a in enumerate(own):
                for b in own[i + 1 :]:
                    yield a, b


def register(spark: SparkSession) -> None:
    from cutstream.functions.columns import register_functions

    register_functions(spark)
    for name, f in (("cosine", cosine), ("geometric_mean", geometric_mean), ("imbalance", imbalance)):
        spark.udf.register(name, f)
    spark.udtf.register("adjacency_lines", AdjacencyLines)
    spark.udtf.register("neighbour_pairs", NeighbourPairs)


def explain_text(df) -> str:
    """The formatted plan as text, for tests of plans."""
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


__all__ = ["AdjacencyLines", "NeighbourPairs", "cosine", "explain_text", "geometric_mean", "imbalance", "register"]
