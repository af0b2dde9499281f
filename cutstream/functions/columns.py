"""Column functions and their SQL texts: keyed mixing, load penalty, gain, capacity."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

M31 = 1 << 31
#: Multipliers and shifts of the 31-bit mixer; products stay below 2^62.
MIX = (1103515245, 15, 1566083941, 13)


def mix31_sql(expr: str, seed: int, dialect: str = "spark") -> str:
    """The mixer as SQL text: the same numbers in Spark and in DuckDB."""
    a, s, b, t = MIX
    x = f"((({expr}) + {seed * 7919 % M31}) % {M31} * {a}) % {M31}"
    fold = (lambda e, n: f"(({e}) ^ shiftright({e}, {n}))") if dialect == "spark" else (lambda e, n: f"xor({e}, ({e}) >> {n})")
    return fold(f"(({fold(x, s)}) * {b}) % {M31}", t)


def mix31(column: str, seed: int = 0) -> Column:
    """Pseudo-random number below 2^31 from a whole number; column is SQL text."""
    return F.expr(mix31_sql(f"CAST({column} AS BIGINT)", seed))


def cut_number(column: str, cuts) -> Column:
    """Number of ascending cut points at or below a whole number, by a binary search in the plan."""
    if not len(cuts):
        return F.lit(0)
    table = F.from_json(F.lit(str([int(x) for x in cuts])), "array<bigint>")
    start = F.struct(F.lit(0).alias("lo"), F.lit(len(cuts)).alias("hi"))

    def halve(at: Column, _: Column) -> Column:
        middle = F.shiftright(at["lo"] + at["hi"], 1)
        below, open_ = F.get(table, middle) <= F.col(column), at["lo"] < at["hi"]
        return F.struct(F.when(open_ & below, middle + 1).otherwise(at["lo"]).alias("lo"), F.when(open_ & ~below, middle).otherwise(at["hi"]).alias("hi"))

    return F.aggregate(F.array(*[F.lit(0)] * len(cuts).bit_length()), start, halve, lambda at: at["lo"])


def penalty_expr(load: Column, alpha: float, gamma: float = 1.5) -> Column:
    """Marginal load penalty alpha * gamma * load^(gamma - 1)."""
    root = F.sqrt(load) if gamma == 1.5 else F.pow(load, F.lit(gamma - 1))
    return F.lit(alpha * gamma) * root


def gain_expr(connection: Column, weight: Column, load: Column, alpha: float, gamma: float = 1.5) -> Column:
    return connection - weight * penalty_expr(load, alpha, gamma)


def register_functions(spark: SparkSession) -> None:
    """SQL functions penalty(load, scale), gain(conn, weight, load, scale), capacity(total, k, eps) for this session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION penalty(load DOUBLE, scale DOUBLE) RETURNS DOUBLE RETURN scale * 1.5 * sqrt(load)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gain(conn DOUBLE, weight DOUBLE, load DOUBLE, scale DOUBLE) RETURNS DOUBLE RETURN conn - weight * (scale * 1.5 * sqrt(load))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION capacity(total BIGINT, k INT, eps DECIMAL(9,6)) RETURNS BIGINT RETURN CAST(ceil((1 + eps) * total / k) AS BIGINT)")
