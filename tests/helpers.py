"""Comparison of a Spark result with a DuckDB result, as unordered rows."""

from __future__ import annotations

import decimal
import math


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else (0.0 if v == 0 else round(v, 8))
    if isinstance(v, decimal.Decimal):
        return round(float(v), 8)
    if hasattr(v, "isoformat"):
        return v.isoformat()
    return v


def rows_of(df) -> list[tuple]:
    cols = sorted(df.columns)
    return sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=str)


def rows_of_sql(duck, sql: str) -> tuple[list[str], list[tuple]]:
    r = duck.sql(sql)
    cols = list(r.columns)
    at = [cols.index(c) for c in sorted(cols)]
    return sorted(cols), sorted((tuple(plain(x[i]) for i in at) for x in r.fetchall()), key=str)
