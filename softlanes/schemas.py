"""Explicit schemas of every table the engine passes around, and their validation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


EDGE = "src bigint, dst bigint, weight double"
OP = "i bigint, j bigint, w double"
VEC = "i bigint, p int, v double"
WIDE = "i bigint, x array<double>"
GEN = "p int, q int, re double, im double"
LANE = "q int, steps int, speed double"
TAU = "l int, value double"
PSI = "a int, b int, value double"
SCORE = "scheme string, law string, deadline double, p int, sse double, mse double"
COST = "metric string, lane int, value double"

KEYS = {"edge": ["src", "dst"], "op": ["i", "j"], "vec": ["i", "p"], "gen": ["p", "q"], "lane": ["q"]}


class InvalidTable(ValueError):
    """A table with null or repeated keys, or without a needed column."""


def validated(df: DataFrame, kind: str) -> DataFrame:
    """``df`` unchanged, after checking that the key columns of ``kind`` are there, not null and unique.

    One aggregation with map-side combine; use it at the border, not inside a loop.
    """
    keys = KEYS[kind]
    missing = [k for k in keys if k not in df.columns]
    if missing:
        raise InvalidTable(f"{kind}: no column {missing}")
    null = F.lit(False)
    for k in keys:
        null = null | F.col(k).isNull()
    bad = df.groupBy(*keys).agg(F.count("*").alias("n")).where(null | (F.col("n") > 1)).limit(1).collect()
    if bad:
        raise InvalidTable(f"{kind}: null or repeated key {bad[0].asDict()}")
    return df
