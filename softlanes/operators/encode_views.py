"""Codes written as relations: the Fourier generator and its Gram matrix by column functions and joins."""

from __future__ import annotations

from math import pi, sqrt

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def dft_table(spark: SparkSession, n: int, k: int, digits: int = 9) -> DataFrame:
    """``gen(p, q, re, im)`` of the Fourier code, from two ranges (k x n rows, a parameter)."""
    p, q = spark.range(k).select(F.col("id").cast("int").alias("p")), spark.range(n).select(F.col("id").cast("int").alias("q"))
    angle = F.lit(2 * pi) * F.col("p") * F.col("q") / n
    scale = 1 / sqrt(n)
    out = p.crossJoin(F.broadcast(q)).select("p", "q", (F.cos(angle) * scale).alias("re"), (-F.sin(angle) * scale).alias("im"))
    return out.select("p", "q", (F.round("re", digits) + 0.0).alias("re"), (F.round("im", digits) + 0.0).alias("im"))


def dft_gram(spark: SparkSession, n: int, k: int, loads: DataFrame) -> DataFrame:
    """Real part of the rows' inner products over lanes of ``loads(q, v)``: near the identity where loads are near even."""
    g = dft_table(spark, n, k, 15).join(F.broadcast(loads), "q")
    a = g.select(F.col("p").alias("a"), "q", F.col("re").alias("ar"), F.col("im").alias("ai"), "v")
    b = g.select(F.col("p").alias("b"), "q", F.col("re").alias("br"), F.col("im").alias("bi"))
    return a.join(b, "q").groupBy("a", "b").agg((F.round(F.sum(F.col("v") * (F.col("ar") * F.col("br") + F.col("ai") * F.col("bi"))), 9) + 0.0).alias("re"))
