"""Functions callable from SQL: vectorised kernels and table functions. Built-in functions are preferred; these are
what they cannot express."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from softlanes.functions.hashing import hash_uniform_value
from softlanes.sources.session import ship_package


# type objects, not DDL: a DDL string is parsed by a session, and this module is imported before there is one
ARRAY = T.ArrayType(T.DoubleType())
GENERATOR = T.StructType([T.StructField("p", T.IntegerType()), T.StructField("q", T.IntegerType()), T.StructField("re", T.DoubleType()), T.StructField("im", T.DoubleType())])
LANES = T.StructType([T.StructField("q", T.IntegerType()), T.StructField("steps", T.IntegerType())])


@pandas_udf(ARRAY)
def vec_axpy(a: pd.Series, x: pd.Series, y: pd.Series) -> pd.Series:
    """``a * x + y`` on array columns, batch by batch; a null in any argument gives null."""
    return pd.Series([
        None if u is None or v is None or s is None or (isinstance(s, float) and math.isnan(s)) else s * np.asarray(u, float) + np.asarray(v, float)
        for s, u, v in zip(a, x, y)
    ], index=x.index)


@pandas_udf(ARRAY)
def vec_sum(x: pd.Series) -> np.ndarray:
    """Sum of arrays in a group. It has no partial form, so it is for groups of bounded size only."""
    kept = [np.asarray(v, float) for v in x if v is not None]
    return np.sum(kept, axis=0).tolist() if kept else []


@udtf(returnType=GENERATOR)
class DftRows:
    """``dft_rows(n, k)``: the Fourier generator."""

    def eval(self, n: int, k: int):
        for p in range(k):
            for q in range(n):
                angle = 2 * math.pi * p * q / n
                yield p, q, math.cos(angle) / math.sqrt(n), -math.sin(angle) / math.sqrt(n)


@udtf(returnType=LANES)
class StragglerLaw:
    """``straggler_law(law, n, seed, deadline)``: step counts of n lanes; laws 'exponential', 'uniform', 'two_point'."""

    def eval(self, law: str, n: int, seed: int, deadline: float):
        for q in range(n):
            u = hash_uniform_value(q, seed)
            if law == "exponential":
                yield q, math.ceil(float(deadline) / -math.log1p(-u))
            elif law == "uniform":
                yield q, 1 + math.floor(u * 20)
            elif law == "two_point":
                yield q, 5 if u < 0.5 else 20
            else:
                raise ValueError(law)


def register_all(spark: SparkSession) -> None:
    ship_package(spark)
    spark.udf.register("vec_axpy", vec_axpy)
    spark.udf.register("vec_sum", vec_sum)
    spark.udtf.register("dft_rows", DftRows)
    spark.udtf.register("straggler_law", StragglerLaw)
