"""How far each lane gets by the deadline: ``lane(q, steps, speed)``, where speed is the time of one iteration.

Random laws come from the hash of (lane, seed), so that any engine draws the same.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform, hash_uniform_value


def _lanes(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").cast("int").alias("q"))


def fixed_steps(spark: SparkSession, steps: list[int]) -> DataFrame:
    return spark.createDataFrame([(q, int(s), None) for q, s in enumerate(steps)], "q int, steps int, speed double")


def equal_steps(spark: SparkSession, n: int, s: int) -> DataFrame:
    return fixed_steps(spark, [s] * n)


def steps_from_speed(speeds: DataFrame, deadline: float, rounding: str = "ceil", startup: float = 0.0) -> DataFrame:
    """Iterations by ``deadline`` at a constant time per iteration, after a start-up time (loading the graph).

    "ceil" counts the iteration under way, "floor" only finished ones.
    """
    ratio = F.greatest(F.lit(0.0), F.lit(deadline - startup)) / F.col("speed")
    return speeds.select("q", (F.ceil(ratio) if rounding == "ceil" else F.floor(ratio)).cast("int").alias("steps"), "speed")


def exponential_speeds(spark: SparkSession, n: int, rate: float = 1.0, seed: int = 0, least: float = 0.0) -> DataFrame:
    return _lanes(spark, n).select("q", (F.lit(least) - F.log(1 - hash_uniform(F.col("q"), seed)) / rate).alias("speed"))


def uniform_steps(spark: SparkSession, n: int, low: int = 1, high: int = 20, seed: int = 0) -> DataFrame:
    return _lanes(spark, n).select("q", (low + F.floor(hash_uniform(F.col("q"), seed) * (high - low + 1))).cast("int").alias("steps"), F.lit(None).cast("double").alias("speed"))


def two_point_steps(spark: SparkSession, n: int, slow: int = 5, fast: int = 20, p_slow: float = 0.5, seed: int = 0) -> DataFrame:
    return _lanes(spark, n).select(
        "q", F.when(hash_uniform(F.col("q"), seed) < p_slow, slow).otherwise(fast).cast("int").alias("steps"), F.lit(None).cast("double").alias("speed")
    )


def table_steps(law: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """Independent draws from any law ``(steps, probability)``: a range join on the cumulative probabilities."""
    spark = law.sparkSession
    w = Window.orderBy("steps")  # the law is a parameter: a handful of rows
    cum = law.select("steps", F.sum("probability").over(w).alias("hi")).withColumn("lo", F.coalesce(F.lag("hi").over(w), F.lit(0.0)))
    drawn = _lanes(spark, n).withColumn("u", hash_uniform(F.col("q"), seed))
    return drawn.join(F.broadcast(cum), (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))).select(
        "q", F.col("steps").cast("int").alias("steps"), F.lit(None).cast("double").alias("speed")
    )


def steps_from_events(events: DataFrame, deadline: str) -> DataFrame:
    """A trace as lanes: the user is the worker, an event a finished iteration; those by the deadline count."""
    counted = events.groupBy(F.col("user_id").cast("int").alias("q")).agg(
        F.count(F.when(F.col("ts") <= F.lit(deadline).cast("timestamp_ntz"), 1)).cast("int").alias("steps")
    )
    return counted.select("q", "steps", F.lit(None).cast("double").alias("speed"))


def team_steps(events: DataFrame, deadline: str, n: int) -> DataFrame:
    """Workers of the trace in ``n`` teams, dealt by number: a team is a lane and has made as many steps as its slowest worker."""
    own = steps_from_events(events, deadline)
    return own.groupBy(F.pmod("q", F.lit(n)).cast("int").alias("q")).agg(F.min("steps").alias("steps"))


def order_statistics(lanes: DataFrame) -> DataFrame:
    """Lanes with their place by speed (ties by number); one row per lane, and lanes are a parameter."""
    return lanes.select("q", "speed", F.row_number().over(Window.orderBy("speed", "q")).alias("place"))


def kth_fastest(lanes: DataFrame, k: int) -> DataFrame:
    return order_statistics(lanes).where(F.col("place") == k)


def collected_steps(lanes: DataFrame) -> list[int]:
    """Step counts in lane order; the lanes are a parameter-sized table."""
    return [int(r.steps) for r in lanes.orderBy("q").collect()]


def draw_steps(law: str, n: int, seed: int, deadline: float = 20.0, p_slow: float = 0.5) -> np.ndarray:
    """The same laws on the driver, for loops over many draws."""
    u = np.array([hash_uniform_value(q, seed) for q in range(n)])
    if law == "exponential":
        return np.ceil(deadline / (-np.log1p(-u))).astype(int)
    if law == "shifted":
        return np.ceil(deadline / (1 - 0.5 * np.log1p(-u))).astype(int)
    if law == "uniform":
        return (1 + np.floor(u * 20)).astype(int)
    if law == "two_point":
        return np.where(u < p_slow, 5, 20)
    raise ValueError(law)
