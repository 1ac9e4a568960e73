"""What soft decoding is compared with: no redundancy, twins, hard erasure.

``state(i, p, v)`` holds real columns of real codes here: lane q is column q.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from softlanes.operators.codes import twin_choice
from softlanes.operators.decode import apply_decode


def uncoded(state: DataFrame, k: int) -> DataFrame:
    """Problem p is what lane p has."""
    return state.where(F.col("p") < k)


def twin_map(spark, n: int, k: int, policy: str = "first", seed: int = 0) -> DataFrame:
    """``(q, k)``: lane q works on problem k."""
    rows = [(p, p) for p in range(k)] + [(k + s, p) for s, p in enumerate(twin_choice(n, k, policy, seed))]
    return spark.createDataFrame(rows, "q int, k int")


def twins_best(state: DataFrame, lanes: DataFrame, n: int, k: int, policy: str = "first") -> DataFrame:
    """The twin with more steps wins; ties go to the primary. The choice is made on the lane table, then joined."""
    own = twin_map(state.sparkSession, n, k, policy).join(lanes.select("q", "steps"), "q")
    best = own.withColumn("r", F.row_number().over(Window.partitionBy("k").orderBy(F.desc("steps"), "q"))).where("r = 1")
    return state.join(F.broadcast(best.select("q", "k")), F.col("p") == F.col("q")).select("i", F.col("k").alias("p"), "v")


def twins_weighted(state: DataFrame, lanes: DataFrame, tau: DataFrame, n: int, k: int, policy: str = "first", weight: str = "inverse_root") -> DataFrame:
    """Weighted mean of twins: by 1 / sqrt(tau) of their step counts, or by 1 / tau ("inverse_mse")."""
    own = twin_map(state.sparkSession, n, k, policy).join(lanes.select("q", "steps"), "q").join(tau, F.col("steps") == F.col("l"))
    w = 1 / (F.sqrt("value") if weight == "inverse_root" else F.col("value"))
    weighed = own.select("q", "k", w.alias("w"))
    return state.join(F.broadcast(weighed), F.col("p") == F.col("q")).groupBy("i", F.col("k").alias("p")).agg(
        (F.sum(F.col("w") * F.col("v")) / F.sum("w")).alias("v")
    )


def fastest_lanes(steps: list[int], k: int) -> list[int]:
    """The k lanes with most steps, ties by number."""
    return sorted(sorted(range(len(steps)), key=lambda q: (-steps[q], q))[:k])


def fastest_k_matrix(g: np.ndarray, steps: list[int]) -> np.ndarray:
    """Decode matrix that inverts the fastest k columns and gives the others nothing."""
    k, n = g.shape
    own = fastest_lanes(steps, k)
    r = np.zeros((n, k), g.dtype)
    r[own] = np.linalg.inv(g[:, own])
    return r


def fastest_k_decode(state: DataFrame, g: np.ndarray, steps: list[int]) -> DataFrame:
    return apply_decode(state, g, fastest_k_matrix(g, steps)).select("i", "p", "v")


def erasure_or_fail(state: DataFrame, g: np.ndarray, steps: list[int], needed: int) -> DataFrame:
    """Only lanes with at least ``needed`` steps count as done; with fewer than k of them every value is null."""
    done = [q for q, s in enumerate(steps) if s >= needed]
    k = len(g)
    if len(done) < k:
        spark = state.sparkSession
        ps = F.broadcast(spark.range(k).select(F.col("id").cast("int").alias("p")))
        return state.select("i").distinct().crossJoin(ps).select("i", "p", F.lit(None).cast("double").alias("v"))
    r = np.zeros((g.shape[1], k), g.dtype)
    r[done[:k]] = np.linalg.inv(g[:, done[:k]])
    return apply_decode(state, g, r).select("i", "p", "v")


def twin_matrix(k: int, n: int, steps: list[int], tau: np.ndarray, rule: str, policy: str = "first") -> np.ndarray:
    """The same merges as decode matrices over the twin code, for scoring many draws at once."""
    r = np.zeros((n, k))
    r[:k, :k] = np.eye(k)
    for lane, p in enumerate(twin_choice(n, k, policy), start=k):
        if rule == "best":
            a, b = (1.0, 0.0) if steps[p] >= steps[lane] else (0.0, 1.0)
        else:
            power = 0.5 if rule == "inverse_root" else 1.0
            last = len(tau) - 1
            wa, wb = tau[min(steps[p], last)] ** -power, tau[min(steps[lane], last)] ** -power
            a, b = wa / (wa + wb), wb / (wa + wb)
        r[p, p], r[lane, p] = a, b
    return r
