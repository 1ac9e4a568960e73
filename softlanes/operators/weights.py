"""Noise weights: the expected squared residual of a problem after l steps, and cross moments of a common part."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.operators import engine
from softlanes.operators.engine import _block_of, csr_apply, shared_columns, shared_csr, solve_converged
from softlanes.operators.systems import AffineSystem, multiply
from softlanes.sources.session import materialise


def tau_exact(b: np.ndarray, c: np.ndarray, most: int) -> np.ndarray:
    """trace(B^l C B^lᵀ) for l = 0..most: small dense systems, for tests."""
    out = []
    for _ in range(most + 1):
        out.append(float(np.trace(c)))
        c = b @ c @ b.T
    return np.array(out)


def power_norms(system: AffineSystem, most: int, group: int = 256) -> np.ndarray:
    """Squared Frobenius norms of B^l for l = 0..most, exactly: each task pushes unit vectors of some nodes through the
    operator (of a checked size), one after the other and only over the entries they have reached."""
    shared = shared_columns(system)
    n = system.nodes.count()
    spark = system.op.sparkSession
    firsts = spark.range(0, n, group).repartition(max(1, min(n // group, 8 * int(spark.conf.get("spark.sql.shuffle.partitions")))))

    def work(batches):
        starts, row, w = shared.value
        size = len(starts) - 1
        for pdf in batches:
            total = np.zeros(most + 1)
            for first in pdf["id"]:
                for j in range(first, min(size, first + group)):
                    at, value = np.array([j]), np.ones(1)
                    total[0] += 1.0
                    for l in range(1, most + 1):
                        count = starts[at + 1] - starts[at]
                        place = np.repeat(starts[at] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
                        y = np.bincount(row[place], w[place] * np.repeat(value, count), size)
                        at = np.flatnonzero(y)
                        value = y[at]
                        total[l] += value @ value
            yield pd.DataFrame({"l": np.arange(most + 1), "s": total})

    rows = firsts.mapInPandas(work, "l int, s double").groupBy("l").agg(F.sum("s").alias("s")).collect()
    out = np.zeros(most + 1)
    for r in rows:
        out[r.l] = r.s
    return out


def tau_geometric(rho: float, most: int, scale: float = 1.0) -> np.ndarray:
    return scale * rho ** (2.0 * np.arange(most + 1))


def tau_monte_carlo(system: AffineSystem, probes: DataFrame, most: int, layout: str = "auto") -> DataFrame:
    """``tau(l, value)``: mean over probes of the squared norm of their residual after l steps, all l in one sweep.

    "lane": each task iterates some probes over the whole operator (checked size). "long": a product per step.
    "packed": a few probes at a time over row blocks. "auto": "lane" where the operator fits each task, else "packed"
    where the nodes do, else "long".
    """
    spark = system.op.sparkSession
    if layout == "auto":
        layout = "lane" if engine.choose_layout(system.op, system.nodes) == "lane" else "packed" if engine.fits_packed(system, 1) else "long"
    if layout == "packed":
        own, total, m = engine.packed(system), np.zeros(most + 1), probes.agg(F.max("p")).first()[0] + 1
        for first, count in own.chunks(m):
            x = own.dense(probes, first, count)
            for l in range(most + 1):
                total[l] += float((x * x).sum())
                x = own.product(x) if l < most else x
        return spark.createDataFrame([(l, v / m) for l, v in enumerate(total.tolist())], "l int, value double")
    if layout == "long":
        state, parts = materialise(probes, "probe"), []
        m = max(1, probes.select("p").distinct().count())
        for l in range(most + 1):
            parts.append(state.agg((F.sum(F.col("v") * F.col("v")) / m).alias("value")).select(F.lit(l).alias("l"), "value"))
            if l < most:
                state = materialise(multiply(system.op, state), "probe")
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out
    shared = shared_csr(system)

    def sweep(pdf: pd.DataFrame) -> pd.DataFrame:
        matrix = shared.value
        cols = sorted(pdf["p"].unique().tolist())
        x = _block_of(pdf, matrix[0], cols)
        rows = []
        for l in range(most + 1):
            rows += [(l, p, s) for p, s in zip(cols, (x * x).sum(axis=0))]
            x = csr_apply(matrix, x)
        return pd.DataFrame(rows, columns=["l", "p", "s"])

    return probes.select("i", "p", "v").groupBy("p").applyInPandas(sweep, "l int, p int, s double").groupBy("l").agg(F.avg("s").alias("value"))


def psi_monte_carlo(system: AffineSystem, probes: DataFrame, most: int) -> DataFrame:
    """``psi(a, b, value)``: mean inner product of a common probe's residuals after a and b steps.

    An operator too large for each task is applied step by step, and the residuals of all steps meet by node and probe.
    """
    spark = system.op.sparkSession
    if engine.choose_layout(system.op, system.nodes) != "lane":
        state = materialise(probes.select("i", "p", "v"), "probe")
        m, every = max(1, state.select("p").distinct().count()), state.select("i", "p", "v", F.lit(0).alias("l"))
        for l in range(1, most + 1):
            state = materialise(multiply(system.op, state).select("i", "p", "v"), "probe")
            every = every.unionByName(state.select("i", "p", "v", F.lit(l).alias("l")))
        own = every.groupBy("i", "p").agg(F.collect_list(F.struct("l", "v")).alias("x"))  # most + 1 entries
        pairs = own.select(F.explode("x").alias("s"), "x").select("s", F.explode("x").alias("t")).groupBy(
            F.col("s.l").alias("a"), F.col("t.l").alias("b")).agg((F.sum(F.col("s.v") * F.col("t.v")) / m).alias("value"))
        grid = spark.createDataFrame([(a, b) for a in range(most + 1) for b in range(most + 1)], "a int, b int")
        return grid.join(pairs, ["a", "b"], "left").select("a", "b", F.coalesce("value", F.lit(0.0)).alias("value"))
    shared = shared_csr(system)

    def sweep(pdf: pd.DataFrame) -> pd.DataFrame:
        matrix = shared.value
        x = _block_of(pdf, matrix[0], sorted(pdf["p"].unique().tolist()))
        kept = [x[:, 0]]
        for _ in range(most):
            x = csr_apply(matrix, x)
            kept.append(x[:, 0])
        gram = np.stack(kept) @ np.stack(kept).T
        a, b = np.indices(gram.shape)
        return pd.DataFrame({"a": a.ravel().astype(np.int32), "b": b.ravel().astype(np.int32), "s": gram.ravel()})

    return probes.select("i", "p", "v").groupBy("p").applyInPandas(sweep, "a int, b int, s double").groupBy("a", "b").agg(F.avg("s").alias("value"))


def error_probes(system: AffineSystem, inputs: DataFrame, problems: int, start_value: float | None = None) -> DataFrame:
    """Draws like the initial error: solve extra problems from the input law and subtract the starting point,
    the constant ``start_value`` at every node (1/N by default)."""
    truth = solve_converged(system, inputs, problems)
    n = max(1, system.nodes.count())
    s = 1.0 / n if start_value is None else start_value
    ps = F.broadcast(system.op.sparkSession.range(problems).select(F.col("id").cast("int").alias("p")))
    return system.nodes.crossJoin(ps).join(truth, ["i", "p"], "left").select("i", "p", (F.coalesce("v", F.lit(0.0)) - s).alias("v"))


def table_of(tau: DataFrame) -> np.ndarray:
    """The numbers of a tau table in order of l: as many as the steps that were asked for."""
    return np.array([r.value for r in tau.orderBy("l").collect()])


def square_of(psi: DataFrame) -> np.ndarray:
    rows = psi.collect()
    n = 1 + max(r.a for r in rows)
    out = np.zeros((n, n))
    for r in rows:
        out[r.a, r.b] = r.value
    return out


def nearest_positive(psi: np.ndarray) -> np.ndarray:
    """The nearest symmetric matrix without negative eigenvalues: an estimate of moments may have small ones."""
    value, vector = np.linalg.eigh((psi + psi.T) / 2)
    return (vector * np.maximum(value, 0.0)) @ vector.T


def stationary_weights(system: AffineSystem, own: DataFrame, common: DataFrame, rho: float, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(own, psi) for problems that mix ``1 - rho`` of their own part with ``rho`` of a common one.

    ``own`` and ``common`` are initial errors ``vec(i, p, v)`` of probes with only one of the parts (``error_probes``).
    What all own parts share, their mean, counts as common: a draw of the common part is ``rho`` times a common
    probe plus ``1 - rho`` times that mean. The mean of m probes carries an m-th of their spread, which is taken off.
    """
    m = max(2, own.select("p").distinct().count())
    mean, spread = moments_from_data(own)
    mixed = common.select("i", "p", F.col("v") * rho).toDF("i", "p", "v")
    ps = F.broadcast(common.select("p").distinct())
    shared = mean.select("i", (F.col("v") * (1 - rho)).alias("v")).crossJoin(ps).select("i", "p", "v")
    draws = materialise(mixed.unionByName(shared).groupBy("i", "p").agg(F.sum("v").alias("v")), "common")
    left = materialise(spread.select("i", "p", (F.col("v") * ((1 - rho) * (m / (m - 1)) ** 0.5)).alias("v")), "own")
    cross = square_of(psi_monte_carlo(system, left, most))
    return np.diag(cross).copy(), nearest_positive(square_of(psi_monte_carlo(system, draws, most)) - cross / m)


def mixed_weights(moments: np.ndarray, probes: int, rho: float) -> tuple[np.ndarray, np.ndarray]:
    """``stationary_weights`` of any mix from the ``moments`` of residuals of ``probes`` own and of common probes: by linearity a
    mix's residuals are the mixes of theirs."""
    own, mean, common, both = moments
    cross = (1 - rho) ** 2 * max(2, probes) / (max(2, probes) - 1) * (own - mean)
    psi = rho**2 * common + rho * (1 - rho) * (both + both.T) + (1 - rho) ** 2 * mean
    return np.diag(cross).copy(), nearest_positive(psi - cross / max(2, probes))


def tau_variance_bound(b: np.ndarray, steps: int, fourth_moment: float, probes: int) -> float:
    """Upper bound of the variance of the Monte-Carlo estimate: ‖B^l‖_F⁴ E‖a‖⁴ / m."""
    return float(np.linalg.norm(np.linalg.matrix_power(b, steps), "fro") ** 4 * fourth_moment / probes)


def moments_from_data(states: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Common part and own parts estimated from the problems' residuals ``vec(i, p, v)``: (mean over
    problems, deviations from it)."""
    common = states.groupBy("i").agg(F.avg("v").alias("v"))
    own = states.join(common.withColumnRenamed("v", "m"), "i").select("i", "p", (F.col("v") - F.col("m")).alias("v"))
    return common.select("i", F.lit(0).alias("p"), "v"), own
