"""Scoring many schemes and draws on one run of the un-encoded problems.

By linearity a lane's residual is the mix of the problems' residuals at its step count. The problems are run
once; their residuals at every step mark are kept in blocks of nodes; each block then gives its part of the
squared error of any number of plans (generator, step counts, decode matrix), and the parts are added. Plans are
parameter-sized and go to every task.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.operators import baselines, codes, decode, engine, weights
from softlanes.operators.engine import _block_of, csr_apply, shared_csr
from softlanes.operators.systems import AffineSystem
from softlanes.sources.session import materialise

BLOCK = 512
GROUP = 8


@dataclass
class Plan:
    """What one scheme does in one draw: generator (k x n), step counts, decode matrix (n x k).

    ``mix`` (columns x k): the problems are mixes of the columns that were run; None where they are the first k of them.
    """

    labels: tuple
    g: np.ndarray
    steps: np.ndarray
    r: np.ndarray
    mix: np.ndarray | None = None


def error_blocks(system: AffineSystem, inputs: DataFrame, problems: int, most: int, start_value: float | None = None, tol: float = 1e-17, converge: int = 400) -> DataFrame:
    """``(b, g, data)``: residuals of a group of problems at steps 0..most, then the solution, on a block of nodes, as bytes.

    An operator too large for each task runs on the wide layout.
    """
    spark = system.op.sparkSession
    if engine.choose_layout(system.op, system.nodes) != "lane":
        return _wide_error_blocks(system, inputs, problems, most, start_value, tol, converge)
    shared = shared_csr(system)
    s0 = 1.0 / max(1, len(shared.value[0])) if start_value is None else start_value
    every = spark.createDataFrame([(-1, p, 0.0) for p in range(problems)], "i long, p int, v double")
    radius = system.radius

    def work(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        m = shared.value
        cols = sorted(pdf["p"].unique().tolist())
        f = _block_of(pdf[pdf["i"] >= 0], m[0], cols)
        x = np.full(f.shape, s0)
        kept, before, weight = [x], x, None
        for t in range(1, converge + 1):
            new = csr_apply(m, x) + f
            change = np.abs(new - x).max(initial=0)
            if t <= most:
                kept.append(new)
            elif change <= max(tol, engine.ROUND_OFF * np.abs(new).max(initial=0)):
                x = new
                break
            elif radius is not None:  # only the solution is wanted from here on
                weight = engine.chebyshev_weight(radius, weight)
                new = before + weight * (new - before) if weight != 1.0 else new
            before, x = x, new
        if change > engine.SLACK * np.abs(x).max(initial=0):
            raise engine.NotConverged(f"entries still change by {change} after {converge} steps")
        e = np.stack([*(k - x for k in kept), x])
        blocks = range(0, len(m[0]), BLOCK)
        return pd.DataFrame({"b": [a // BLOCK for a in blocks], "g": key[0], "data": [e[:, a : a + BLOCK].tobytes() for a in blocks]})

    rows = system.forcing(inputs).select("i", "p", "v").unionByName(every).withColumn("g", F.floor(F.col("p") / GROUP).cast("int"))
    return materialise(rows.groupBy("g").applyInPandas(work, "b int, g int, data binary"), "errors")


def _wide_error_blocks(system, inputs, problems, most, start_value, tol, converge) -> DataFrame:
    spark = system.op.sparkSession
    n = max(1, system.nodes.count())
    s0 = 1.0 / n if start_value is None else start_value
    ps = F.broadcast(spark.range(problems).select(F.col("id").cast("int").alias("p")))
    start = materialise(system.nodes.select("i").crossJoin(ps).select("i", "p", F.lit(s0).alias("v")), "start")
    forcing = materialise(system.forcing(inputs).select("i", "p", "v"), "forcing")
    shots = engine.snapshots(system, forcing, start, problems, list(range(most + 1)))
    shots[most + 1] = engine.solve_converged(system, inputs, problems, tol=tol, most=converge)
    every = None
    for l, shot in shots.items():
        own = shot.select("i", "p", "v", F.lit(l).alias("l"))
        every = own if every is None else every.unionByName(own)
    block = F.pmod(F.xxhash64("i"), F.lit(-(-n // BLOCK))).cast("int")

    def work(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        b, g = key
        ids, row = np.unique(pdf["i"].to_numpy(), return_inverse=True)
        x = np.zeros((most + 2, len(ids), min(GROUP, problems - g * GROUP)))
        x[pdf["l"].to_numpy(), row, pdf["p"].to_numpy() - g * GROUP] = pdf["v"].to_numpy()
        x[:-1] -= x[-1]
        return pd.DataFrame({"b": [b], "g": [g], "data": [x.tobytes()]})

    rows = every.withColumn("b", block).withColumn("g", F.floor(F.col("p") / GROUP).cast("int"))
    return materialise(rows.groupBy("b", "g").applyInPandas(work, "b int, g int, data binary"), "errors")


def _assembled(pdf: pd.DataFrame, problems: int, marks: int) -> np.ndarray:
    parts = []
    for g, data in sorted(zip(pdf["g"], pdf["data"])):
        width = min(GROUP, problems - g * GROUP)
        parts.append(np.frombuffer(data).reshape(marks, -1, width))
    return np.concatenate(parts, axis=2)


def moments(blocks: DataFrame, problems: int, most: int, probes: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(tau, tau of own parts, psi of the common part) from the probes' residuals: (most+1) or its square of numbers.

    Different probes share only the common part, so psi is the mean product of residuals over pairs of different
    probes, which has no share of the own parts, and those are what is left of tau.
    """
    marks, m = most + 1, len(probes)

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        e = _assembled(pdf, problems, marks + 1)[:marks, :, probes]
        total = e.sum(axis=2)
        same = np.einsum("anp,bnp->ab", e, e)
        pairs = (total @ total.T - same) / max(1, m * (m - 1))
        a, b = np.indices(same.shape)
        kinds = np.concatenate([np.zeros(marks), np.full(same.size, 1)]).astype(np.int32)
        value = np.concatenate([np.diag(same) / m, pairs.ravel()])
        at = np.concatenate([np.arange(marks), a.ravel() * marks + b.ravel()])
        return pd.DataFrame({"kind": kinds, "at": at, "value": value})

    rows = blocks.groupBy("b").applyInPandas(work, "kind int, at long, value double").groupBy("kind", "at").agg(F.sum("value").alias("value")).collect()
    tau, psi = np.zeros(marks), np.zeros(marks * marks)
    for r in rows:
        (tau, psi)[r.kind][r.at] = r.value
    psi = weights.nearest_positive(psi.reshape(marks, marks))
    return tau, np.maximum(tau - np.diag(psi), 1e-6 * tau), psi


def score(blocks: DataFrame, problems: int, most: int, plans: list[Plan], names: list[str]) -> DataFrame:
    """``(*names, p, sse)``: squared error of every problem under every plan."""
    spark = blocks.sparkSession
    shared = spark.sparkContext.broadcast([(p.g, np.minimum(p.steps, most), p.r, p.mix) for p in plans])
    marks = most + 1

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        e = _assembled(pdf, problems, marks + 1)
        rows = []
        for n, (g, steps, r, mix) in enumerate(shared.value):
            k = len(g)
            z = np.empty((e.shape[1], g.shape[1]), g.dtype)
            of = (lambda a: a[:, :k]) if mix is None else (lambda a: a[:, : len(mix)] @ mix)  # noqa: B023
            for mark in np.unique(steps):
                own = steps == mark
                z[:, own] = of(e[mark]) @ g[:, own]
            # decode whole lanes, solution included: a decode matrix that only nearly inverts the code must show it
            x = of(e[-1])
            sse = ((((x @ g + z) @ r).real - x) ** 2).sum(axis=0)
            rows.append(pd.DataFrame({"plan": np.int32(n), "p": np.arange(k, dtype=np.int32), "sse": sse}))
        return pd.concat(rows)

    got = blocks.groupBy("b").applyInPandas(work, "plan int, p int, sse double").groupBy("plan", "p").agg(F.sum("sse").alias("sse"))
    return labelled(got, plans, names)


def labelled(got: DataFrame, plans: list[Plan], names: list[str]) -> DataFrame:
    """``(*names, p, sse)`` from ``(plan, p, sse)``."""
    spark = got.sparkSession
    kinds = {str: "string", float: "double", int: "int"}
    schema = "plan int, " + ", ".join(f"{n} {kinds[type(v)]}" for n, v in zip(names, plans[0].labels))
    labels = spark.createDataFrame([(i, *p.labels) for i, p in enumerate(plans)], schema)
    return got.join(F.broadcast(labels), "plan").select(*names, "p", "sse")


def scheme_plans(g: np.ndarray, steps: np.ndarray, tau: np.ndarray, labels: tuple, schemes=("uncoded", "twins_best", "twins_weighted", "soft", "fastest_k"),
                 own: np.ndarray | None = None, psi: np.ndarray | None = None) -> list[Plan]:
    """Plans of the named schemes for one draw of step counts; labels are prefixed by the scheme."""
    k, n = g.shape
    last = len(tau) - 1
    at = np.minimum(steps, last)
    floor = decode.floor_tau(tau, float(tau[0]))
    out = []
    for name in schemes:
        if name == "uncoded":
            code, r = codes.identity_code(k), np.eye(k)
            out.append(Plan((name, *labels), code, steps[:k], r))
        elif name.startswith("twins"):
            rule = {"twins_best": "best", "twins_weighted": "inverse_root", "twins_inverse_mse": "inverse_mse"}[name]
            out.append(Plan((name, *labels), codes.twin_code(n, k), steps, baselines.twin_matrix(k, n, steps.tolist(), floor, rule)))
        elif name == "soft":
            solver = "syndrome" if codes.has_orthonormal_rows(g) else "qr"
            out.append(Plan((name, *labels), g, steps, decode.decode_matrix(g, floor[at], solver)))
        elif name == "soft_correlated":
            om = decode.correlated_weights(g, decode.floor_tau(own, float(tau[0]))[at], psi[np.ix_(at, at)])
            out.append(Plan((name, *labels), g, steps, decode.decode_matrix(g, om)))
        elif name == "soft_literal":
            out.append(Plan((name, *labels), g, steps, decode.decode_matrix(g, tau[at], "normal")))
        elif name == "no_straggler":
            out.append(Plan((name, *labels), codes.identity_code(k), np.full(k, steps.max()), np.eye(k)))
        elif name == "fastest_k":
            out.append(Plan((name, *labels), g, steps, baselines.fastest_k_matrix(g, steps.tolist())))
        else:
            raise ValueError(name)
    return out
