"""Costs of encoding, iterating, communicating and decoding: ``cost(metric, lane, value)``.

Operations are multiply-adds counted once each as two; complex codes double what a lane does.
"""

from __future__ import annotations

import time
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes import schemas
from softlanes.operators.codes import real_columns


def encode_decode_cost(spark, n_nodes: int, g: np.ndarray) -> DataFrame:
    """Encoding inputs and starting points, decoding, and building the decode matrix."""
    k, n = g.shape
    factor = len(real_columns(g)[1]) / n
    rows = [
        ("encode", None, 2.0 * n * k * n_nodes * factor), ("decode", None, float(n * k * n_nodes) * factor),
        ("decode_matrix", None, float(k**3 + k**2 * n)), ("encode_decode_order", None, float(n * k * n_nodes)),
    ]
    return spark.createDataFrame(rows, schemas.COST)


def lane_cost(op: DataFrame, nodes: DataFrame, lanes: DataFrame, g: np.ndarray) -> DataFrame:
    """Work of each lane (sparse and dense), values sent in and out, and work per value: a pure table computation."""
    _, owner = real_columns(g)
    doubled = lanes.sparkSession.createDataFrame([(q, float(owner.count(q))) for q in range(g.shape[1])], "q int, columns double")
    size = op.agg(F.count("*").cast("double").alias("entries")).crossJoin(nodes.agg(F.count("*").cast("double").alias("n_nodes")))
    base = lanes.join(F.broadcast(doubled), "q").crossJoin(F.broadcast(size))
    metrics = F.array(*[
        F.struct(F.lit(name).alias("metric"), value.alias("value")) for name, value in [
            ("sparse_operations", 2 * F.col("entries") * F.col("steps") * F.col("columns")),
            ("dense_operations", F.col("n_nodes") * F.col("n_nodes") * F.col("steps") * F.col("columns")),
            ("values_in", F.col("n_nodes") * F.col("columns")), ("values_out", F.col("n_nodes") * F.col("columns")),
            ("operations_per_value", F.col("steps") * F.col("entries") / F.col("n_nodes")),
        ]
    ])
    return base.select(F.col("q").alias("lane"), F.explode(metrics).alias("m")).select("m.metric", "lane", "m.value")


def weight_cost(spark, entries: int, n_nodes: int, probes: int, most: int, converge: int = 100) -> DataFrame:
    """One-time cost of estimating weights: solves of the probes, their sweep, and cross moments."""
    return spark.createDataFrame([
        ("probe_solves", None, 2.0 * entries * converge * probes), ("tau_sweep", None, 2.0 * entries * most * probes),
        ("psi_products", None, float(probes) * (most + 1) ** 2 * n_nodes),
    ], schemas.COST)


class PhaseCounters:
    """What Spark did in named phases: seconds, stages, tasks, shuffled bytes and task seconds.

        counters = PhaseCounters(spark)
        with counters.phase("encode"):
            ...
        counters.table()
    """

    def __init__(self, spark):
        self.spark, self.rows = spark, []

    def _stages(self) -> dict:
        scala = self.spark._jsc.sc()
        scala.listenerBus().waitUntilEmpty()  # counters arrive with the events
        store = scala.statusStore()
        default = [getattr(store, f"stageList$default${n}")() for n in range(2, 6)]
        found = store.stageList(None, *default)
        stages = [found.apply(i) for i in range(found.size())]
        return {(s.stageId(), s.attemptId()): s for s in stages if s.status().toString() == "COMPLETE"}

    @contextmanager
    def phase(self, name: str):
        before, began = set(self._stages()), time.monotonic()
        yield
        seconds = time.monotonic() - began
        new = [s for k, s in self._stages().items() if k not in before]
        self.rows.append((
            name, seconds, len(new), sum(s.numCompleteTasks() for s in new), sum(s.shuffleWriteBytes() for s in new),
            sum(s.inputBytes() for s in new), sum(s.executorRunTime() for s in new) / 1000.0,
        ))

    def table(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, "phase string, seconds double, stages int, tasks int, shuffle_bytes long, input_bytes long, task_seconds double")
