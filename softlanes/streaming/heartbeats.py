"""Heartbeats of workers as a stream: iteration counts in windows, late beats, steps at the deadline, anytime decoding.

A batch run reads the same files with ``availableNow``; results land in Parquet folders that all executors see.
"""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from softlanes.operators.decode import apply_decode, decode_matrix, noise_weights
from softlanes.sources.session import materialise, shared_folder
from softlanes.sources.tables import load, read_heartbeats

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def beats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a stream of heartbeats; ``ts`` becomes a timestamp, since watermarks refuse one without a zone.

    The trailing pattern lets the source take a single file as well as a folder.
    """
    raw = read_heartbeats(spark, f"{sf_dir}/events.parque[t]", SCHEMA)
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").cast("int").alias("user_id"))


def run_once(stream: DataFrame, mode: str) -> DataFrame:
    """Run a query over what is there and return what it emitted, by (trigger)."""
    spark = stream.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/trigger={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("trigger", T.IntegerType())])).parquet(f"{folder}/out")


def latest(emitted: DataFrame, *keys: str) -> DataFrame:
    """The last update of each key."""
    rest = [c for c in emitted.columns if c not in {*keys, "trigger"}]
    return emitted.groupBy(*keys).agg(*[F.max_by(c, "trigger").alias(c) for c in rest])


def _window(df, width, slide=None):
    return df.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width)).agg(F.count("*").alias("n"))


def _ends(df, *more):
    return df.select(F.col("window.start").cast("timestamp_ntz").alias("start"), F.col("window.end").cast("timestamp_ntz").alias("end"), *more, "n")


def stream_tumbling(spark, sf_dir):
    """Beats by day in append mode: a day is emitted when the watermark has passed it."""
    out = _window(beats(spark, sf_dir).withWatermark("ts", "1 hour"), "1 day")
    return _ends(run_once(out, "append"))


def stream_sliding(spark, sf_dir):
    out = _window(beats(spark, sf_dir).withWatermark("ts", "1 hour"), "1 day", "6 hours")
    return _ends(run_once(out, "append"))


def stream_session(spark, sf_dir):
    """Sessions of a worker with gaps of at most two hours."""
    s = beats(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "2 hours").alias("window"), "user_id").agg(F.count("*").alias("n"))
    return _ends(run_once(s, "append"), "user_id")


def stream_deadline_steps(spark, sf_dir, deadline="2024-01-20"):
    """Steps of every lane by the deadline: later beats do not count."""
    s = beats(spark, sf_dir).where(F.col("ts") <= F.lit(deadline).cast("timestamp")).groupBy(F.col("user_id").alias("q")).agg(F.count("*").cast("int").alias("steps"))
    return latest(run_once(s, "update"), "q")


def stream_late_drop(spark, sf_dir):
    """Beats with repeats dropped within the watermark, then counted by worker."""
    twice = beats(spark, sf_dir)
    s = twice.unionByName(beats(spark, sf_dir)).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    emitted = run_once(s, "append")
    return emitted.groupBy("user_id").agg(F.count("*").alias("n"))


def stream_static_join(spark, sf_dir):
    """Heartbeats joined with a table of weights by the hour: the expected error a beat leaves."""
    table = spark.createDataFrame([(h, 0.85 ** (2.0 * h)) for h in range(24)], "hour int, value double")
    s = beats(spark, sf_dir).select("event_id", F.hour("ts").alias("hour")).join(F.broadcast(table), "hour").select("event_id", F.round("value", 9).alias("value"))
    return run_once(s, "append").select("event_id", "value")


KEPT_BEATS = 4096
STEPS_STATE = "done long, floor long, recent binary"


def count_steps(key, batches, state):
    """Stateful counter of one lane: distinct beats seen so far, in whatever order they come.

    The state is the count and the last ``KEPT_BEATS`` beat numbers; a beat older than all of those counts as a repeat.
    """
    done, floor, recent = state.get if state.exists else (0, -1, b"")
    seen = np.frombuffer(bytes(recent), np.int64)
    for pdf in batches:
        ids = np.unique(pdf["event_id"].to_numpy().astype(np.int64))
        new = np.setdiff1d(ids[ids > floor], seen, assume_unique=True)
        done, seen = done + len(new), np.union1d(seen, new)
    if len(seen) > KEPT_BEATS:
        floor, seen = int(seen[-KEPT_BEATS - 1]), seen[-KEPT_BEATS:]
    state.update((int(done), int(floor), seen.astype(np.int64).tobytes()))
    yield pd.DataFrame({"q": [key[0]], "steps": [int(done)]})


def stream_stateful_steps(spark, sf_dir):
    """Lane step counts by custom state: beats come numbered, late ones count, repeats of a number do not."""
    s = beats(spark, sf_dir).groupBy("user_id").applyInPandasWithState(count_steps, "q int, steps int", STEPS_STATE, "update", "NoTimeout")
    return latest(run_once(s, "update"), "q")


class AnytimeDecoder:
    """Decodes the present state whenever beats arrive: ``update`` for ``foreachBatch``.

    ``states`` maps a step count to the lanes' values there (``vec(i, p, v)`` of real codes); lanes past the last
    mark stay at it. Each batch adds its counts, rebuilds the decode matrix and writes an estimate.
    """

    def __init__(self, g: np.ndarray, tau: np.ndarray, states: dict[int, DataFrame], folder: str):
        self.g, self.tau, self.states, self.folder = g, tau, states, folder
        self.steps = np.zeros(g.shape[1], int)

    def update(self, batch: DataFrame, number: int) -> None:
        for r in batch.where(F.col("q") < len(self.steps)).groupBy("q").agg(F.count("*").alias("n")).collect():  # lanes at most
            self.steps[r.q] += r.n
        marks = np.array(sorted(self.states))
        at = marks[np.maximum(np.searchsorted(marks, self.steps, side="right") - 1, 0)]
        state = None
        for mark in np.unique(at):
            lanes = [int(q) for q in np.flatnonzero(at == mark)]
            part = self.states[int(mark)].where(F.col("p").isin(lanes))
            state = part if state is None else state.unionByName(part)
        r = decode_matrix(self.g, noise_weights(self.tau, at.tolist()))
        apply_decode(state, self.g, r).select("i", "p", "v").write.mode("overwrite").parquet(f"{self.folder}/trigger={number}")


def stream_anytime_decode(spark, sf_dir):
    """Estimates as all beats of the lanes come in, three files of them: error of the decode after each trigger."""
    from softlanes.operators import codes, engine, metrics, systems
    from softlanes.plans.ranking import PAIR, walk
    from softlanes.sources import graphs

    g = codes.parity_code(2)
    system = walk(spark, sf_dir)
    inputs = materialise(graphs.in_segment(spark, sf_dir, PAIR), "inputs")
    forcing = materialise(system.forcing(engine.encode_columns(inputs, g)), "forcing")
    start = materialise(engine.encode_columns(systems.initial_state(system, [0, 1]), g), "start")
    shots = engine.snapshots(system, forcing, start, 3, [0, 4, 8, 16, 32, 64])
    folder = f"{shared_folder(spark)}/anytime-{uuid.uuid4().hex}"
    decoder = AnytimeDecoder(g, 0.85 ** (2.0 * np.arange(65)), shots, f"{folder}/out")
    events = load(spark, sf_dir, "events", "event_id", "ts", "user_id").where("user_id < 3")  # the three lanes there are
    for n, (a, b) in enumerate([("1970-01-01", "2024-01-08"), ("2024-01-08", "2024-01-22"), ("2024-01-22", "9999-01-01")]):
        part = events.where((F.col("ts") >= F.lit(a).cast("timestamp_ntz")) & (F.col("ts") < F.lit(b).cast("timestamp_ntz")))
        part.coalesce(1).write.parquet(f"{folder}/in/part={n}")
    stream = spark.readStream.schema("event_id long, ts timestamp_ntz, user_id long, part int").option("maxFilesPerTrigger", 1).parquet(f"{folder}/in").select(F.col("user_id").cast("int").alias("q"))
    stream.writeStream.foreachBatch(decoder.update).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    truth = engine.solve_converged(system, inputs, 2, tol=1e-17)
    found = spark.read.schema("i long, p int, v double, trigger int").parquet(f"{folder}/out")
    joined = found.join(truth.withColumnRenamed("v", "t"), ["i", "p"])
    return joined.groupBy("trigger").agg(F.sum((F.col("v") - F.col("t")) ** 2).alias("sse"))


_CUT = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
QUERIES = {
    "stream_tumbling": (stream_tumbling, f"""SELECT date_trunc('day', ts)::TIMESTAMP AS start, (date_trunc('day', ts) + INTERVAL 1 DAY)::TIMESTAMP AS "end", count(*) AS n
        FROM events GROUP BY 1, 2 HAVING "end" <= {_CUT}"""),
    "stream_sliding": (stream_sliding, f"""WITH w AS (SELECT unnest([time_bucket(INTERVAL 6 HOURS, ts) - INTERVAL 18 HOURS, time_bucket(INTERVAL 6 HOURS, ts) - INTERVAL 12 HOURS,
        time_bucket(INTERVAL 6 HOURS, ts) - INTERVAL 6 HOURS, time_bucket(INTERVAL 6 HOURS, ts)]) AS start FROM events)
        SELECT start::TIMESTAMP AS start, (start + INTERVAL 24 HOURS)::TIMESTAMP AS "end", count(*) AS n FROM w GROUP BY 1, 2 HAVING "end" <= {_CUT}"""),
    "stream_session": (stream_session, f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOURS THEN 0 ELSE 1 END AS new FROM events),
        s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
        SELECT user_id::INT AS user_id, min(ts) AS start, max(ts) + INTERVAL 2 HOURS AS "end", count(*) AS n FROM s GROUP BY user_id, k HAVING "end" <= {_CUT}"""),
    "stream_deadline_steps": (stream_deadline_steps, "SELECT user_id::INT AS q, count(*)::INT AS steps FROM events WHERE ts <= TIMESTAMP '2024-01-20' GROUP BY 1"),
    "stream_late_drop": (stream_late_drop, "SELECT user_id::INT AS user_id, count(*) AS n FROM events GROUP BY 1"),
    "stream_static_join": (stream_static_join, "SELECT event_id, round(power(0.85, 2.0 * hour(ts)), 9) AS value FROM events"),
    "stream_stateful_steps": (stream_stateful_steps, "SELECT user_id::INT AS q, count(*)::INT AS steps FROM events GROUP BY 1"),
    "stream_anytime_decode": (stream_anytime_decode, None),
}
