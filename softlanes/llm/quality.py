"""Quality classifier: random Fourier features of document statistics, ridge, isotonic calibration.

Every whole text becomes a row of statistics. Random cosines of the standardised statistics approximate
a Gaussian kernel; each partition of labelled rows sums its part of the normal equations, the parts are
added, and one small system gives the ridge scores. An isotonic fit (pool adjacent violators) on a fold
that the ridge did not see turns scores into probabilities.

Labels are learnt only from documents outside the held-out fold, and from at most ``max_rows`` of them, a
hash sample (a documented bound; statistics, features and scores cover every document).

Edge cases: null counts as an empty text, and every text gets a score; documents without an id are held
out; labels that disagree about one id are averaged; without two kinds of labels every score is the share
of good labels, or 0.5 without labels; repeated rows give repeated results; an empty table gives none;
extra columns are kept by ``keep_good``.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import held_out_fold, load, materialise

STATISTICS = [
    "log_bytes", "log_words", "lower", "upper", "digit", "space", "newline", "stop", "comma", "symbol", "bang", "pipe", "quote",
    "high", "word_length", "long_words", "short_words", "distinct", "top_word", "repeated_pairs", "capital_words", "marked_words",
    "log_lines", "distinct_lines", "line_words",
]
_CLASS = np.full(256, 11, np.int64)
for _i, _chars in enumerate([b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" \t\r\x0b\x0c", b"\n", b".", b",",
                             b"*&%$#@^~=+<>\\_", b"!?", b"|", b"'\"()[]{}:;-/`"]):
    _CLASS[list(_chars)] = _i
_CLASS[128:] = 12


def statistics(text: str | None) -> list[float]:
    """The statistics of one whole text, in the order of ``STATISTICS``; all are finite."""
    text = text or ""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    n = max(1, len(raw))
    share = np.bincount(_CLASS, weights=np.bincount(raw, minlength=256), minlength=13) / n
    words = text.split()
    w = max(1, len(words))
    seen = Counter(words)
    lines = [x for x in text.split("\n") if x]
    pairs = len(words) - 1
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    return [
        math.log1p(len(raw)), math.log1p(len(words)), *share[:11].tolist(), float(share[12]),
        float(lengths.sum()) / w, float((lengths > 12).sum()) / w, float((lengths < 3).sum()) / w,
        len(seen) / w, max(seen.values(), default=0) / w,
        1 - len(set(zip(words, words[1:]))) / pairs if pairs > 0 else 0.0,
        sum(x[:2].isupper() and len(x) > 1 for x in words) / w,
        sum(not x[-1].isalnum() and x[-1] not in ".," for x in words) / w,
        math.log1p(len(lines)), len(set(lines)) / max(1, len(lines)), math.log1p(len(words) / max(1, len(lines))),
    ]


def document_statistics(df: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(doc_id, x array<double>)`` of every row."""

    def run(batches):
        for batch in batches:
            rows = [statistics(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.float64()))], names=["doc_id", "x"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, x array<double>")


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    waves: np.ndarray
    phase: np.ndarray
    weights: np.ndarray
    knots: np.ndarray
    levels: np.ndarray

    def features(self, x: np.ndarray) -> np.ndarray:
        return kernel_features((x - self.mean) / self.scale, self.waves, self.phase)

    def score(self, x: np.ndarray) -> np.ndarray:
        if not len(self.weights):
            return np.full(len(x), float(self.levels[0]))
        return np.clip(np.interp(self.features(x) @ self.weights, self.knots, self.levels), 0.0, 1.0)


def kernel_features(z: np.ndarray, waves: np.ndarray, phase: np.ndarray) -> np.ndarray:
    """Constant, the statistics themselves (clipped) and the random cosines."""
    z = np.clip(z, -6, 6)
    return np.hstack([np.ones((len(z), 1)), z, np.sqrt(2 / len(phase)) * np.cos(z @ waves + phase)])


def pool_adjacent_violators(value: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """The non-decreasing sequence nearest to ``value`` in weighted squares."""
    blocks: list[list[float]] = []
    for v, w in zip(value, weight):
        blocks.append([v, w, 1])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            v2, w2, n2 = blocks.pop()
            v1, w1, n1 = blocks.pop()
            blocks.append([(v1 * w1 + v2 * w2) / (w1 + w2), w1 + w2, n1 + n2])
    return np.concatenate([np.full(int(n), v) for v, _, n in blocks]) if blocks else np.empty(0)


def _summed(rows: DataFrame, part, length: int) -> np.ndarray:
    """Sum over partitions of ``part(x, y)``, a vector of ``length`` doubles; one row per partition is gathered."""

    def run(batches):
        total = np.zeros(length)
        for batch in batches:
            if batch.num_rows:
                x = np.stack(batch.column(0).to_numpy(zero_copy_only=False))
                total += part(x, batch.column(1).to_numpy(zero_copy_only=False))
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["part"])

    # the training rows are bounded, so a few partitions hold them
    parts = rows.select("x", "y").coalesce(16).mapInArrow(run, "part binary").collect()
    return sum((np.frombuffer(r.part) for r in parts), np.zeros(length))


def training_labels(labels: DataFrame, max_rows: int) -> DataFrame:
    """``(doc_id, y)`` outside the held-out fold: at most ``max_rows``, chosen by hash. This bound lets every join with it
    broadcast it, so no document is shuffled for training."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col("y").isNotNull() & ~held_out_fold(F.col("doc_id")))
    known = materialise(known.groupBy("doc_id").agg(F.avg(F.col("y").cast("double")).alias("y")), "quality-labels")
    n, coin = known.count(), F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30))
    if n <= max_rows:
        return known
    return materialise(known.where(coin < int((1 << 30) * 1.1 * max_rows / n)).orderBy(coin, "doc_id").limit(max_rows), "quality-labels")


def fit(stats: DataFrame, known: DataFrame, cosines: int = 160, ridge: float = 1e-3, width: float = 1.0, seed: int = 7) -> QualityModel:
    """Learn from ``stats(doc_id, x)`` and ``known(doc_id, y)``, which ``training_labels`` chose."""
    d = len(STATISTICS)
    rows = materialise(stats.join(F.broadcast(known), "doc_id").select("doc_id", "x", "y"), "quality-train")
    moments = _summed(rows, lambda x, y: np.concatenate([[len(x), y.sum()], x.sum(0), (x * x).sum(0)]), 2 + 2 * d)
    count, good = moments[:2]
    mean = moments[2 : 2 + d] / max(1, count)
    scale = np.sqrt(np.maximum(moments[2 + d :] / max(1, count) - mean**2, 1e-8))
    rng = np.random.default_rng(seed)
    waves, phase = rng.normal(size=(d, cosines)) / (width * np.sqrt(d)), rng.uniform(0, 2 * np.pi, cosines)
    if not 0 < good < count:
        level = good / count if count else 0.5
        none = np.empty(0)
        return QualityModel(mean, scale, waves, phase, none, none, np.array([level]))
    k = 1 + d + cosines
    remainder = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5

    def equations(x, y):
        f = kernel_features((x - mean) / scale, waves, phase)
        return np.concatenate([(f.T @ f).ravel(), f.T @ y])

    got = _summed(rows.where(remainder != 1), equations, k * k + k)
    weights = np.linalg.solve(got[: k * k].reshape(k, k) + ridge * max(1, got[0]) * np.eye(k), got[k * k :])
    model = QualityModel(mean, scale, waves, phase, weights, np.empty(0), np.empty(0))
    bins, low, high = 400, -0.5, 1.5

    def histogram(x, y):
        at = np.clip(((model.features(x) @ weights - low) / (high - low) * bins).astype(int), 0, bins - 1)
        return np.concatenate([np.bincount(at, minlength=bins), np.bincount(at, weights=y, minlength=bins)])

    seen = _summed(rows.where(remainder == 1), histogram, 2 * bins)
    total, ones = seen[:bins], seen[bins:]
    used = total > 0
    if not used.any():
        model.knots, model.levels = np.array([0.0, 1.0]), np.array([0.0, 1.0])
        return model
    model.knots = (low + (np.arange(bins) + 0.5) * (high - low) / bins)[used]
    model.levels = pool_adjacent_violators(ones[used] / total[used], total[used])
    return model


def scored(stats: DataFrame, model: QualityModel, threshold: float = 0.3) -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` of every row of ``stats``."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                s = model.score(np.stack(batch.column(1).to_numpy(zero_copy_only=False)))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s)], names=["doc_id", "score"])

    out = stats.select("doc_id", "x").mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", held_out_fold(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def quality_scores(df: DataFrame, labels: DataFrame, max_rows: int = 100_000, **settings) -> DataFrame:
    stats = materialise(document_statistics(df), "quality-stats")
    return scored(stats, fit(stats, training_labels(labels, max_rows), **settings))


def keep_good(df: DataFrame, labels: DataFrame, threshold: float = 0.3, max_rows: int = 100_000) -> DataFrame:
    """``df`` without the documents that the classifier rejects; scores are taken in the row, nothing is joined.
    Statistics are taken of the bounded training rows first, then once of every row."""
    known = training_labels(labels, max_rows)
    model = fit(document_statistics(df.join(F.broadcast(known.select("doc_id")), "doc_id", "left_semi")), known)

    @F.pandas_udf("double")
    def score(texts):
        import pandas as pd

        x = np.array([statistics(t) for t in texts.fillna("")]).reshape(len(texts), len(STATISTICS))
        return pd.Series(model.score(x), index=texts.index)

    return df.where(score("text") >= threshold)


def op4_fourier_quality(spark, sf_dir: str) -> DataFrame:
    labels = load(spark, sf_dir, "labels").select("doc_id", F.col("quality").alias("y"))
    return quality_scores(load(spark, sf_dir, "documents"), labels)
