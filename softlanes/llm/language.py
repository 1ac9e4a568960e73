"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads a whole text byte by byte, in windows of ``WINDOW`` bytes, from both ends; it labels
every position, and the document's probabilities are the mean over its positions. It is trained here, in
numpy, by back-propagation through time, on a bounded sample of labelled documents (``per_language`` rows
of each of the ``most_languages`` commonest languages, three windows of each; documented bounds). Prediction covers every byte of every text.

Edge cases: null texts and texts without a letter are ``und`` with score 0, and so is everything where
nothing can be learnt (``keep_recognised`` then keeps every text with a letter); documents without an id are held out; repeated rows give repeated results; an
empty table gives none; extra columns are kept by ``keep_recognised``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from softlanes.llm.bpe import slices
from softlanes.llm.shared import held_out_fold, load

WINDOW = 128
HIDDEN = 8
PAD = 256
_FOLD = np.arange(257, dtype=np.int16)
_FOLD[65:91] += 32
HAS_LETTER = r"\p{L}"


def _sigmoid(x: np.ndarray) -> np.ndarray:
    np.negative(x, out=x)
    np.exp(x, out=x)
    x += 1
    return np.reciprocal(x, out=x)


def _tanh(x: np.ndarray) -> np.ndarray:
    x *= 2
    x = _sigmoid(x)
    x *= 2
    x -= 1
    return x


@dataclass
class Recurrent:
    """Both directions' tables (input by byte, 257 x 3H), recurrences (H x 3H), and the output layer."""

    languages: list[str]
    table: np.ndarray
    rec: np.ndarray
    out: np.ndarray
    bias: np.ndarray

    def states(self, codes: np.ndarray, direction: int, store: bool = False):
        """Hidden states (T, B, H) over byte codes (T, B), read from the start or from the end."""
        h3, hid = self.table.shape[2], self.table.shape[2] // 3
        table, rec = self.table[direction], self.rec[direction]
        steps = range(len(codes)) if direction == 0 else range(len(codes) - 1, -1, -1)
        hs = np.empty((*codes.shape, hid), np.float32)
        kept = {} if store else None
        h = np.zeros((codes.shape[1], hid), np.float32)
        for t in steps:
            x, u = table.take(codes[t], axis=0), h @ rec
            zr = x[:, : 2 * hid] + u[:, : 2 * hid]
            np.clip(zr, -30, 30, out=zr)
            zr = _sigmoid(zr)
            z, r = zr[:, :hid], zr[:, hid:]
            n = u[:, 2 * hid : h3] * r
            n += x[:, 2 * hid :]
            np.clip(n, -15, 15, out=n)
            n = _tanh(n)
            new = h - n
            new *= z
            new += n
            if store:
                kept[t] = (h, z, r, n, u[:, 2 * hid :])
            h = new
            hs[t] = h
        return hs, kept

    def positions(self, codes: np.ndarray) -> np.ndarray:
        """Probabilities (T, B, L) of every position."""
        hid = self.rec.shape[1]
        logits = self.states(codes, 0)[0] @ self.out[:hid]
        logits += self.states(codes, 1)[0] @ self.out[hid:]
        logits += self.bias
        logits -= logits.max(axis=2, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(axis=2, keepdims=True)
        return logits


def _backward(net: Recurrent, codes, direction, kept, dh_out, grads) -> None:
    hid = net.rec.shape[1]
    rec = net.rec[direction]
    steps = range(len(codes) - 1, -1, -1) if direction == 0 else range(len(codes))
    carry = np.zeros((codes.shape[1], hid), np.float32)
    for t in steps:
        h, z, r, n, un = kept[t]
        dh = dh_out[t] + carry
        dn = dh * (1 - z) * (1 - n * n)
        dz = dh * (h - n) * z * (1 - z)
        dr = dn * un * r * (1 - r)
        dx = np.hstack([dz, dr, dn])
        du = np.hstack([dz, dr, dn * r])
        grads["rec"][direction] += h.T @ du
        carry = dh * z + du @ rec.T
        np.add.at(grads["table"][direction], codes[t], dx)


def train(windows: np.ndarray, labels: np.ndarray, languages: list[str], hidden: int = HIDDEN, rounds: int = 160, batch: int = 128, rate: float = 0.02, seed: int = 3) -> Recurrent:
    """Fit by Adam on windows (M, T) of byte codes and their label indices."""
    rng = np.random.default_rng(seed)
    n_out = len(languages)
    f32 = np.float32
    net = Recurrent(
        languages, rng.normal(0, 0.3, (2, 257, 3 * hidden)).astype(f32), rng.normal(0, 0.3, (2, hidden, 3 * hidden)).astype(f32),
        rng.normal(0, 0.3, (2 * hidden, n_out)).astype(f32), np.zeros(n_out, f32),
    )
    params = {"table": net.table, "rec": net.rec, "out": net.out, "bias": net.bias}
    first = {k: np.zeros_like(v) for k, v in params.items()}
    second = {k: np.zeros_like(v) for k, v in params.items()}
    weight = len(labels) / (n_out * np.maximum(1, np.bincount(labels, minlength=n_out)))
    for step in range(1, rounds + 1):
        pick = rng.integers(0, len(windows), batch)
        codes, y = windows[pick].T, labels[pick]
        (hf, kf), (hb, kb) = net.states(codes, 0, True), net.states(codes, 1, True)
        both = np.concatenate([hf, hb], axis=2)
        logits = both @ net.out + net.bias
        logits -= logits.max(axis=2, keepdims=True)
        p = np.exp(logits)
        p /= p.sum(axis=2, keepdims=True)
        real = (codes != PAD)[:, :, None] * weight[y][None, :, None]
        p[:, np.arange(batch), y] -= 1
        d = (p * real / max(1.0, float(real.sum()))).astype(f32)
        grads = {k: np.zeros_like(v) for k, v in params.items()}
        grads["out"] += np.einsum("tbh,tbl->hl", both, d, optimize=True)
        grads["bias"] += d.sum(axis=(0, 1))
        dh = d @ net.out.T
        _backward(net, codes, 0, kf, dh[:, :, :hidden], grads)
        _backward(net, codes, 1, kb, dh[:, :, hidden:], grads)
        norm = float(np.sqrt(sum((g * g).sum() for g in grads.values())))
        for k, g in grads.items():
            g *= min(1.0, 1.0 / max(norm, 1e-12))
            first[k] += 0.1 * (g - first[k])
            second[k] += 0.01 * (g * g - second[k])
            lr = rate * min(1.0, 2 * (1 - step / (rounds + 1)))
            params[k] -= lr * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-8)
    return net


def codes_of(texts: list[bytes], window: int) -> tuple[np.ndarray, np.ndarray]:
    """Folded byte codes in windows (M, window), padded at each text's end, and the text of each window."""
    rows = [-(-len(t) // window) for t in texts]
    flat = np.full(sum(rows) * window, PAD, np.int16)
    at = 0
    for t, n in zip(texts, rows):
        flat[at : at + len(t)] = np.frombuffer(t, np.uint8)
        at += n * window
    return _FOLD[flat].reshape(-1, window), np.repeat(np.arange(len(texts)), rows)


def predict(net: Recurrent, texts: list[str], at_once: int = 2048) -> np.ndarray:
    """Mean probabilities (documents, languages) over all positions; empty texts have zeros."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    codes, of = codes_of(raw, WINDOW)
    out = np.zeros((len(texts), len(net.languages)))
    for i in range(0, len(codes), at_once):
        block = np.ascontiguousarray(codes[i : i + at_once].T)
        p = net.positions(block)
        p *= (block != PAD)[:, :, None]
        np.add.at(out, of[i : i + at_once], p.sum(axis=0))
    return out / np.maximum(1, np.array([len(r) for r in raw]))[:, None]


def training_windows(df: DataFrame, per_language: int = 600, width: int = 64, most_languages: int = 256) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """Three windows of each of at most ``per_language`` labelled documents of a language, chosen by hash, of the
    ``most_languages`` languages with the most documents."""
    coin = F.xxhash64("doc_id", F.lit(11))
    n = F.length("text")
    cut = lambda part: F.substring(F.col("text"), (n * part).cast("int") + 1, F.lit(width))
    known = df.where(~held_out_fold(F.col("doc_id")) & F.col("lang").isNotNull())
    counted = known.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most_languages).collect()
    counts = df.sparkSession.createDataFrame([(r.lang, r["count"]) for r in counted], "lang string, _n long")
    # Of a language with n rows only those whose coin is among the first few shares of 1/n can be chosen. They are found
    # where they lie, cut to their windows, and ranked in two levels, so no language's rows or texts meet in one task.
    near = (
        known.join(F.broadcast(counts), "lang").where((coin.cast("double") + 2.0**63) / 2.0**64 * F.col("_n") < 4 * per_language)
        .where(F.col("text").rlike(HAS_LETTER))
        .select("lang", coin.alias("coin"), "doc_id", cut(0.0).alias("a"), cut(0.35).alias("b"), cut(0.7).alias("c"))
        .withColumn("part", F.pmod(F.xxhash64("coin", "a"), F.lit(16)))
    )
    order = ["coin", "doc_id", "a", "b", "c"]
    for keys in (["lang", "part"], ["lang"]):
        near = near.withColumn("k", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where(F.col("k") <= per_language)
    rows = near.orderBy("lang", "k").collect()
    languages = sorted({r.lang for r in rows})
    texts, labels = [], []
    for r in rows:
        for piece in (r.a, r.b, r.c):
            if raw := piece.encode("utf-8", "surrogatepass")[:width]:
                texts.append(raw)
                labels.append(languages.index(r.lang))
    return codes_of(texts, width)[0], np.array(labels, np.int64), languages


def learn(df: DataFrame, **bounds) -> Recurrent | None:
    windows, labels, languages = training_windows(df, **bounds)
    return train(windows, labels, languages) if languages else None


def predictions(df: DataFrame, net: Recurrent | None) -> DataFrame:
    """``(doc_id, held_out, lang_pred, score)`` of every row of ``df(doc_id, text)``."""

    def run(batches):
        for batch in batches:
            texts = ["" if t is None else t for t in batch.column(1).to_pylist()]
            for a, b in slices(texts, 1_000_000):
                if net is None:
                    names, score = ["und"] * (b - a), np.zeros(b - a)
                else:
                    p = predict(net, texts[a:b])
                    names, score = [net.languages[i] for i in p.argmax(axis=1)], p.max(axis=1)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, b - a), batch.column(2).slice(a, b - a), pa.array(names, pa.string()), pa.array(score, pa.float64())],
                    names=["doc_id", "lettered", "lang_pred", "score"],
                )

    lettered = F.coalesce(F.col("text").rlike(HAS_LETTER), F.lit(False)).alias("lettered")
    out = df.select(F.col("doc_id").cast("long").alias("doc_id"), "text", lettered).mapInArrow(
        run, "doc_id long, lettered boolean, lang_pred string, score double"
    )
    return out.select(
        "doc_id", held_out_fold(F.col("doc_id")).alias("held_out"),
        F.when(F.col("lettered"), F.col("lang_pred")).otherwise("und").alias("lang_pred"),
        F.when(F.col("lettered"), F.least(F.lit(1.0), F.col("score"))).otherwise(0.0).alias("score"),
    )


def keep_recognised(df: DataFrame, over_chance: float = 1.2) -> DataFrame:
    """``df`` without documents that have no letter or whose best language has a mean probability under ``over_chance``
    times that of guessing among the learnt languages (0.3 where there are four)."""
    net = learn(df)
    least = over_chance / max(2, len(net.languages)) if net else 0.0

    @F.pandas_udf("double")
    def best(texts):
        import pandas as pd

        texts = texts.fillna("")
        if net is None or not len(texts):
            return pd.Series(np.zeros(len(texts)), index=texts.index)
        values = texts.tolist()
        return pd.Series(np.concatenate([predict(net, values[a:b]).max(axis=1) for a, b in slices(values, 1_000_000)]), index=texts.index)

    return df.where(F.coalesce(F.col("text").rlike(HAS_LETTER), F.lit(False))).where(best("text") >= least)


def op6_recurrent_language(spark, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return predictions(docs, learn(docs))
