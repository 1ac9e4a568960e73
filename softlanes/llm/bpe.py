"""Byte-level BPE encoding and decoding in batched numpy merge rounds.

Symbols of many words lie in one flat array. A round looks up every adjacent pair by binary search in
the sorted pair keys, takes the lowest rank of each word, merges it wherever the word has it, and drops
words that have none left. A word of over ``LONG`` bytes would hold up the rounds of all others, each of which
reads it whole: its pairs wait in a heap by rank and place instead, and its symbols are a linked list. Words met
before come from a cache of bounded size; the result does not depend on it. Whole texts are encoded, in slices of
a few megabytes of documents.

Edge cases: null counts as empty; empty texts have no ids; special tokens in a text become their ids, as
the file's own settings have it; repeated rows give repeated results; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
from heapq import heapify, heappop, heappush
from itertools import islice

import numpy as np
import pyarrow as pa
import public_tokenizers
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import load

CACHED_WORDS = 300_000
LONG = 400
SLICE_CHARS = 2_000_000
_NONE = np.iinfo(np.int64).max


def printable_bytes() -> dict[str, int]:
    """The byte that each character of a byte-level vocabulary stands for."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class MergeTable:
    """Vocabulary and merges of a byte-level BPE file, with encoding and decoding of whole texts."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        of_char = printable_bytes()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.size = max([*vocab.values(), *self.special.values()]) + 1
        self.bytes_of = [b""] * self.size
        for token, i in vocab.items():
            self.bytes_of[i] = bytes(of_char[c] for c in token)
        for token, i in self.special.items():
            self.bytes_of[i] = token.encode()
        self.of_byte = np.zeros(256, np.int64)
        for c, b in of_char.items():
            self.of_byte[b] = vocab[c]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        keys = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.ranks, self.made = keys[order], order.astype(np.int64), made[order]
        self.words = regex.compile(public_tokenizers.PATTERN)
        self.split = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.cache: dict[str, bytes] = {}
        self.by_key: dict[int, tuple[int, int]] = {}

    def merge_long(self, word: bytes) -> bytes:
        """Ids of one word of any length, in about n log n steps."""
        if not self.by_key:
            self.by_key = dict(zip(self.keys.tolist(), zip(self.ranks.tolist(), self.made.tolist())))
        size, by_key, n = self.size, self.by_key, len(word)
        symbols = self.of_byte[np.frombuffer(word, np.uint8)].tolist()
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))

        def entry(i: int) -> int:
            """Rank, then place, as one number; -1 where the symbol and the next make no pair."""
            j = after[i]
            known = by_key.get(symbols[i] * size + symbols[j]) if j < n else None
            return -1 if known is None else known[0] * n + i

        waiting = [e for e in map(entry, range(n)) if e >= 0]
        heapify(waiting)
        while waiting:
            at = heappop(waiting)
            i = at % n
            if symbols[i] < 0 or entry(i) != at:
                continue  # merged away, or another pair by now
            j = after[i]
            symbols[i] = by_key[symbols[i] * size + symbols[j]][1]
            symbols[j] = -1
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            for k in (before[i], i):
                if k >= 0 and (e := entry(k)) >= 0:
                    heappush(waiting, e)
        return np.array([x for x in symbols if x >= 0], "<u4").tobytes()

    def merge(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word (not empty), as little-endian unsigned 32-bit integers."""
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        symbols = self.of_byte[np.frombuffer(b"".join(words), np.uint8)]
        word = np.repeat(np.arange(len(words)), lengths)
        ended_w, ended_s = [], []
        while len(symbols):
            starts = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
            rank = np.full(len(symbols), _NONE)
            made = np.zeros(len(symbols), np.int64)
            inner = np.flatnonzero(word[1:] == word[:-1])
            key = symbols[inner] * self.size + symbols[inner + 1]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            known = self.keys[at] == key
            rank[inner[known]] = self.ranks[at[known]]
            made[inner[known]] = self.made[at[known]]
            lowest = np.minimum.reduceat(rank, starts)
            counts = np.diff(np.r_[starts, len(symbols)])
            lowest = np.repeat(lowest, counts)
            over = lowest == _NONE
            if over.any():
                ended_w.append(word[over])
                ended_s.append(symbols[over])
            here = (rank == lowest) & ~over
            # a pair of equal symbols can overlap itself: every second place of a run, from the left
            place = np.flatnonzero(here)
            if len(place):
                first = np.r_[True, np.diff(place) != 1]
                since = np.arange(len(place)) - np.maximum.accumulate(np.where(first, np.arange(len(place)), 0))
                place = place[since % 2 == 0]
            symbols[place] = made[place]
            keep = ~over
            keep[place + 1] = False
            symbols, word = symbols[keep], word[keep]
        w, s = np.concatenate(ended_w), np.concatenate(ended_s).astype("<u4")
        order = np.argsort(w, kind="stable")
        flat = s[order].tobytes()
        ends = 4 * np.cumsum(np.bincount(w, minlength=len(words)))
        return [flat[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist())]

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Ids of whole texts, as little-endian unsigned 32-bit integers."""
        cache = self.cache
        if len(cache) > CACHED_WORDS:  # the older half goes
            for w in list(islice(cache, len(cache) // 2 + 1)):
                del cache[w]
        found = []
        for text in texts:
            if self.split is not None and any(s in text for s in self.special):
                parts = self.split.split(text)
                found.append([x for i, part in enumerate(parts) for x in ([(part,)] if i % 2 else self.words.findall(part))])
            else:
                found.append(self.words.findall(text))
        new = {w: w.encode("utf-8", "surrogatepass") for w in {w for ws in found for w in ws if w.__class__ is str} - cache.keys()}
        cache.update((w, self.merge_long(b)) for w, b in new.items() if len(b) > LONG)
        for block in self._blocks([w for w, b in new.items() if len(b) <= LONG]):
            cache.update(zip(block, self.merge([new[w] for w in block])))
        special = {(s,): int(i).to_bytes(4, "little") for s, i in self.special.items()}
        return [b"".join([cache[w] if w.__class__ is str else special[w] for w in ws]) for ws in found]

    @staticmethod
    def _blocks(words: list[str], at_once: int = 100_000):
        for i in range(0, len(words), at_once):
            yield words[i : i + at_once]

    def decode(self, ids: bytes) -> str:
        of = self.bytes_of
        return b"".join([of[i] for i in np.frombuffer(ids, "<u4").tolist()]).decode("utf-8", "replace")


_TABLES: dict[str, MergeTable] = {}


def table(path: str) -> MergeTable:
    if path not in _TABLES:
        _TABLES[path] = MergeTable(path)
    return _TABLES[path]


def slices(values: list[str], limit: int = SLICE_CHARS):
    """Consecutive runs of texts of about ``limit`` characters, so that memory does not follow batch size."""
    start, held = 0, 0
    for i, v in enumerate(values):
        held += len(v)
        if held >= limit:
            yield start, i + 1
            start, held = i + 1, 0
    if start < len(values):
        yield start, len(values)


def encode(df: DataFrame, path: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(doc_id, ids array<int>)`` of every row."""

    def run(batches):
        own = table(path)
        for batch in batches:
            texts = ["" if t is None else t for t in batch.column(1).to_pylist()]
            for a, b in slices(texts):
                ids = own.encode_batch(texts[a:b])
                lengths = np.array([0, *(len(x) // 4 for x in ids)])
                flat = pa.array(np.frombuffer(b"".join(ids), "<u4").astype(np.int32))
                arrays = pa.ListArray.from_arrays(pa.array(np.cumsum(lengths), pa.int32()), flat)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), arrays], names=["doc_id", "ids"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode(df: DataFrame, path: str, ids: str = "ids", doc_id: str = "doc_id") -> DataFrame:
    """``(doc_id, text)`` from arrays of ids; a null array gives an empty text."""

    def run(batches):
        own = table(path)
        for batch in batches:
            texts = [own.decode(np.array(x or [], "<u4").tobytes()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(ids).alias("ids")).mapInArrow(run, "doc_id long, text string")


def round_trip(df: DataFrame, path: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """Encode every text and decode its ids again: ``(doc_id, n_tokens, ids_sha256, decoded_sha256)``."""

    def run(batches):
        own = table(path)
        for batch in batches:
            texts = ["" if t is None else t for t in batch.column(1).to_pylist()]
            for a, b in slices(texts):
                ids = own.encode_batch(texts[a:b])
                yield pa.RecordBatch.from_arrays([
                    batch.column(0).slice(a, b - a),
                    pa.array([len(x) // 4 for x in ids], pa.int64()),
                    pa.array([hashlib.sha256(x).hexdigest() for x in ids]),
                    pa.array([hashlib.sha256(own.decode(x).encode("utf-8", "surrogatepass")).hexdigest() for x in ids]),
                ], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(
        run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    )


def op10_bpe_merge_rounds(spark, sf_dir: str) -> DataFrame:
    return round_trip(load(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
