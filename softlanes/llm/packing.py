"""Best-fit packing with Martello-Toth dominance reduction.

Whole texts become token pieces of at most ``capacity`` tokens. The packing instance is the histogram of
piece lengths, at most ``capacity`` rows whatever the corpus: the reduction permanently fixes sets that
dominate every other set with their largest piece (a piece that nothing fits beside, a piece with its
perfect complement, the best pair where only one more piece fits, the best triple where only two fit and
no other pair is larger in both parts), each as often as the counts allow. Best-fit decreasing packs what
remains, also on counts. Pieces of one length are interchangeable, so rows get their places by their rank
within the length, which is found with windows salted by the count of the length: no length is gathered into one task.

Edge cases: null counts as an empty text, which is one separator token; longer texts are cut into
``capacity`` pieces, the last may be shorter; repeated rows are packed as often as they occur; an empty
table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import json
import zlib
from array import array
from bisect import bisect_left, insort
from contextlib import contextmanager
from math import isqrt

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from softlanes.llm.bpe import printable_bytes, slices
from softlanes.llm.shared import load, materialise

CACHED_RUNS = 300_000  # of each of two generations
LONGEST_CACHED = 48
_LOADED: dict[str, RunIds] = {}
# How this vocabulary's file normalises and splits text.
_PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_NORMALISED = ["NFC", "Replace", "Lowercase"]
_FIND = regex.compile(_PIECES)
_CUT = regex.compile("[^\\x00-\u024f]|\u0130")
_PRINTABLE = {b: c for c, b in printable_bytes().items() if chr(b) != c}
# classes of characters; what lies past _LATIN, and a letter whose lower case is two characters, is never cut from its neighbours
_LETTER, _DIGIT, _MARK, _WHITE, _OTHER = range(5)
_LATIN, _TWO_LOWER = 0x250, 0x130
_KINDS = [(r"\p{L}", _LETTER), (r"\p{N}", _DIGIT), (r"\s", _WHITE), ("", _MARK)]
_CLASSES = np.array([next(k for pattern, k in _KINDS if regex.match(pattern, chr(c))) if c != _TWO_LOWER else _OTHER for c in range(_LATIN)], np.uint8)
_BYTES = np.concatenate([_CLASSES[:128], np.full(128, _OTHER, np.uint8)])
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def runs(raw: np.ndarray) -> np.ndarray:
    """Starts of the runs that UTF-8 bytes are cut into: of letters, of marks, of white space, and single digits.

    No piece of the vocabulary's pattern reaches over a cut. A lone apostrophe stays with the letters after it
    (the pattern has contractions), and whatever is not Latin, or may hold a special token, is cut at white
    space only.
    """
    kind = _BYTES[raw]
    lead = np.flatnonzero((raw >= 0xC2) & (raw <= 0xC9))
    code = (raw[lead].astype(np.int64) & 31) << 6 | raw[lead + 1] & 63
    lead, code = lead[code < _LATIN], code[code < _LATIN]
    kind[lead] = kind[lead + 1] = _CLASSES[code]
    cut = np.r_[True, kind[1:] != kind[:-1]] | ((kind == _DIGIT) & (raw & 0xC0 != 0x80))
    lone = np.flatnonzero((raw[:-1] == 39) & cut[:-1] & cut[1:] & (kind[1:] == _LETTER))
    cut[lone + 1] = False
    whole = np.r_[np.flatnonzero(kind == _OTHER), np.flatnonzero((raw[:-1] == 60) & (raw[1:] == 124))]
    if len(whole):
        white = kind == _WHITE
        edge = np.r_[True, white[1:] != white[:-1]]
        chunk = np.cumsum(edge) - 1
        kept = np.zeros(chunk[-1] + 1, bool)
        kept[chunk[whole]] = True
        cut &= edge | ~kept[chunk]
    return np.flatnonzero(cut)


class RunIds:
    """Ids (little-endian unsigned 32-bit integers) of whole texts, with each distinct run of a batch looked up once.

    The runs of a batch are dictionary-encoded; ids of distinct runs come from two generations of a cache, of
    which only the older is ever forgotten, or are split and merged by the library's model; other than Latin
    runs go through the library's whole tokenizer. All runs' ids are then gathered from flat arrays.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        steps = [s.get("type") for s in (spec["normalizer"] or {}).get("normalizers", [])]
        splits = [s.get("pattern", {}).get("Regex") for s in (spec["pre_tokenizer"] or {}).get("pretokenizers", [])]
        if steps != _NORMALISED or splits != [_PIECES, None] or any("<|" not in t["content"] for t in spec["added_tokens"]):
            raise ValueError("this packing cuts text as word_bpe_49k.json does; the file splits or normalises otherwise")
        self.whole = Tokenizer.from_file(path)
        self.whole.no_truncation()
        self.whole.no_padding()
        self.model = self.whole.model
        self.young: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}

    def of_run(self, run: bytes) -> bytes:
        ids = self.old.get(run)
        if ids is None:
            text = run.decode("utf-8", "surrogatepass")
            if run.isalpha():  # Latin letters without marks: one piece, which the vocabulary spells as it is
                pieces = [text.lower()]
            elif "<|" not in text and _CUT.search(text) is None:
                pieces = [p.encode().decode("latin-1").translate(_PRINTABLE) for p in _FIND.findall(text.lower())]
            else:
                pieces = None
            if pieces is None:
                ids = array("I", self.whole.encode(text, add_special_tokens=False).ids).tobytes()
            else:
                ids = array("I", [t.id for p in pieces for t in self.model.tokenize(p)]).tobytes()
        if len(run) <= LONGEST_CACHED:
            if len(self.young) >= CACHED_RUNS:
                self.old, self.young = self.young, {}
            self.young[run] = ids
        return ids

    def encode(self, texts: list[str]) -> list[bytes]:
        parts = [t.encode("utf-8", "surrogatepass") for t in texts]
        joined = b"\n".join([*parts, b""])  # texts are cut from each other by white space
        if not joined:
            return []
        raw = np.frombuffer(joined if b"<|" in joined else joined.translate(_LOWER), np.uint8)
        start = runs(raw)
        ends = np.append(start, len(raw)).astype(np.int32)
        coded = pa.Array.from_buffers(pa.binary(), len(start), [None, pa.py_buffer(ends), pa.py_buffer(raw)]).dictionary_encode()
        young, of_run = self.young, self.of_run
        known = [young[r] if r in young else of_run(r) for r in coded.dictionary.to_pylist()]
        place = coded.indices.to_numpy()
        size = np.fromiter(map(len, known), np.int32, len(known)) // 4
        first, flat = np.cumsum(size, dtype=np.int32) - size, np.frombuffer(b"".join(known), "<u4")
        own = size[place]
        until = np.cumsum(own, dtype=np.int32)
        ids = flat[np.repeat(first[place] - until + own, own) + np.arange(until[-1], dtype=np.int32)]
        at = np.cumsum([0, *(len(p) + 1 for p in parts)])
        bounds = np.r_[0, until][np.searchsorted(start, at)].tolist()
        return [ids[a:b].tobytes() for a, b in zip(bounds, bounds[1:])]


def encode_texts(path: str, texts: list[str]) -> list[bytes]:
    """Ids of whole texts as little-endian unsigned 32-bit integers, as the tokenizers library gives them.

    ``path`` must be a file that splits as ``word_bpe_49k.json`` does; any other raises ValueError.
    """
    if path not in _LOADED:
        _LOADED[path] = RunIds(path)
    return _LOADED[path].encode(texts)


def token_pieces(df: DataFrame, path: str, capacity: int = 2048, end_id: int = 0, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(doc_id, piece, start, length, ids_crc32)`` of every text's ids followed by ``end_id``."""
    step, tail = 4 * capacity, int(end_id).to_bytes(4, "little")

    def run(batches):
        for batch in batches:
            texts = ["" if t is None else t for t in batch.column(1).to_pylist()]
            for a, b in slices(texts):
                ids = [x + tail for x in encode_texts(path, texts[a:b])]
                row = [i for i, x in enumerate(ids) for _ in range(0, len(x), step)]
                cut = [(p, s, x[s : s + step]) for x in ids for p, s in enumerate(range(0, len(x), step))]
                yield pa.RecordBatch.from_arrays([
                    batch.column(0).slice(a, b - a).take(pa.array(row, pa.int64())),
                    pa.array([p for p, _, _ in cut], pa.int32()),
                    pa.array([s // 4 for _, s, _ in cut], pa.int64()),
                    pa.array([len(x) // 4 for _, _, x in cut], pa.int64()),
                    pa.array([zlib.crc32(x) for _, _, x in cut], pa.int64()),
                ], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(
        run, "doc_id long, piece int, start long, length long, ids_crc32 long"
    )


Pattern = tuple[int, list[tuple[int, int]]]  # how many sequences; runs of (length, repeats) in each


class _Sizes:
    """Counts by size, with the next smaller and larger size that is left."""

    def __init__(self, counts: dict[int, int]):
        self.n = {s: c for s, c in counts.items() if c > 0}
        self.sorted = sorted(self.n)

    def take(self, size: int, k: int) -> None:
        self.n[size] -= k
        if not self.n[size]:
            del self.n[size]
            self.sorted.pop(bisect_left(self.sorted, size))

    def largest(self, most: int, without: dict[int, int]) -> int | None:
        """The largest size <= most of which more are left than ``without`` sets aside."""
        i = bisect_left(self.sorted, most + 1) - 1
        while i >= 0:
            if self.n[self.sorted[i]] > without.get(self.sorted[i], 0):
                return self.sorted[i]
            i -= 1
        return None

    def smallest(self, k: int, without: int) -> list[int]:
        out: list[int] = []
        for s in self.sorted:
            out += [s] * min(k - len(out), self.n[s] - (s == without))
            if len(out) == k:
                break
        return out


def dominance_reduction(counts: dict[int, int], capacity: int) -> tuple[list[Pattern], dict[int, int]]:
    """Sets fixed for good, and the counts that remain."""
    left, fixed = _Sizes(counts), []

    def fix(*sizes: int) -> None:
        need = {s: sizes.count(s) for s in sizes}
        times = min(left.n[s] // k for s, k in need.items())
        fixed.append((times, [(s, k) for s, k in need.items()]))
        for s, k in need.items():
            left.take(s, times * k)

    for a in sorted(left.n, reverse=True):
        while left.n.get(a):
            room = capacity - a
            k = left.largest(room, {a: 1})
            if k is None:
                fix(a)
                continue
            low = left.smallest(3, a)
            if k == room or sum(low[:2]) > room or len(low) == 1:
                fix(a, k)
                continue
            if len(low) == 2 or sum(low) > room:  # at most two more pieces fit
                second = left.largest(room - k, {a: 1 + (a == k), k: 1 + (a == k)})
                # the largest smaller part of any pair that fits
                part = left.largest(room // 2, {a: 1})
                while part is not None:
                    partner = next((s for s in left.sorted[bisect_left(left.sorted, part):] if left.n[s] > (s == a) + (s == part)), None)
                    if partner is not None and part + partner <= room:
                        break
                    part = left.largest(part - 1, {a: 1})
                if second is not None and part is not None and part <= second:
                    fix(a, k, second)
                    continue
            break
    return fixed, dict(left.n)


def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[Pattern]:
    """Best-fit decreasing on counts: sequences of one pattern are filled together."""
    by_room: dict[int, list[list]] = {}  # free tokens -> [sequences, runs]
    rooms: list[int] = []

    def put(room: int, n: int, runs: list) -> None:
        if room not in by_room:
            by_room[room] = []
            insort(rooms, room)
        by_room[room].append([n, runs])

    for size in sorted(counts, reverse=True):
        n = counts[size]
        while n:
            i = bisect_left(rooms, size)
            if i == len(rooms):
                room, bins, runs = capacity, n, []
            else:
                room = rooms[i]
                bins, runs = by_room[room].pop()
                if not by_room[room]:
                    del by_room[room]
                    rooms.pop(i)
            each = room // size
            full = min(bins, n // each)
            if full:
                put(room - each * size, full, [*runs, (size, each)])
                n -= full * each
                bins -= full
            if n and bins:  # fewer pieces than one more sequence takes
                put(room - n * size, 1, [*runs, (size, n)])
                bins -= 1
                n = 0
            if bins and runs:
                put(room, bins, runs)
    return [(n, runs) for room in rooms for n, runs in by_room[room]]


def packing_plan(counts: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int, int]]:
    """Rows (length, first rank, end rank, repeats, first sequence, offset): where pieces of a length go by rank."""
    fixed, rest = dominance_reduction(counts, capacity)
    used: dict[int, int] = {}
    rows, base = [], 0
    for n, runs in [*fixed, *best_fit_decreasing(rest, capacity)]:
        offset = 0
        for size, each in runs:
            first = used.get(size, 0)
            used[size] = first + n * each
            rows.append((size, first, used[size], each, base, offset))
            offset += size * each
        base += n
    assert used == {s: c for s, c in counts.items() if c}, "every piece has a place"
    return rows


def pack(pieces: DataFrame, capacity: int = 2048) -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to ``pieces``, a table that is read from files (``token_pieces`` written)."""
    spark = pieces.sparkSession
    counts = {int(r["length"]): int(r["count"]) for r in pieces.groupBy("length").count().collect()}  # <= capacity rows
    plan = spark.createDataFrame(
        packing_plan(counts, capacity) or [(0, 0, 0, 1, 0, 0)],
        "p_length long, first long, end long, repeats long, base long, p_offset long",
    )
    salts = spark.createDataFrame([(n, 1 + isqrt(c)) for n, c in counts.items()] or [(0, 1)], "length long, _salts long")
    salted = pieces.withColumn("_at", F.xxhash64("_metadata.row_index", "doc_id")).join(F.broadcast(salts), "length").withColumn(
        "_salt", F.pmod("_at", "_salts")
    ).drop("_at", "_salts")
    held = salted.groupBy("length", "_salt").count()  # about the root of the pieces of a length
    start = held.withColumn("_start", F.sum("count").over(Window.partitionBy("length").orderBy("_salt")) - F.col("count"))
    inside = Window.partitionBy("length", "_salt").orderBy("doc_id", "piece")
    ranked = salted.withColumn("_in", F.row_number().over(inside) - 1).join(start.drop("count"), ["length", "_salt"])
    ranked = ranked.withColumn("_rank", F.col("_start") + F.col("_in"))
    place = F.col("_rank") - F.col("first")
    return ranked.join(
        F.broadcast(plan), (F.col("length") == F.col("p_length")) & (F.col("_rank") >= F.col("first")) & (F.col("_rank") < F.col("end"))
    ).select(
        *pieces.columns,
        (F.col("base") + F.floor(place / F.col("repeats"))).cast("long").alias("sequence_id"),
        (F.col("p_offset") + place % F.col("repeats") * F.col("length")).cast("long").alias("offset"),
    )


@contextmanager
def arrow_batches(spark, rows: int):
    """Batches of at most ``rows`` rows between Spark and Python while the body's actions run: whole texts are long,
    and both sides hold a batch in memory."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def pack_documents(df: DataFrame, path: str, capacity: int = 2048) -> DataFrame:
    with arrow_batches(df.sparkSession, 500):
        pieces = materialise(token_pieces(df, path, capacity), "pieces")
    return pack(pieces, capacity).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op8_dominance_packing(spark, sf_dir: str) -> DataFrame:
    return pack_documents(load(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
