"""Tokenisation against the library, packing against its laws."""

import collections
import hashlib
import random
import time
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from softlanes.llm import bpe, packing
from softlanes.llm.shared import materialise

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
DOCS = "doc_id long, text string"


def odd_texts():
    rng = random.Random(3)
    alphabet = [chr(c) for c in [*range(0, 0x180), 0x300, 0x3A3, 0x3C2, 0x130, 0x2003, 0x3000, 0x1F600, 0xAC00, 0xFB01, 0x2126]]
    made = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 60))) for _ in range(300)]
    return made + ["", " ", "aaaaaaaaaaaa aaaa", "I'LL don't it's", "a<|endoftext|>b <|endoftext|>", "<|startoftext|>", "x" * 20_000, "\n\n \t  end  ", "ΟΔΟΣ ΣΣ"]


def test_encoding_equals_the_library():
    texts = odd_texts()
    mine, ref = bpe.MergeTable(BYTE), Tokenizer.from_file(BYTE)
    for text, ids, want in zip(texts, mine.encode_batch(texts), ref.encode_batch(texts, add_special_tokens=False)):
        assert np.frombuffer(ids, "<u4").tolist() == want.ids, repr(text)
        assert mine.decode(ids) == ref.decode(want.ids, skip_special_tokens=False)


def test_long_words_equal_the_library_in_little_time():
    rng, ref = random.Random(2), Tokenizer.from_file(BYTE)
    texts = ["".join(rng.choice(letters) for _ in range(n)) for letters, n in [("thean", 200_000), ("a", 50_001), ("日本語のé", 20_000), ("abcdefghij", bpe.LONG), ("ab", bpe.LONG + 1)]]
    mine = bpe.MergeTable(BYTE)
    began = time.process_time()
    got = mine.encode_batch(texts)
    assert time.process_time() - began < 20
    for text, ids, want in zip(texts, got, ref.encode_batch(texts, add_special_tokens=False)):
        assert np.frombuffer(ids, "<u4").tolist() == want.ids
    short = ["abcabcab", "aaaaaaa", "theethe"]
    assert [mine.merge_long(w.encode()) for w in short] == mine.merge([w.encode() for w in short])


def test_chunks_equal_the_library():
    texts = odd_texts()
    ref = Tokenizer.from_file(WORD)
    for text, ids, want in zip(texts, packing.encode_texts(WORD, texts), ref.encode_batch(texts, add_special_tokens=False)):
        assert np.frombuffer(ids, "<u4").tolist() == want.ids, repr(text)


def test_runs_are_cut_where_the_library_cuts(monkeypatch):
    rng, ref = random.Random(5), Tokenizer.from_file(WORD)
    alphabet = "ab'sStTrRe vVmMlLdD 09.,\n²½é'İΣ日 <|>\u0301\x1c\x85 "
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 80))) for _ in range(3000)]
    want = [np.array(e.ids, "<u4").tobytes() for e in ref.encode_batch(texts, add_special_tokens=False)]
    assert packing.encode_texts(WORD, texts) == want
    monkeypatch.setattr(packing, "CACHED_RUNS", 7)
    small = packing.RunIds(WORD)
    assert [x for i in range(0, 3000, 500) for x in small.encode(texts[i : i + 500])] == want
    assert small.encode([]) == []


def test_a_file_that_splits_otherwise_is_refused():
    with pytest.raises(ValueError, match="splits or normalises"):
        packing.encode_texts(BYTE, ["a"])


def test_cache_size_changes_nothing(monkeypatch):
    texts = odd_texts()
    a = bpe.MergeTable(BYTE).encode_batch(texts)
    monkeypatch.setattr(bpe, "CACHED_WORDS", 0)
    own = bpe.MergeTable(BYTE)
    assert [own.encode_batch([t])[0] for t in texts] == a


def test_round_trip_rows(spark):
    rows = [(0, None), (1, ""), (2, "hello"), (2, "hello"), (None, "é")]
    df = spark.createDataFrame(rows, DOCS).withColumn("ids", F.lit("clash"))
    got = bpe.round_trip(df, BYTE).collect()
    assert len(got) == 5
    for r, (_, t) in zip(sorted(got, key=lambda r: (r.doc_id is None, r.doc_id)), sorted(rows, key=lambda r: (r[0] is None, r[0]))):
        assert r.decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    ids = bpe.encode(df, BYTE)
    back = {r.doc_id: r.text for r in bpe.decode(ids, BYTE).collect()}
    assert back[2] == "hello" and back[0] == ""
    assert bpe.round_trip(df.where("false"), BYTE).count() == 0


def bins_of(plan):
    bins = collections.defaultdict(list)
    for size, first, end, each, base, offset in plan:
        for rank in range(first, end):
            bins[base + (rank - first) // each].append((offset + (rank - first) % each * size, size))
    return bins


def least_bins(sizes, cap):
    """Exact minimum by search, for small instances."""
    sizes, best = sorted(sizes, reverse=True), [len(sizes)]

    def go(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(sizes):
            best[0] = len(bins)
            return
        for b in range(len(bins)):
            if bins[b] + sizes[i] <= cap and bins[b] not in bins[:b]:
                go(i + 1, [*bins[:b], bins[b] + sizes[i], *bins[b + 1 :]])
        go(i + 1, [*bins, sizes[i]])

    go(0, [])
    return best[0]


@pytest.mark.parametrize("seed", range(60))
def test_plans_fill_without_gaps_and_reduction_keeps_the_optimum(seed):
    rng = random.Random(seed)
    cap = rng.choice([10, 20, 100])
    sizes = [rng.randint(1, cap) for _ in range(rng.randint(0, 9))]
    counts = dict(collections.Counter(sizes))
    bins = bins_of(packing.packing_plan(counts, cap))
    assert sum(map(len, bins.values())) == len(sizes)
    for inside in bins.values():
        at = 0
        for offset, size in sorted(inside):
            assert offset == at
            at += size
        assert at <= cap
    fixed, rest = packing.dominance_reduction(counts, cap)
    left = [s for s, c in rest.items() for _ in range(c)]
    assert sum(n for n, _ in fixed) + least_bins(left, cap) == least_bins(sizes, cap)


def test_documents_are_packed_whole(spark, monkeypatch):
    rng = random.Random(1)
    rows = [(i, " ".join(rng.choice(["one", "two", "three"]) for _ in range(rng.choice([0, 3, 90, 700, 2047, 2048, 5000])))) for i in range(120)] + [(200, None), (3, ""), (3, "")]
    out = packing.pack_documents(materialise(spark.createDataFrame(rows, DOCS).withColumn("length", F.lit("clash")), "d"), WORD).toPandas()
    ref = Tokenizer.from_file(WORD)
    for i, t in rows[:120:7]:
        ids = np.array([*ref.encode(t, add_special_tokens=False).ids, 0], "<u4")
        own = out[(out.doc_id == i)].sort_values("piece")
        if i != 3:
            assert own.length.tolist() == [len(ids[a : a + 2048]) for a in range(0, len(ids), 2048)]
            assert own.ids_crc32.tolist() == [zlib.crc32(ids[a : a + 2048].tobytes()) for a in range(0, len(ids), 2048)]
            assert own.start.tolist() == list(range(0, len(ids), 2048))
    for _, g in out.groupby("sequence_id"):
        g = g.sort_values("offset")
        assert g.offset.tolist() == [0, *g.length.cumsum().tolist()[:-1]] and g.length.sum() <= 2048
    rooms = []  # best-fit decreasing one piece at a time
    for size in sorted(out.length, reverse=True):
        fits = [r for r in rooms if r >= size]
        if fits:
            rooms.remove(min(fits))
        rooms.append((min(fits) if fits else 2048) - size)
    assert out.sequence_id.nunique() <= len(rooms)
    monkeypatch.setattr(packing, "isqrt", lambda n: n // 3)
    many = packing.pack_documents(spark.createDataFrame(rows, DOCS), WORD).toPandas()
    assert sorted(many.length) == sorted(out.length) and many.sequence_id.nunique() == out.sequence_id.nunique()
    assert not many.duplicated(["sequence_id", "offset"]).any() and (many.groupby("sequence_id").length.sum() <= 2048).all()
    assert packing.pack_documents(spark.createDataFrame([], DOCS), WORD).count() == 0
