"""Sharding, licences and exact deduplication: laws, edge cases, brute force."""

import hashlib
import re
import textwrap
import zlib
from collections import Counter
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

from softlanes.llm import exact_dedup, licenses, sharding
from softlanes.llm.shared import connected_components, located, materialise

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, texts):
    return materialise(spark.createDataFrame([(i, t, "en", "s", 0) for i, t in texts], DOCS), "docs")


ODD = [(0, None), (1, ""), (2, "a  b"), (3, "a b"), (3, "a b"), (4, "a\t\nb"), (5, "x" * 50_000), (6, "x" * 50_000), (None, "a b"), (7, "é ü"), (8, " ")]


def test_shards_are_near_equal_with_gapless_slots(spark):
    rows = [(i, ("hot " * 50 if i % 3 == 0 else f"text {i} " * (i % 40))) for i in range(3000)]
    out = sharding.sampled_splitter_shards(
        docs(spark, rows).select("doc_id", "text"), 8, F.xxhash64("text"), F.octet_length("text") + 8, F.col("doc_id")).toPandas()
    size = out.groupby("shard").apply(lambda g: sum(len(t) + 8 for t in g.text))
    assert len(out) == 3000 and len(size) == 8 and size.max() < 1.06 * size.mean() and size.min() > 0.94 * size.mean()
    for _, g in out.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))


def test_shards_keep_the_stated_balance_and_whole_groups(spark):
    rows = [(i, f"text {i // 2} " * 20) for i in range(4000)] + [(i, "hot " * 40) for i in range(4000, 6000)] + [(i, f"copy {i % 9} " * 9) for i in range(6000, 6180)]
    rows += [(7000, "same row " * 30)] * 900 + [(8000, "very long " * 3000)]
    df, at = located(docs(spark, rows).select("doc_id", "text"), "d")
    out = sharding.sampled_splitter_shards(df, 6, F.xxhash64("text"), F.octet_length("text") + 8, F.xxhash64("doc_id", at)).toPandas()
    out["size"] = out.text.str.len() + 8
    held, total = out.groupby("shard")["size"].sum(), out["size"].sum()
    piece = max(0.02 * total / 6, 2 * total / (6 * 192), out["size"].max())
    assert len(out) == len(rows) and (held - total / 6).abs().max() <= piece
    groups = out.groupby("text").agg(size=("size", "sum"), shards=("shard", "nunique"))
    assert (groups[groups["size"] <= 0.02 * total / 6].shards == 1).all()
    assert (groups.shards <= groups["size"] / (total / 6) + 2).all()


def test_registered_shards_are_near_equal(spark):
    out = sharding.op1_sampled_splitters(spark, "/root/testdata/sf0.01").toPandas()
    held = out.groupby("shard")["size"].sum()
    assert (held - held.mean()).abs().max() <= max(0.02 * held.mean(), out["size"].max())


@pytest.mark.parametrize("rows", [[], [(1, "one")], ODD])
def test_shards_of_odd_tables(spark, rows):
    out = sharding.sampled_splitter_shards(
        docs(spark, rows).withColumn("shard", F.lit("mine")), 3, F.xxhash64("text"), F.coalesce(F.octet_length("text"), F.lit(0)) + 8, F.col("doc_id")).toPandas()
    assert len(out) == len(rows)
    for _, g in out.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))


def test_license_canon(spark):
    text = licenses.TEXTS["MIT"]
    rows = [(0, "Copyright (c) 2020 A. Person\n" + text.upper().replace("LICENSE", "LICENCE")), (1, text + " more"), (2, "x\nReleased under the MIT licence\ny"), (3, None), (4, "")]
    got = {r.doc_id: r for r in licenses.scan_licenses(docs(spark, rows).withColumn("license", F.lit("other"))).collect()}
    assert got[0].license == "MIT" and got[1].license is None and got[2].notices == "MIT" and got[2].license is None
    assert got[3].canonical_sha256 == got[4].canonical_sha256 == hashlib.sha256(b"").hexdigest() and got[3].notices is None
    assert licenses.scan_licenses(docs(spark, [])).count() == 0


def test_whole_license_texts_titles_and_wrapped_lines(spark):
    head, mit = "Copyright (c) 2021 A. Person\n\n", licenses.TEXTS["MIT"].removeprefix("MIT License\n\n")
    folder = Path(licenses.__file__).parent / "license_texts"
    whole = [(f.stem.removesuffix("-Regents"), f.read_text()) for f in sorted(folder.glob("*.txt"))]
    bsd3 = licenses._BSD_HEAD + licenses._BSD_NAMES.format("the copyright holder") + licenses._BSD_TAIL.format("HOLDER")
    wrapped = mit.replace("AUTHORS OR COPYRIGHT", "AUTHORS OR\nCOPYRIGHT").replace("above copyright", "above\ncopyright")
    whole += [("MIT", "The MIT License (MIT)\n\n" + head + mit), ("MIT", head + mit), ("MIT", "MIT License\n\nCopyright Jane Doe\n" + wrapped)]
    whole += [("BSD-3-Clause", "BSD 3-Clause License\n\n" + head + bsd3), ("BSD-3-Clause", head + bsd3.replace("1. ", "* ").replace("2. ", "* ").replace("3. ", "* "))]
    whole += [("Apache-2.0", "\n".join(textwrap.wrap(dict(whole)["Apache-2.0"].split("APPENDIX")[0], 61))), (None, bsd3 + " more")]
    got = {r.doc_id: r.license for r in licenses.scan_licenses(docs(spark, [(i, t) for i, (_, t) in enumerate(whole)])).collect()}
    assert [got[i] for i in range(len(whole))] == [k for k, _ in whole]


def test_scan_equals_its_sql_on_spellings_and_copyright_lines(spark, tmp_path):
    lines = [
        "licence licence licence", "the sub-licence  sub licence,licences", "non commercial non-commercial whilst whilst", "LICENCE", "copyright holder copyright holders copyright holder",
        "Copyright (c) 2020 X", "copyright holders and contributors", "  * Copyright 1999", "Copyright Jane Doe", "COPYRIGHT HOLDERS BE LIABLE", "© Me", "(c) 2001 Y", "(c) the licensee keeps",
        "Copyright by all", "Copyright bystanders", "Copyright: [yyyy] name", "Copyright", "2020 follows", "Copyright And More", "Released under the MIT Licence.", "日本 ライセンス", "",
    ]
    rows = [(i, x) for i, x in enumerate([*lines, "\n".join(lines), "\n".join(reversed(lines)), None, "\r\n".join(lines), ("word " * 40_000) + "licence"])]
    docs(spark, rows).coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    got = licenses.op2_license_scan(spark, str(tmp_path)).collect()
    duck = duckdb.connect()
    duck.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert sorted(map(tuple, got), key=str) == sorted(duck.sql(licenses.oracle_op2()).fetchall(), key=str)
    word = licenses.canonical(F.lit("Licence licence\nlicence"))
    assert spark.range(1).select(word.alias("w")).first().w == "license license license"


def brute(rows):
    norm = [(i, re.sub(r"[\x20\x09-\x0D]+", " ", t or "")) for i, t in rows]
    groups = {}
    for i, t in norm:
        groups.setdefault(t, []).append(i)
    least = lambda ids: min((i for i in ids if i is not None), default=None)
    return Counter((i, least(groups[t]), len(groups[t]), hashlib.sha256(t.encode()).hexdigest()) for i, t in norm), len(groups)


@pytest.mark.parametrize("rows", [ODD, [], [(5, "q"), (4, "q"), (4, "q"), (9, "Q")]])
@pytest.mark.parametrize("weak", [False, True])
def test_exact_dedup(spark, rows, weak):
    digest = {"digest": lambda norm: F.length(norm) % 2} if weak else {}
    out = exact_dedup.dedup_decisions(docs(spark, rows), **digest).collect()
    want, groups = brute(rows)
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in out) == want
    assert sum(r.kept for r in out) == groups
    assert all(r.doc_id == r.keep_id for r in out if r.kept)


def kept_brute(rows, groups_of):
    """Row numbers that stay: of each group the smallest id, no id last; any one row where ids repeat."""
    best = {}
    for i, (doc_id, text) in enumerate(rows):
        best.setdefault(groups_of(text), []).append((doc_id is None, doc_id or 0))
    return Counter((k, min(v)) for k, v in best.items())


def shapes(spark, rows):
    """The same rows straight from files, in memory, aggregated, joined and exploded, with columns of all clashing names."""
    extra = {c: F.lit(c) for c in ("_file", "_row", "_metadata", "_gone", "_at", "_AT_", "digest", "norm", "fp", "at", "keep")}
    plain = spark.createDataFrame([(i, t, n) for n, (i, t) in enumerate(rows)], "doc_id long, text string, n long")
    yield materialise(plain, "d").withColumns(extra)
    yield materialise(plain.withColumns(extra), "d")
    yield plain.withColumns(extra)
    yield plain.groupBy("n").agg(F.first("doc_id").alias("doc_id"), F.first("text").alias("text")).withColumns(extra)
    yield materialise(plain, "d").join(plain.select("n", F.lit(1).alias("m")), "n").withColumns(extra)
    one = materialise(plain.groupBy().agg(F.collect_list(F.struct("doc_id", "text", "n")).alias("all")), "d")
    yield one.select(F.explode("all").alias("x")).select("x.*").withColumns(extra)


@pytest.mark.parametrize("shape", range(6))
def test_drop_keeps_one_row_of_each_text_and_all_columns(spark, shape):
    df = list(shapes(spark, ODD))[shape]
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    out = exact_dedup.drop_duplicates(df)
    assert out.columns == df.columns
    assert Counter((norm(r.text), (r.doc_id is None, r.doc_id or 0)) for r in out.collect()) == kept_brute(ODD, norm)


def test_state_goes_on_over_runs(spark, tmp_path):
    folder = str(tmp_path / "state")
    first = exact_dedup.drop_duplicates(docs(spark, [(5, "a  b"), (6, "a b"), (7, "c")]), state_folder=folder).collect()
    assert sorted(r.doc_id for r in first) == [5, 7]
    got = {r.doc_id: r for r in exact_dedup.dedup_decisions(docs(spark, [(2, "c"), (9, "a b"), (10, "new")]), state_folder=folder).collect()}
    assert [(got[i].keep_id, got[i].group_size, got[i].kept) for i in (2, 9, 10)] == [(2, 2, True), (5, 3, False), (10, 1, True)]


def test_bytes_are_compared_across_runs(spark, tmp_path):
    weak = {"digest": lambda norm: F.length(norm), "state_folder": str(tmp_path / "state")}
    exact_dedup.dedup_decisions(docs(spark, [(1, "ab"), (2, "cd")]), **weak).collect()
    got = {r.doc_id: r for r in exact_dedup.dedup_decisions(docs(spark, [(3, "cd"), (4, "ef"), (5, "ab")]), **weak).collect()}
    assert [(got[i].keep_id, got[i].group_size, got[i].kept) for i in (3, 4, 5)] == [(2, 2, False), (4, 1, True), (1, 2, False)]


def test_many_hits_are_joined_by_shuffle(spark, monkeypatch):
    monkeypatch.setattr(exact_dedup, "BROADCAST_HITS", 0)
    out = exact_dedup.dedup_decisions(docs(spark, ODD), digest=lambda norm: F.length(norm) % 2).collect()
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in out) == brute(ODD)[0]


def test_components(spark):
    chain = [(i, i + 1) for i in range(60)] + [(100, 200), (200, 150), (150, 150), (7, 3)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and got[200] == got[150] == got[100] == 100
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_registered_sizes_and_checksums(spark, small):
    out = sharding.op1_sampled_splitters(spark, small).toPandas().set_index("doc_id")
    for r in spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").collect():
        assert out.loc[r.doc_id, "size"] == len(r.text.encode()) + 8 and out.loc[r.doc_id, "text_crc32"] == zlib.crc32(r.text.encode())
