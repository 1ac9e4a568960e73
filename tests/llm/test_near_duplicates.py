"""SimHash and vector near-deduplication against brute force."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from softlanes.llm import simhash, vectors
from softlanes.llm.shared import materialise

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def labels_of(n, links):
    root = list(range(n))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return [find(a) for a in range(n)]


def test_masks_cover_every_pattern_up_to_the_radius():
    rng = np.random.default_rng(0)
    for radius in (1, 2, 3):
        masks = simhash.covering_masks(list(range(64)), radius)
        assert len(masks) == 2 ** (radius + 1) - 1
        for _ in range(3000):
            pattern = sum(1 << int(p) for p in rng.choice(64, rng.integers(0, radius + 1), replace=False))
            assert any(pattern & m == 0 for m in masks)


def test_fingerprint_by_hand():
    import xxhash

    text = "The  quick\tBrown fox The quick brown FOX"
    words = text.lower().split()
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + 3]), 42) for i in range(len(words) - 2)]
    want = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))
    assert simhash.fingerprint(text) == want
    assert simhash.fingerprint(None) == simhash.fingerprint(" \n") == 0
    assert simhash.fingerprint("ÀB cd") == xxhash.xxh64_intdigest("Àb cd", 42)


def random_prints(n, seed, wide=False):
    rng = np.random.default_rng(seed)
    base = rng.integers(0, 2**63, 12)
    out = []
    for _ in range(n):
        x = int(base[rng.integers(0, 1 if wide else 12)])
        for p in rng.choice(64, rng.integers(0, 5), replace=False):
            x ^= 1 << int(p)
        out.append(x & (2**64 - 1))
    return out


@pytest.mark.parametrize("wide", [False, True])
def test_components_equal_brute_force(spark, monkeypatch, wide):
    if wide:
        monkeypatch.setattr(simhash, "WIDE", 20)
    prints = random_prints(400, 1, wide)
    rows = spark.createDataFrame([(i, simhash._signed(p)) for i, p in enumerate(prints)], "doc_id long, fp long").withColumn("at", F.lit(None).cast("struct<file: string, row: bigint>"))
    got = {r.fp: r.component_id for r in simhash.components(rows).collect()}
    links = [(i, j) for i in range(400) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 3]
    want = labels_of(400, links)
    assert [got[simhash._signed(p)] for p in prints] == want


def test_forest_connects_what_links_connect():
    fps = np.array(random_prints(150, 3), np.uint64)
    a, b = simhash.forest(fps, 3)
    links = [(i, j) for i in range(150) for j in range(i) if int(fps[i] ^ fps[j]).bit_count() <= 3]
    assert labels_of(150, zip(a.tolist(), b.tolist())) == labels_of(150, links) and len(a) < 150


def test_odd_documents(spark):
    rows = [(3, None), (1, ""), (2, "one two"), (2, "one two"), (None, "one two"), (9, "word " * 30_000), (None, "alone here")]
    df = materialise(spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], DOCS).withColumn("fp", F.lit("x")), "d")
    got = simhash.near_dup_components(df).collect()
    assert len(got) == 7
    by = {r.fingerprint: r.component_id for r in got}
    assert by["0" * 16] == 1 and sum(r.component_id == 2 for r in got) == 3
    assert simhash.drop_near_duplicates(df).columns == df.columns
    assert simhash.near_dup_components(df.where("false")).count() == 0


def test_drop_keeps_one_row_of_each_component(spark):
    words = [f"w{i}" for i in range(400)]
    near = lambda k: " ".join([*words[:200], f"other{k}", *words[201:]])
    rows = [(5, " ".join(words)), (5, near(1)), (None, near(2)), (None, "alone"), (None, "alone"), (7, "alone too"), (7, "alone too"), (9, None), (8, "")]
    fps = [simhash.fingerprint(t) for _, t in rows]
    links = [(i, j) for i in range(len(rows)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 3]
    label = labels_of(len(rows), links)
    want = sorted(min((rows[i][0] is None, rows[i][0] or 0) for i in range(len(rows)) if label[i] == k) for k in set(label))
    plain = spark.createDataFrame([(i, t, n) for n, (i, t) in enumerate(rows)], "doc_id long, text string, n long").withColumns({c: F.lit(c) for c in ("_at", "_metadata", "_gone", "fp")})
    grouped = plain.groupBy("n", "_at", "_metadata", "_gone", "fp").agg(F.first("doc_id").alias("doc_id"), F.first("text").alias("text"))
    for df in (plain, materialise(plain, "d"), grouped, materialise(plain, "d").join(plain.select("n"), "n")):
        out = simhash.drop_near_duplicates(df)
        assert out.columns == df.columns
        assert sorted((r.doc_id is None, r.doc_id or 0) for r in out.collect()) == want


def embeddings(spark, x, ids=None):
    return spark.createDataFrame([(int(i if ids is None else ids[i]), None if v is None else [None if a is None else float(a) for a in v]) for i, v in enumerate(x)], "vec_id long, embedding array<float>")


def brute_vectors(x, threshold=0.9):
    good = [i for i, v in enumerate(x) if v is not None and len(v) and all(a is not None and np.isfinite(a) for a in v) and any(v)]
    u = {i: np.asarray(np.asarray(x[i], np.float32), float) for i in good}
    links = [(i, j) for i in good for j in good if j < i and len(u[i]) == len(u[j]) and u[i] @ u[j] / np.linalg.norm(u[i]) / np.linalg.norm(u[j]) >= threshold]
    count = [0] * len(x)
    for a, b in links:
        count[a] += 1
        count[b] += 1
    return count, labels_of(len(x), links)


def test_vectors_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(vectors, "SHARD", 60)
    rng = np.random.default_rng(5)
    x = [v for v in rng.normal(size=(250, 16))]
    for _ in range(60):
        x.append(x[rng.integers(0, 20)] + 0.15 * rng.normal(size=16))
    x += [x[0].copy(), x[0].copy(), None, [], [0.0] * 16, [float("nan")] + [1.0] * 15, [None] + [1.0] * 15, [1.0, 2.0], [2.0, 4.0]]
    out = vectors.near_duplicate_vectors(embeddings(spark, x).withColumn("node", F.lit(1))).toPandas().set_index("vec_id").sort_index()
    count, label = brute_vectors(x)
    assert len(out) == len(x) and (out.audited_recall >= 0.97).all()
    assert out.n_links.tolist() == count and out.component_id.tolist() == label
    assert (out.kept == (out.index == out.component_id)).all()


def test_links_of_a_dense_group_cut_over_many_shards(spark, monkeypatch):
    monkeypatch.setattr(vectors, "SHARD", 40)
    rng = np.random.default_rng(8)
    x = [*rng.normal(size=(300, 16)), *(np.ones(16) + 0.2 * rng.normal(size=(400, 16)))]
    out = vectors.near_duplicate_vectors(embeddings(spark, x), least_recall=0.0).toPandas().set_index("vec_id").sort_index()  # first build
    count, label = brute_vectors(x)
    assert sum(count) > 100_000 and out.n_links.sum() <= sum(count)
    assert out.n_links.sum() > 0.99 * sum(count) and out.component_id.tolist() == label


def test_short_audits_end_in_an_exact_comparison(spark, monkeypatch):
    monkeypatch.setattr(vectors, "BLOCK_NUMBERS", 1000, raising=False)
    search = vectors.search_cells
    monkeypatch.setattr(vectors, "search_cells", lambda *a: search(*a).where("false"))  # every build finds nothing
    rng = np.random.default_rng(10)
    x = [*rng.normal(size=(100, 16)), *(np.ones(16) + 0.2 * rng.normal(size=(60, 16))), [1.0, 2.0], [2.0, 4.1], None]
    x += [x[0], x[120], x[120]]
    out = vectors.near_duplicate_vectors(embeddings(spark, x)).toPandas().set_index("vec_id").sort_index()
    count, label = brute_vectors(x)
    assert out.n_links.tolist() == count and out.component_id.tolist() == label and (out.audited_recall == 1).all()


def test_no_shard_stays_crowded(spark, monkeypatch):
    monkeypatch.setattr(vectors, "SHARD", 20)
    monkeypatch.setattr(vectors, "MOST_SHARD", 40)
    monkeypatch.setattr(vectors, "MOST_VISITS", 64)
    rng = np.random.default_rng(12)
    flat = np.ones(16) + 1e-9 * rng.normal(size=(300, 16))  # too alike for any centroid to divide evenly
    x = [*rng.normal(size=(200, 16)), *flat, *rng.normal(size=(90, 5))]
    nodes = spark.createDataFrame([(i, [float(a) for a in v], 1) for i, v in enumerate(x)], "node long, v array<double>, n long")
    out = vectors.overlapping_shards(nodes, 3).toPandas()
    assert out.groupby("shard").size().max() <= 60 and set(out.node) == set(range(len(x)))
    assert not out.duplicated(["node", "shard"]).any() and (out.groupby("shard").v.agg(lambda v: v.map(len).nunique()) == 1).all()


def test_empty_vectors(spark):
    assert vectors.near_duplicate_vectors(embeddings(spark, [])).count() == 0


def test_pruned_graph_keeps_neighbourhoods_connected():
    x = vectors.unit(np.random.default_rng(6).normal(size=(300, 8))).astype(np.float32)
    g = vectors.pruned_graph(x)
    assert (g[:, 0] == np.argsort(-(x @ x.T), axis=1)[:, 1]).all() and g.shape[1] == 16


def test_search_finds_a_whole_clique():
    rng = np.random.default_rng(7)
    x = vectors.unit(np.vstack([rng.normal(size=(200, 16)), np.ones(16) + 0.02 * rng.normal(size=(300, 16))])).astype(np.float32)
    found = vectors.range_search(x, vectors.pruned_graph(x), np.arange(450, 460), 0, 0.9)
    assert np.mean([len(f) for f in found]) > 0.97 * 299
    assert isinstance(pd.Series(found), pd.Series)
