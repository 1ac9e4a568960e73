"""Quality classifier, language network, URL rules: held-out accuracy, gradients, odd input."""

import random
from collections import Counter
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from softlanes.llm import language, quality, urls
from softlanes.llm.shared import load, materialise

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
MEDIUM = "/root/testdata/sf0.01"


def test_quality_held_out_accuracy(spark):
    out = quality.op4_fourier_quality(spark, MEDIUM).join(load(spark, MEDIUM, "labels"), "doc_id").toPandas()
    held = out[out.held_out]
    assert (held.predicted == held.quality).mean() > 0.95 and out.score.between(0, 1).all()


def test_quality_without_labels_and_odd_rows(spark):
    rows = [(0, None), (1, ""), (1, ""), (None, "some words"), (2, "!" * 100_000)]
    df = materialise(spark.createDataFrame([(i, t, None, None, None) for i, t in rows], DOCS).withColumn("x", F.lit("clash")), "d")
    none = spark.createDataFrame([], "doc_id long, y int")
    got = quality.quality_scores(df, none).collect()
    assert len(got) == 5 and all(r.score == 0.5 and r.predicted == 1 for r in got) and sum(r.held_out for r in got if r.doc_id is None) == 1
    assert quality.quality_scores(df.where("false"), none).count() == 0
    assert quality.keep_good(df, none).columns == df.columns


def test_isotonic_and_features():
    got = quality.pool_adjacent_violators(np.array([1.0, 3, 2, 2, 5]), np.ones(5))
    assert np.allclose(got, [1, 7 / 3, 7 / 3, 7 / 3, 5])
    rng = np.random.default_rng(0)
    z = rng.normal(size=(2, 5))
    waves, phase = rng.normal(size=(5, 20000)), rng.uniform(0, 2 * np.pi, 20000)
    f = quality.kernel_features(z, waves, phase)[:, 6:]
    assert f[0] @ f[1] == pytest.approx(np.exp(-((z[0] - z[1]) ** 2).sum() / 2), abs=0.03)
    assert len(quality.statistics(None)) == len(quality.STATISTICS) and np.isfinite(quality.statistics("a" * 10)).all()


def test_language_held_out_accuracy(spark):
    out = language.op6_recurrent_language(spark, MEDIUM).join(load(spark, MEDIUM, "documents").select("doc_id", "lang"), "doc_id").toPandas()
    assert (out[out.held_out].lang == out[out.held_out].lang_pred).mean() > 0.97 and out.score.between(0, 1).all()


def test_gradients_by_differences():
    rng = np.random.default_rng(1)
    codes, y = rng.integers(97, 110, (7, 5)).astype(np.int16), rng.integers(0, 2, 5)
    net = language.Recurrent(["a", "b"], rng.normal(size=(2, 257, 9)) * 0.5, rng.normal(size=(2, 3, 9)) * 0.5, rng.normal(size=(6, 2)), np.zeros(2))

    def loss():
        p = net.positions(codes)
        return -np.log(p[:, np.arange(5), y]).mean()

    (hf, kf), (hb, kb) = net.states(codes, 0, True), net.states(codes, 1, True)
    p = net.positions(codes)
    p[:, np.arange(5), y] -= 1
    d = p / 35
    grads = {"table": np.zeros_like(net.table), "rec": np.zeros_like(net.rec)}
    dh = d @ net.out.T
    language._backward(net, codes, 0, kf, dh[:, :, :3], grads)
    language._backward(net, codes, 1, kb, dh[:, :, 3:], grads)
    for name in ("table", "rec"):
        param = getattr(net, name)
        for at in [tuple(int(v) for v in rng.integers(0, s)) for s in [param.shape] * 6]:
            if name == "table":
                at = (at[0], int(codes[0, at[1] % 5]), at[2])
            keep = param[at]
            param[at] = keep + 1e-2
            up = loss()
            param[at] = keep - 1e-2
            down = loss()
            param[at] = keep
            assert (up - down) / 2e-2 == pytest.approx(grads[name][at], abs=2e-4)


def test_language_odd_rows(spark):
    rows = [(0, None, "en"), (1, "", "en"), (2, "123 !?", "en"), (3, "hello", None), (3, "hello", None), (None, "x", "en")]
    df = materialise(spark.createDataFrame([(i, t, k, None, None) for i, t, k in rows], DOCS), "d")
    got = language.predictions(df, language.learn(df)).collect()
    assert len(got) == 6 and all(r.lang_pred == "und" and r.score == 0 for r in got)
    assert sorted(str(r.doc_id) for r in language.keep_recognised(df).collect()) == ["3", "3", "None"]
    trained = language.train(language.codes_of([b"aaaa", b"zzzz"] * 20, 8)[0], np.array([0, 1] * 20), ["a", "z"], rounds=30, batch=16)
    got = {r.doc_id: r.lang_pred for r in language.predictions(df, trained).collect()}
    assert got[0] == got[1] == got[2] == "und" and got[3] in "az"
    assert language.predict(trained, ["aaaa" * 500, "zzzz" * 500, ""]).argmax(axis=1).tolist()[:2] == [0, 1]
    assert language.predictions(df.where("false"), trained).count() == 0


URLS = [
    (0, None), (1, "no scheme"), (2, "http://A.Example.COM/en/7?q"), (3, "http://example.com/en/8"), (4, "https://x.example.net/de/81#t"), (5, "https://net/de/1"),
    (6, "http://notexample.net/de/8"), (7, "ftp://org/es"), (8, "ftp://a.org/es/"), (9, "http://com?x=/en/"), (10, "http://"), (11, "a://b://com/en/"),
]


def test_url_rules(spark):
    pages = spark.createDataFrame(URLS, "page_id long, url string").withColumn("rule", F.lit("clash"))
    none = spark.createDataFrame([], "url string, bad boolean")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge_urls(pages, none).collect()}
    assert got[0] == got[1] == ("", "", None, "allow")
    assert got[2] == ("a.example.com", "/en/7", "example.com/en/7", "allow")
    assert got[3][2:] == ("com/en/", "block") and got[4][2:] == ("example.net/de/8", "block") and got[5][2:] == ("net/de/", "allow")
    assert got[6][2:] == ("net/de/", "allow") and got[7][2] is None and got[8][2:] == ("org/es/", "block")
    assert got[9][:3] == ("com", "", None) and got[10][:2] == ("", "") and got[11][:2] == ("b:", "//com/en/")


def test_mined_rules_block(spark):
    rows = [(f"http://cheap-pills{i % 5}.example/{w}", True) for i in range(40) for w in ("buy",)] + [(f"http://blog{i % 7}.example/post", False) for i in range(200)]
    labels = spark.createDataFrame(rows, "url string, bad boolean")
    pages = spark.createDataFrame([(0, "http://cheap-pills9.example/buy/1"), (1, "http://blog9.example/post"), (1, "http://blog9.example/post")], "page_id long, url string")
    got = [(r.page_id, r.verdict) for r in urls.judge_urls(pages, labels).collect()]
    assert sorted(got) == [(0, "block"), (1, "allow"), (1, "allow")]
    rules = urls.mine_rules(labels.select(urls.tokens_of(urls.host_of(F.col("url")), urls.path_of(F.col("url"))).alias("tokens"), "bad")).collect()
    assert rules and all(r.confidence >= 0.6 for r in rules)


def brute_rules(rows, least, confidence):
    """Every token set of every URL, counted; those that predict the bad label and have no part that does."""
    seen, hits = Counter(), Counter()
    for tokens, bad in rows:
        for k in range(1, len(tokens) + 1):
            for part in combinations(sorted(tokens), k):
                seen[part] += 1
                hits[part] += bad
    base = sum(bad for _, bad in rows) / len(rows)
    good = {p: hits[p] / seen[p] for p in seen if hits[p] >= least and hits[p] / seen[p] >= confidence and hits[p] / seen[p] > base}
    return {p: c for p, c in good.items() if not any(q in good for k in range(1, len(p)) for q in combinations(p, k))}


@pytest.mark.parametrize("seed", range(3))
def test_mined_rules_equal_brute_force(spark, seed):
    rng = random.Random(seed)
    rows = []
    for _ in range(300):
        tokens = rng.sample("abcdefgh", rng.randint(0, 6))
        rows.append((tokens, rng.random() < (0.9 if {"a", "b", "c", "d"} <= set(tokens) or {"e", "f"} <= set(tokens) else 0.25)))
    labelled = spark.createDataFrame([*rows, (["a"], None)], "tokens array<string>, bad boolean")
    got = {tuple(r.tokens): r.confidence for r in urls.mine_rules(labelled, support=0.02, confidence=0.7).collect()}
    assert got == pytest.approx(brute_rules(rows, 6, 0.7)) and max(map(len, got)) >= 2


@pytest.mark.parametrize("seed", range(2))
def test_rules_of_rarer_tokens_of_long_urls_are_mined(spark, seed):
    """Fourteen tokens that are likelier bad than the pair that decides: no bound may drop that pair."""
    rng = random.Random(seed)
    rows = [([f"t{i:02}" for i in range(14) if rng.random() < 0.5] + ["x", "y"], True) for _ in range(60)]
    rows += [([f"t{i:02}" for i in range(14) if rng.random() < 0.3] + [rng.choice("xy")], False) for _ in range(60)]
    labelled = spark.createDataFrame(rows, "tokens array<string>, bad boolean")
    got = {tuple(r.tokens): r.confidence for r in urls.mine_rules(labelled, support=0.1, confidence=0.75, most_items=None).collect()}
    assert got == pytest.approx(brute_rules(rows, 12, 0.75)) and ("x", "y") in got


def test_tokens_that_come_together_do_not_multiply(spark):
    """Forty tokens of the same rows decide nothing until one more comes: a rule with each of them, found in a few levels."""
    together = [f"t{i:02}" for i in range(40)]
    rows = [([*together, "z"], True)] * 20 + [(together, False)] * 20 + [(["z"], False)] * 20
    labelled = spark.createDataFrame(rows, "tokens array<string>, bad boolean")
    got = {tuple(r.tokens) for r in urls.mine_rules(labelled, most_items=None).collect()}
    assert got == {(t, "z") for t in together}
    pages = spark.createDataFrame([(0, "http://t39.z/"), (1, "http://t39.t38/")], "page_id long, url string")
    shown = spark.createDataFrame([(f"http://{'.'.join(t)}/", bad) for t, bad in rows], "url string, bad boolean")
    assert [r.verdict for r in urls.judge_urls(pages, shown).orderBy("page_id").collect()] == ["block", "allow"]


def test_mining_of_long_urls_and_odd_labels(spark):
    long = [f"t{i}" for i in range(400)]
    rules = urls.mine_rules(spark.createDataFrame([(long, True)] * 30 + [(["x"], False)] * 300, "tokens array<string>, bad boolean"))
    assert rules.count() == 12
    assert urls.mine_rules(spark.createDataFrame([([], True)] * 30, "tokens array<string>, bad boolean")).count() == 0
    empty = spark.createDataFrame([], "page_id long, url string")
    assert urls.judge_urls(empty, spark.createDataFrame([], "url string, bad boolean")).count() == 0
    far = spark.createDataFrame([(1, "http://com/en/" + "x" * 200_000)], "page_id long, url string")
    assert urls.judge_urls(far, spark.createDataFrame([], "url string, bad boolean")).first().verdict == "block"
