"""URL filter: rules by host and path, and association rules mined from labelled URLs.

Combinations of URL tokens that predict the bad label are mined level by level: of token sets with enough bad URLs,
those that predict it (by confidence, which must also beat the share of bad URLs) are rules and grow no further; the
others grow by a token. A set that covers the same URLs as one of its parts is dropped: whatever grows from it is a rule
only where the same without the idle token is one too. So all rules with no part that is a rule are found, of any length
and from all tokens, and tokens that always come together do not multiply. Rules are matched against all tokens of a
URL by an inverted index: tokens meet the rules that contain them, and a rule holds when as many of its tokens met as
it has.

Given rules come first: of those whose host is the URL's host or a parent domain of it, and whose path
begins the URL's path, the longest decides; a URL without one gets the mined rules' verdict.

Edge cases: null URLs and URLs without ``://`` have empty host and path, no tokens, and are allowed;
repeated rows give repeated results; an empty table, or labels without bad rows, gives no mined rules;
extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import load, materialise

# The given rules.
RULES = [("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/")]
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    host = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(host, _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def given_rule(host: Column, path: Column, rules: list[tuple[str, str]]) -> tuple[Column, Column]:
    """The longest rule that fits and its verdict, both null where none fits. Equal lengths: the first given."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, text in sorted(rules, key=lambda r: len(r[1])):
        own, _, rest = text.partition("/")
        fits = ((host == own) | host.endswith("." + own)) & path.startswith("/" + rest)
        rule, verdict = F.when(fits, text).otherwise(rule), F.when(fits, kind).otherwise(verdict)
    return rule, verdict


def tokens_of(host: Column, path: Column) -> Column:
    """Distinct tokens: labels of the host and words of the path, marked by where they stand; numbers left out."""
    mark = lambda c, sep, kind: F.transform(
        F.filter(F.split(F.lower(c), sep), lambda x: (F.length(x) > 0) & ~x.rlike(r"^\d+$")), lambda x: F.concat(F.lit(kind), x)
    )
    return F.array_distinct(F.concat(mark(host, r"[.\-:@_]+", "h:"), mark(path, r"[^\p{L}\p{N}]+", "p:")))


def mine_rules(labelled: DataFrame, support: float = 0.002, confidence: float = 0.6, most_items: int | None = 12, least_rows: int = 5) -> DataFrame:
    """``(rule_id, tokens, size, confidence)`` from ``labelled(tokens, bad boolean)``.

    ``least_rows`` bad URLs, or ``support`` of all, make a set frequent. ``most_items=None`` mines all tokens; a number
    keeps that many of the likeliest bad tokens of each URL, for a quick look: ``judge_urls`` mines all.
    """
    spark = labelled.sparkSession
    schema = "rule_id long, tokens array<string>, size int, confidence double"
    rows = materialise(labelled.where("bad IS NOT NULL").select(F.monotonically_increasing_id().alias("i"), "tokens", "bad"), "url-labels")
    n, bad = rows.agg(F.count("*"), F.coalesce(F.sum(F.col("bad").cast("long")), F.lit(0))).first()
    least = max(least_rows, math.ceil(support * n))
    if bad < least or bad == n:
        return spark.createDataFrame([], schema)
    each = rows.select("i", "bad", F.explode("tokens").alias("token")).where("token IS NOT NULL").distinct()
    hits = F.sum(F.col("bad").cast("long"))
    # a set has no more bad URLs than any of its tokens
    useful = each.groupBy("token").agg(hits.alias("hits"), (hits / F.count("*")).alias("rate")).where(F.col("hits") >= least)
    listed = F.array_sort(F.collect_list(F.struct(-F.col("rate"), -F.col("hits"), F.col("token").alias("token"))))
    own = each.join(useful, "token").groupBy("i", "bad").agg((listed if most_items is None else F.slice(listed, 1, most_items)).getField("token").alias("items"))
    # equal token sets are one basket that counts for all of them
    baskets = materialise(own.groupBy(F.array_sort("items").alias("items")).agg(F.count("*").alias("seen"), hits.alias("hits")).withColumn("b", F.monotonically_increasing_id()), "url-baskets")
    items = baskets.select("b", "seen", "hits", F.explode("items").alias("token"))
    occurs, growing, found, size = items.withColumn("set", F.array("token")).drop("token"), None, None, 1  # which basket holds which set
    ratio = F.col("hits") / F.col("seen")
    while True:
        counted = occurs.groupBy("set").agg(F.sum("seen").alias("seen"), F.sum("hits").alias("hits")).where(F.col("hits") >= least)
        free = counted.where(F.col("seen") < n) if size == 1 else _without_idle(counted, growing, size)
        level = materialise(free.withColumn("rule", (ratio >= confidence) & (ratio > bad / n)), "url-sets")
        rules, growing = level.where("rule").drop("rule"), level.where("NOT rule").select("set", "seen")
        found = rules if found is None else found.unionByName(rules)
        if growing.isEmpty():
            break
        if size == 1:
            items = items.join(growing.select(F.col("set")[0].alias("token")), "token", "left_semi")
        longer = occurs.join(growing.select("set"), "set", "left_semi").join(items.select("b", "token"), "b").where(F.col("token") > F.element_at("set", -1))
        occurs = materialise(longer.select("b", "seen", "hits", F.concat("set", F.array("token")).alias("set")), "url-occurs")
        size += 1
    return materialise(found.select(F.monotonically_increasing_id().alias("rule_id"), F.col("set").alias("tokens"), F.size("set").alias("size"), ratio.alias("confidence")), "url-rules")


def _without_idle(counted: DataFrame, growing: DataFrame, size: int) -> DataFrame:
    """Sets of ``size`` tokens whose parts of one token less all still grow and all cover more URLs than they do."""
    part = F.explode(F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda gone: F.filter("set", lambda x, at: at != gone))).alias("part")
    parts = counted.select("set", "seen", "hits", part).join(growing.select(F.col("set").alias("part"), F.col("seen").alias("wider")), "part")
    whole = parts.groupBy("set", "seen", "hits").agg(F.count("*").alias("parts"), F.min("wider").alias("wider"))
    return whole.where((F.col("parts") == size) & (F.col("wider") > F.col("seen"))).select("set", "seen", "hits")


def matched(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """Keys of ``urls(key, tokens)`` for which some rule holds: ``(key)``.

    Only tokens that some rule has survive the first join, so what is shuffled is small.
    """
    index = rules.select("rule_id", "size", F.explode("tokens").alias("token"))
    hits = urls.select("key", F.explode("tokens").alias("token")).join(index, "token")
    met = hits.groupBy("key", "rule_id", "size").agg(F.count("*").alias("met"))
    return met.where("met = size").select("key").distinct()


def judge_urls(df: DataFrame, labels: DataFrame, rules=RULES, url: str = "url", page_id: str = "page_id", **mining) -> DataFrame:
    """``(page_id, host, path, rule, verdict)`` of every row; ``labels(url, bad)`` are the URLs to learn from."""
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    learnt = mine_rules(labels.select(tokens_of(host, path).alias("tokens"), "bad").where("bad IS NOT NULL"), **{"most_items": None, **mining})
    rule, verdict = given_rule(F.col("host"), F.col("path"), rules)
    split = df.select(F.col(page_id).alias("page_id"), F.col(url).alias("url")).select(
        "page_id", "url", host.alias("host"), path.alias("path")
    ).select("page_id", "host", "path", rule.alias("rule"), verdict.alias("given"))
    # the mined verdict depends on host and path alone
    key = F.struct("host", "path")
    undecided = split.where("given IS NULL").groupBy("host", "path").agg(F.lit(1).alias("one")).select(
        key.alias("key"), tokens_of(F.col("host"), F.col("path")).alias("tokens")
    )
    bad = matched(undecided, learnt).select("key.host", "key.path", F.lit("block").alias("mined"))
    return split.join(bad, ["host", "path"], "left").select(
        "page_id", "host", "path", "rule", F.coalesce("given", "mined", F.lit("allow")).alias("verdict")
    )


def labelled_urls(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """``(url, bad)``: a page shows the document whose number ends its path; bad is low quality or toxic."""
    number = F.regexp_extract(path_of(F.col("url")), r"/(\d{1,18})(?:\.\w+)?/?$", 1)
    shown = pages.select("url", number.try_cast("long").alias("doc_id"))
    judged = labels.groupBy("doc_id").agg(F.max((F.col("quality") == 0) | (F.col("toxic") == 1)).alias("bad"))
    return shown.join(judged, "doc_id").select("url", "bad")


def op9_association_rules(spark, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages").select("page_id", "url")
    return judge_urls(pages, labelled_urls(pages, load(spark, sf_dir, "labels")))
