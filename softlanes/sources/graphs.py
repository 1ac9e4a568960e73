"""Graphs and input batches built on the given tables, each beside its SQL.

Builders return ``edge(src, dst, weight)`` or ``vec(i, p, v)``; customers are even nodes and parts or
suppliers' counterparts odd ones, so that two kinds share one number line. The SQL of a builder is a
SELECT that DuckDB runs on the same tables.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform, hash_uniform_sql
from softlanes.sources.session import materialise
from softlanes.sources.tables import load

SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]


def both_ways(pairs: DataFrame) -> DataFrame:
    """Undirected edges from distinct pairs ``(src, dst, weight)``."""
    back = pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")
    return pairs.unionByName(back)


def _purchases(spark, sf_dir):
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    return orders.join(lines, orders.o_orderkey == lines.l_orderkey)


def purchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer and part, bipartite, both directions, weight 1."""
    pairs = _purchases(spark, sf_dir).select(
        (F.col("o_custkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst")
    ).distinct().withColumn("weight", F.lit(1.0))
    return both_ways(pairs)


def purchase_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = _purchases(spark, sf_dir).groupBy(
        (F.col("o_custkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst")
    ).agg(F.sum("l_quantity").alias("weight"))
    return both_ways(pairs)


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = load(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey").select(
        (F.col("l_suppkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst")
    ).distinct().withColumn("weight", F.lit(1.0))
    return both_ways(pairs)


def transition(spark: SparkSession, sf_dir: str, slices: int = 64) -> DataFrame:
    """User to the next event's user, directed, loops kept.

    The global order is cut into time slices, each windowed alone; what joins one slice's last event to the
    next one's first is a window over at most ``slices`` rows, so no task holds all events.
    """
    events = load(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    span = events.agg(F.min("t").alias("lo"), F.max("t").alias("hi")).first()
    if span.lo is None:
        return events.select(F.col("user_id").cast("long").alias("src"), F.col("user_id").cast("long").alias("dst"), F.lit(1.0).alias("weight"))
    width = (span.hi - span.lo) // slices + 1
    cut = events.withColumn("s", F.floor((F.col("t") - span.lo) / width))
    inside = cut.withColumn("nxt", F.lead("user_id").over(Window.partitionBy("s").orderBy("t", "event_id")))
    ends = cut.groupBy("s").agg(
        F.min_by("user_id", F.struct("t", "event_id")).alias("first_user"), F.max_by("user_id", F.struct("t", "event_id")).alias("last_user")
    )
    seam = ends.withColumn("nxt", F.lead("first_user").over(Window.orderBy("s"))).select(F.col("last_user").alias("user_id"), "nxt")
    pairs = inside.select("user_id", "nxt").unionByName(seam).where("nxt IS NOT NULL")
    return pairs.select(F.col("user_id").cast("long").alias("src"), F.col("nxt").cast("long").alias("dst")).distinct().withColumn("weight", F.lit(1.0))


def nation_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer nation to supplier nation, weight = revenue."""
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_extendedprice", "l_discount")
    customer = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    supplier = load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    joined = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(
        supplier, F.col("l_suppkey") == F.col("s_suppkey")
    )
    return joined.groupBy(F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst")).agg(
        F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("weight")
    )


def anchor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page and the distinct link targets in its HTML, by the target's hash; directed page to token."""
    pages = load(spark, sf_dir, "pages", "page_id", "html")
    tokens = pages.select("page_id", F.explode(F.expr(r"""regexp_extract_all(html, 'href="([^"]*)"', 1)""")).alias("href")).distinct()
    code = F.conv(F.substring(F.md5("href"), 1, 12), 16, 10).cast("long")
    return tokens.select((F.col("page_id") * 2).alias("src"), (code * 2 + 1).alias("dst")).distinct().withColumn("weight", F.lit(1.0))


MOST_VECTORS = 200_000


def nearest_vectors(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Symmetric graph of the ``k`` largest cosines of each vector (vectors have unit norm).

    Blocks of vectors meet a matrix of at most ``MOST_VECTORS`` others in one product each, and only ``k`` rows of
    each vector leave a task. More vectors are met matrix by matrix, and the best ``k`` of all are kept.
    """
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    parts = max(1, -(-e.count() // MOST_VECTORS))
    found = None
    for part in range(parts):
        whole = e.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == part).toPandas()
        if parts > 1 and not len(whole):
            continue
        near = e.mapInPandas(_nearest_in(whole, k), "a long, b long, c double")
        near = materialise(near, "nearest") if parts > 1 else near
        found = near if found is None else found.unionByName(near)
    if parts > 1:
        best = Window.partitionBy("a").orderBy(F.desc("c"), "b")
        found = found.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k)
    pairs = found.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct().withColumn("weight", F.lit(1.0))
    return both_ways(pairs)


def _nearest_in(whole, k: int):
    ids = whole["vec_id"].to_numpy()
    matrix = np.stack(whole["embedding"].to_numpy()).astype(np.float64) if len(whole) else np.empty((0, 0))

    def nearest(batches):
        for pdf in batches:
            for a in range(0, len(pdf), 512):
                own = pdf.iloc[a : a + 512]
                cos = np.round(np.stack(own["embedding"].to_numpy()).astype(np.float64) @ matrix.T, 9)
                cos[own["vec_id"].to_numpy()[:, None] == ids[None, :]] = -np.inf
                order = np.lexsort((np.broadcast_to(ids, cos.shape), -cos), axis=1)[:, :k]
                best = np.take_along_axis(cos, order, 1).ravel()
                rows = pd.DataFrame({"a": own["vec_id"].to_numpy().repeat(order.shape[1]), "b": ids[order].ravel(), "c": best})
                yield rows[best > -np.inf]

    return nearest


def random_graph(spark: SparkSession, n: int = 500, p: float = 0.1, seed: int = 7) -> DataFrame:
    """Erdos-Renyi graph by a hash coin per pair; a theta join of two ranges."""
    a, b = spark.range(n).select(F.col("id").alias("src")), spark.range(n).select(F.col("id").alias("dst"))
    pairs = a.join(F.broadcast(b), F.col("src") < F.col("dst")).where(hash_uniform(F.col("src"), F.col("dst"), seed) < p).withColumn("weight", F.lit(1.0))
    return both_ways(pairs)


EDGE_SQL = {
    "purchase": """SELECT DISTINCT o_custkey * 2 AS src, l_partkey * 2 + 1 AS dst, 1.0::DOUBLE AS weight FROM orders JOIN lineitem ON o_orderkey = l_orderkey
        UNION ALL SELECT DISTINCT l_partkey * 2 + 1, o_custkey * 2, 1.0::DOUBLE FROM orders JOIN lineitem ON o_orderkey = l_orderkey""",
    "purchase_weighted": """SELECT o_custkey * 2 AS src, l_partkey * 2 + 1 AS dst, sum(l_quantity) AS weight FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2
        UNION ALL SELECT l_partkey * 2 + 1, o_custkey * 2, sum(l_quantity) FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2""",
    "supply": """SELECT DISTINCT l_suppkey * 2 AS src, l_partkey * 2 + 1 AS dst, 1.0::DOUBLE AS weight FROM lineitem
        UNION ALL SELECT DISTINCT l_partkey * 2 + 1, l_suppkey * 2, 1.0::DOUBLE FROM lineitem""",
    "transition": """SELECT DISTINCT user_id::BIGINT AS src, nxt::BIGINT AS dst, 1.0::DOUBLE AS weight
        FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL""",
    "nation": """SELECT c_nationkey::BIGINT AS src, s_nationkey::BIGINT AS dst, sum(l_extendedprice * (1 - l_discount)) AS weight
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2""",
    "anchor": """SELECT DISTINCT page_id * 2 AS src, ('0x' || substr(md5(href), 1, 12))::BIGINT * 2 + 1 AS dst, 1.0::DOUBLE AS weight
        FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    "knn": """WITH c AS (SELECT a.vec_id AS a, b.vec_id AS b,
            round(list_sum(list_transform(range(1, len(a.embedding) + 1), lambda t: a.embedding[t]::DOUBLE * b.embedding[t]::DOUBLE)), 9) AS c
            FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id),
        r AS (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY c DESC, b) AS r FROM c),
        e AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM r WHERE r <= 8)
        SELECT src, dst, 1.0::DOUBLE AS weight FROM e UNION ALL SELECT dst, src, 1.0::DOUBLE FROM e""",
    "random": f"""SELECT a.i AS src, b.i AS dst, 1.0::DOUBLE AS weight FROM range(500) a(i), range(500) b(i)
        WHERE a.i <> b.i AND {hash_uniform_sql('least(a.i, b.i)', 'greatest(a.i, b.i)', "7")} < 0.1""",
}

EDGES = {
    "purchase": purchase, "purchase_weighted": purchase_weighted, "supply": supply, "transition": transition, "nation": nation_trade,
    "anchor": anchor, "knn": nearest_vectors, "random": lambda spark, sf_dir: random_graph(spark),
}


# ---- input batches: vec(i, p, v), columns sum to 1

def share(df: DataFrame) -> DataFrame:
    """Scale ``vec(i, p, v)`` to sum to 1 in each problem; totals are one row per problem."""
    total = df.groupBy("p").agg(F.sum("v").alias("t"))
    return df.join(F.broadcast(total), "p").select("i", "p", (F.col("v") / F.col("t")).alias("v"))


def in_segment(spark, sf_dir, names=SEGMENTS) -> DataFrame:
    c = load(spark, sf_dir, "customer", "c_custkey", "c_mktsegment")
    number = F.array_position(F.array(*map(F.lit, names)), F.col("c_mktsegment")).cast("int") - 1
    return share(c.where(F.col("c_mktsegment").isin(*names)).select((F.col("c_custkey") * 2).alias("i"), number.alias("p"), F.lit(1.0).alias("v")))


def in_nation(spark, sf_dir) -> DataFrame:
    c = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    return share(c.select((F.col("c_custkey") * 2).alias("i"), F.col("c_nationkey").cast("int").alias("p"), F.lit(1.0).alias("v")))


def in_taste(spark, sf_dir, k: int = 100) -> DataFrame:
    """Restart on the parts a customer bought, by quantity; the first ``k`` customers with orders are the problems, in order."""
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey").where("o_custkey IS NOT NULL")
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    most = 2 * k  # customers that are looked at: more where too few of these have orders with lines
    while True:
        first = materialise(orders.select("o_custkey").distinct().orderBy("o_custkey").limit(most), "customers")
        own = materialise(orders.join(F.broadcast(first), "o_custkey"), "own-orders")
        bought = materialise(lines.join(own, lines.l_orderkey == own.o_orderkey).select("o_custkey", "l_partkey", "l_quantity"), "bought")
        found = bought.select("o_custkey").distinct().orderBy("o_custkey").limit(k).collect()  # the batch of problems
        if len(found) == k or first.count() < most:
            break
        most *= 8
    number = F.broadcast(spark.createDataFrame([(r.o_custkey, n) for n, r in enumerate(found)], "o_custkey long, p int"))
    return share(bought.join(number, "o_custkey").groupBy((F.col("l_partkey") * 2 + 1).alias("i"), "p").agg(F.sum("l_quantity").alias("v")))


def in_topics(spark, sf_dir, m: int) -> DataFrame:
    """Popularity of parts in ``m`` separate shares of all orders, by hash of the order: draws of a common topic."""
    sold = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    topic = F.floor(hash_uniform(F.col("l_orderkey"), F.lit(0), 13) * m).cast("int")
    return share(sold.groupBy((F.col("l_partkey") * 2 + 1).alias("i"), topic.alias("p")).agg(F.sum("l_quantity").alias("v")))


def in_common(spark, sf_dir, rho: float, k: int = 100) -> tuple[DataFrame, DataFrame]:
    """(inputs, common part): own taste mixed with the popularity of parts, correlated over problems."""
    own = in_taste(spark, sf_dir, k)
    popular = share(load(spark, sf_dir, "lineitem", "l_partkey", "l_quantity").groupBy((F.col("l_partkey") * 2 + 1).alias("i")).agg(
        F.sum("l_quantity").alias("v")).select("i", F.lit(0).alias("p"), "v"))
    spread = popular.crossJoin(F.broadcast(spark.range(k).select(F.col("id").cast("int").alias("q")))).select("i", F.col("q").alias("p"), (F.col("v") * rho).alias("v"))
    mixed = own.select("i", "p", (F.col("v") * (1 - rho)).alias("v")).unionByName(spread).groupBy("i", "p").agg(F.sum("v").alias("v"))
    return mixed, popular


def in_hash(nodes: DataFrame, k: int, seed: int = 3, power: int = 6) -> DataFrame:
    """Independent positive inputs over all ``nodes(i)``: hash uniforms to a power, scaled to 1."""
    spark = nodes.sparkSession
    problems = F.broadcast(spark.range(k).select(F.col("id").cast("int").alias("p")))
    return share(nodes.crossJoin(problems).select("i", "p", F.pow(hash_uniform(F.col("i"), F.col("p"), seed), F.lit(power)).alias("v")))


def in_onehot(spark, sf_dir) -> DataFrame:
    """Indicator of label p over the vectors (rows of the ridge problem)."""
    return load(spark, sf_dir, "embeddings", "vec_id", "label").select(F.col("vec_id").alias("i"), F.col("label").cast("int").alias("p"), F.lit(1.0).alias("v"))


def in_load(spark, sf_dir, k: int) -> DataFrame:
    """``(p, v)``: the quantity ordered in each of ``k`` shares of the orders, over the mean of the shares."""
    sold = load(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity")
    shares = sold.groupBy(F.pmod("l_orderkey", F.lit(k)).cast("int").alias("p")).agg(F.sum("l_quantity").alias("s"))
    return shares.crossJoin(F.broadcast(shares.agg(F.sum("s").alias("t")))).select("p", (F.col("s") * k / F.col("t")).alias("v"))


def in_month(spark, sf_dir) -> DataFrame:
    """Order total of a nation by month since 1995-01: a graph signal at several instants."""
    o = load(spark, sf_dir, "orders", "o_custkey", "o_orderdate", "o_totalprice")
    c = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    month = ((F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1).cast("int")
    return o.join(c, o.o_custkey == c.c_custkey).groupBy(F.col("c_nationkey").cast("long").alias("i"), month.alias("p")).agg(F.sum("o_totalprice").alias("v"))


def load_sql(k: int) -> str:
    return f"SELECT p, s * {k} / sum(s) OVER () AS v FROM (SELECT (l_orderkey % {k})::INT AS p, sum(l_quantity) AS s FROM lineitem GROUP BY 1)"


SEGMENT_SQL = """SELECT c_custkey * 2 AS i, CASE c_mktsegment {cases} END AS p, 1.0 / count(*) OVER (PARTITION BY c_mktsegment) AS v
    FROM customer WHERE c_mktsegment IN ({names})"""


def segment_sql(names=SEGMENTS) -> str:
    cases = " ".join(f"WHEN '{s}' THEN {k}" for k, s in enumerate(names))
    return SEGMENT_SQL.format(cases=cases, names=", ".join(f"'{s}'" for s in names))


NATION_SQL = "SELECT c_custkey * 2 AS i, c_nationkey::INT AS p, 1.0 / count(*) OVER (PARTITION BY c_nationkey) AS v FROM customer"


def taste_sql(k: int = 100) -> str:
    return f"""SELECT i, p, v / sum(v) OVER (PARTITION BY p) AS v FROM (SELECT l_partkey * 2 + 1 AS i, p::INT AS p, sum(l_quantity) AS v
        FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN (SELECT o_custkey, rank() OVER (ORDER BY o_custkey) - 1 AS p
        FROM (SELECT DISTINCT o_custkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey)) USING (o_custkey) WHERE p < {k} GROUP BY 1, 2)"""
