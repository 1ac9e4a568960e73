"""Relational operators that a user of the methods needs around them, each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform, hash_uniform_sql
from softlanes.functions.register import register_all
from softlanes.operators import stragglers
from softlanes.plans import sqlgen
from softlanes.plans.ranking import walk
from softlanes.plans.sqlgen import ranking_start, unroll, walk_ctes, with_
from softlanes.operators import engine, metrics, systems
from softlanes.sources import graphs
from softlanes.sources.tables import load

QUERIES: dict = {}


def rel(name, sql):
    return lambda run: QUERIES.__setitem__(name, (run, sql)) or run


@rel("rel_broadcast_join", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def broadcast_join(spark, d):
    c, n = load(spark, d, "customer", "c_nationkey"), load(spark, d, "nation", "n_nationkey", "n_name")  # 25 rows at any scale
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("n"))


@rel("rel_sort_merge_join", "SELECT o_orderstatus, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def merge_join(spark, d):
    o, l = load(spark, d, "orders", "o_orderkey", "o_orderstatus"), load(spark, d, "lineitem", "l_orderkey", "l_quantity")
    return o.hint("merge").join(l, o.o_orderkey == l.l_orderkey).groupBy("o_orderstatus").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


@rel("rel_shuffle_hash_join", "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def hash_join(spark, d):
    l, p = load(spark, d, "lineitem", "l_partkey"), load(spark, d, "part", "p_partkey", "p_brand")
    return l.join(p.hint("shuffle_hash"), l.l_partkey == p.p_partkey).groupBy("p_brand").agg(F.count("*").alias("n"))


@rel("rel_left_outer", "SELECT c_custkey, coalesce(count(o_orderkey), 0) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_orderstatus = 'F' GROUP BY 1")
def left_outer(spark, d):
    c = load(spark, d, "customer", "c_custkey")
    o = load(spark, d, "orders", "o_custkey", "o_orderkey", "o_orderstatus").where("o_orderstatus = 'F'")
    return c.join(o, c.c_custkey == o.o_custkey, "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@rel("rel_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def semi(spark, d):
    c, o = load(spark, d, "customer", "c_custkey"), load(spark, d, "orders", "o_custkey")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi")


@rel("rel_anti", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def anti(spark, d):
    p, l = load(spark, d, "part", "p_partkey"), load(spark, d, "lineitem", "l_partkey", "l_quantity").where("l_quantity > 45")
    return p.join(l, p.p_partkey == l.l_partkey, "left_anti")


@rel("rel_full_diff", """SELECT coalesce(a.i, b.i) AS i, round(coalesce(a.v, 0) - coalesce(b.v, 0), 9) AS e FROM
    (SELECT o_custkey AS i, sum(o_totalprice) / 1e6 AS v FROM orders WHERE o_orderstatus = 'F' GROUP BY 1) a
    FULL JOIN (SELECT o_custkey AS i, sum(o_totalprice) / 1e6 AS v FROM orders WHERE o_orderstatus = 'O' GROUP BY 1) b ON a.i = b.i""")
def full_diff(spark, d):
    o = load(spark, d, "orders", "o_custkey", "o_orderstatus", "o_totalprice")
    part = lambda s: o.where(F.col("o_orderstatus") == s).groupBy(F.col("o_custkey").alias("i")).agg((F.sum("o_totalprice") / 1e6).alias("v")).withColumn("p", F.lit(0))
    return metrics.errors(part("F"), part("O")).select("i", F.round("e", 9).alias("e"))


@rel("rel_cross_lanes", "SELECT n_nationkey AS i, q::INT AS q FROM nation, range(5) t(q)")
def cross_lanes(spark, d):
    return load(spark, d, "nation", F.col("n_nationkey").alias("i")).crossJoin(F.broadcast(spark.range(5).select(F.col("id").cast("int").alias("q"))))


@rel("rel_range_steps", f"""WITH l AS (SELECT q::INT AS q, (1 + floor({hash_uniform_sql('q', '41')} * 20))::INT AS steps FROM range(60) t(q)),
    b AS (SELECT * FROM (VALUES ('slow', 0, 5), ('middle', 6, 14), ('fast', 15, 99)) t(name, a, b)) SELECT name, count(*) AS n FROM l JOIN b ON steps BETWEEN a AND b GROUP BY 1""")
def range_steps(spark, d):
    lanes = stragglers.uniform_steps(spark, 60, 1, 20, 41)
    bands = spark.createDataFrame([("slow", 0, 5), ("middle", 6, 14), ("fast", 15, 99)], "name string, a int, b int")
    return lanes.join(F.broadcast(bands), F.col("steps").between(F.col("a"), F.col("b"))).groupBy("name").agg(F.count("*").alias("n"))


_MARKS = "(VALUES (TIMESTAMP '2024-01-05'), (TIMESTAMP '2024-01-15'), (TIMESTAMP '2024-01-25')) m(mark)"


@rel("rel_asof_heartbeat", f"""SELECT mark, user_id, max(ts) AS last_beat, arg_max(event_id, (ts, event_id)) AS event_id FROM events JOIN {_MARKS} ON ts <= mark GROUP BY 1, 2""")
def asof(spark, d):
    """Last heartbeat at or before each mark: a range join with a few marks, then a running maximum by key."""
    e = load(spark, d, "events", "event_id", "ts", "user_id")
    marks = spark.createDataFrame([("2024-01-05",), ("2024-01-15",), ("2024-01-25",)], "m string").select(F.col("m").cast("timestamp_ntz").alias("mark"))
    return e.join(F.broadcast(marks), F.col("ts") <= F.col("mark")).groupBy("mark", "user_id").agg(
        F.max("ts").alias("last_beat"), F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id")
    )


@rel("rel_topk_nodes", with_(walk_ctes(), ranking_start(graphs.segment_sql()), unroll(3),
     select="SELECT p, place, i FROM (SELECT p, i, row_number() OVER (PARTITION BY p ORDER BY round(v, 9) DESC, i) AS place FROM s3) WHERE place <= 10"))
def topk(spark, d):
    system = walk(spark, d)
    state = engine.run_lanes(system, system.forcing(graphs.in_segment(spark, d)), systems.initial_state(system, list(range(5))), [3] * 5)
    return metrics.top_nodes(state, 10)


@rel("rel_global_topk", f"SELECT q::INT AS q, round({hash_uniform_sql('q', '42')}, 9) AS speed FROM range(500) t(q) ORDER BY {hash_uniform_sql('q', '42')}, q LIMIT 25")
def global_topk(spark, d):
    return spark.range(500).select(F.col("id").cast("int").alias("q"), hash_uniform(F.col("id"), 42).alias("s")).orderBy("s", "q").limit(25).select("q", F.round("s", 9).alias("speed"))


@rel("rel_window_cumulative", "SELECT event_id, user_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS done FROM events")
def cumulative(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, d, "events", "event_id", "user_id", "ts").select("event_id", "user_id", F.count("*").over(w).alias("done"))


@rel("rel_window_range", """SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events""")
def window_range(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)).alias("last_day"))


@rel("rel_window_analytic", """SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events", "event_id", "user_id", "ts").select(
        "event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"))


@rel("rel_rank_family", """SELECT c_custkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr,
    ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey, c_custkey) AS nt FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)""")
def rank_family(spark, d):
    w, u = Window.partitionBy("c_mktsegment").orderBy("c_nationkey"), Window.partitionBy("c_mktsegment").orderBy("c_nationkey", "c_custkey")
    return load(spark, d, "customer", "c_custkey", "c_mktsegment", "c_nationkey").select(
        "c_custkey", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.ntile(4).over(u).alias("nt"))


def _grouped(name, spark_group, sql_group):
    @rel(name, f"""SELECT coalesce(o_orderstatus, '-') AS status, coalesce(o_orderpriority, '-') AS priority, count(*) AS n, round(sum(o_totalprice), 2) AS total
        FROM orders GROUP BY {sql_group}""")
    def run(spark, d):
        o = load(spark, d, "orders", "o_orderstatus", "o_orderpriority", "o_totalprice")
        return spark_group(o).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total")).select(
            F.coalesce("o_orderstatus", F.lit("-")).alias("status"), F.coalesce("o_orderpriority", F.lit("-")).alias("priority"), "n", "total")


_grouped("rel_rollup", lambda o: o.rollup("o_orderstatus", "o_orderpriority"), "ROLLUP (o_orderstatus, o_orderpriority)")
_grouped("rel_cube", lambda o: o.cube("o_orderstatus", "o_orderpriority"), "CUBE (o_orderstatus, o_orderpriority)")
_grouped("rel_grouping_sets", lambda o: o.groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority"),
         "GROUPING SETS ((o_orderstatus), (o_orderpriority))")


@rel("rel_pivot", """SELECT o_orderpriority AS priority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p
    FROM orders GROUP BY 1""")
def pivot(spark, d):
    o = load(spark, d, "orders", "o_orderstatus", "o_orderpriority")
    wide = o.groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O", "P"]).count()
    return wide.select("priority", *[F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"])


@rel("rel_unpivot", """SELECT l_returnflag AS flag, 'quantity' AS measure, round(avg(l_quantity), 6) AS value FROM lineitem GROUP BY 1
    UNION ALL SELECT l_returnflag, 'discount', round(avg(l_discount), 6) FROM lineitem GROUP BY 1""")
def unpivot(spark, d):
    wide = load(spark, d, "lineitem", "l_returnflag", "l_quantity", "l_discount").groupBy(F.col("l_returnflag").alias("flag")).agg(
        F.round(F.avg("l_quantity"), 6).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"))
    return wide.unpivot("flag", ["quantity", "discount"], "measure", "value")


def _pair_sets(spark, d):
    l = load(spark, d, "lineitem", "l_suppkey", "l_partkey", "l_returnflag")
    return l.where("l_returnflag = 'R'").select("l_suppkey", "l_partkey"), l.where("l_returnflag = 'A'").select("l_suppkey", "l_partkey")


_R, _A = [f"SELECT l_suppkey, l_partkey FROM lineitem WHERE l_returnflag = '{f}'" for f in "RA"]


@rel("rel_union", f"SELECT l_suppkey, count(*) AS n FROM ({_R} UNION ALL {_A}) GROUP BY 1")
def union(spark, d):
    r, a = _pair_sets(spark, d)
    return r.unionByName(a).groupBy("l_suppkey").agg(F.count("*").alias("n"))


@rel("rel_intersect", f"{_R} INTERSECT {_A}")
def intersect(spark, d):
    r, a = _pair_sets(spark, d)
    return r.intersect(a)


@rel("rel_except", f"{_R} EXCEPT {_A}")
def except_(spark, d):
    r, a = _pair_sets(spark, d)
    return r.subtract(a)


@rel("rel_except_all", f"SELECT l_suppkey, l_partkey, count(*) AS n FROM ({_R} EXCEPT ALL {_A}) GROUP BY 1, 2")
def except_all(spark, d):
    r, a = _pair_sets(spark, d)
    return r.exceptAll(a).groupBy("l_suppkey", "l_partkey").agg(F.count("*").alias("n"))


@rel("rel_json_props", "SELECT event_type, sum(CAST(json_extract_string(props, '$.k') AS BIGINT))::BIGINT AS total, count(*) AS n FROM events GROUP BY 1")
def json_props(spark, d):
    e = load(spark, d, "events", "event_type", "props")
    return e.groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total"), F.count("*").alias("n"))


@rel("rel_url_parts", "SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def url_parts(spark, d):
    return load(spark, d, "pages", "url").groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(F.count("*").alias("n"))


@rel("rel_date_month", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1")
def date_month(spark, d):
    o = load(spark, d, "orders", "o_orderdate", "o_totalprice")
    return o.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@rel("rel_array_hof", """SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings""")
def array_hof(spark, d):
    e = load(spark, d, "embeddings", "vec_id", "embedding")
    norm = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", F.round(norm, 5).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@rel("rel_map_lanes", f"SELECT q::INT AS q, (1 + floor({hash_uniform_sql('q', '43')} * 20))::INT AS steps FROM range(12) t(q)")
def map_lanes(spark, d):
    """Lane to steps as one map, taken apart again."""
    lanes = stragglers.uniform_steps(spark, 12, 1, 20, 43).agg(F.sort_array(F.collect_list(F.struct("q", "steps"))).alias("s"))
    as_map = lanes.select(F.map_from_arrays(F.transform("s", lambda x: x["q"]), F.transform("s", lambda x: x["steps"])).alias("m"))
    return as_map.select(F.explode("m").alias("q", "steps"))


@rel("rel_stats", """SELECT l_returnflag AS flag, round(avg(l_quantity), 6) AS mean, round(var_pop(l_quantity), 5) AS vp, round(var_samp(l_quantity), 5) AS vs, round(stddev(l_quantity), 6) AS sd,
    round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2, round(quantile_cont(l_quantity, 0.5), 6) AS med FROM lineitem GROUP BY 1""")
def stats(spark, d):
    l = load(spark, d, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice")
    r = lambda c, n, a: F.round(c, n).alias(a)
    q, x = F.col("l_quantity"), F.col("l_extendedprice")
    return l.groupBy(F.col("l_returnflag").alias("flag")).agg(
        r(F.avg(q), 6, "mean"), r(F.var_pop(q), 5, "vp"), r(F.var_samp(q), 5, "vs"), r(F.stddev(q), 6, "sd"), r(F.regr_slope(x, q), 4, "slope"),
        r(F.regr_r2(x, q), 6, "r2"), r(F.percentile(q, 0.5), 6, "med"))


@rel("rel_count_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, true AS sketch_near FROM lineitem")
def count_distinct(spark, d):
    l = load(spark, d, "lineitem", "l_partkey", "l_suppkey")
    out = l.agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"), F.approx_count_distinct("l_partkey", 0.02).alias("a"))
    return out.select("parts", "suppliers", (F.abs(F.col("a") - F.col("parts")) < 0.1 * F.col("parts")).alias("sketch_near"))


@rel("rel_case_fold", "SELECT c_custkey * 2 AS node, CASE WHEN c_acctbal <= 0 THEN 'none' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'some' ELSE 'much' END AS band FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")
def case_fold(spark, d):
    c = load(spark, d, "customer", "c_custkey", "c_acctbal", "c_mktsegment").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY"))
    return c.select((F.col("c_custkey") * 2).alias("node"), F.when(F.col("c_acctbal") <= 0, "none").when(F.col("c_acctbal").between(0, 5000), "some").otherwise("much").alias("band"))


@rel("rel_empty_columns", f"""WITH e AS ({graphs.EDGE_SQL['anchor']}) SELECT DISTINCT src AS i FROM e WHERE src NOT IN (SELECT dst FROM e)""")
def empty_columns(spark, d):
    """Nodes without an incoming edge: their column is empty."""
    e = graphs.anchor(spark, d)
    return e.select(F.col("src").alias("i")).distinct().join(e.select(F.col("dst").alias("i")), "i", "left_anti")


@rel("udtf_dft_rows", "SELECT p::INT AS p, q::INT AS q, round(cos(2 * pi() * p * q / 6) / sqrt(6), 9) + 0.0 AS re FROM range(5) a(p), range(6) b(q)")
def udtf_dft(spark, d):
    register_all(spark)
    return spark.sql("SELECT p, q, round(re, 9) + 0.0D AS re FROM dft_rows(6, 5)")


@rel("udtf_straggler_law", f"SELECT q::INT AS q, (1 + floor({hash_uniform_sql('q', '44')} * 20))::INT AS steps FROM range(40) t(q)")
def udtf_law(spark, d):
    register_all(spark)
    return spark.sql("SELECT * FROM straggler_law('uniform', 40, 44, 20.0)")


@rel("udf_vec_axpy", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: 2 * x::DOUBLE + x::DOUBLE)), 5) AS s FROM embeddings")
def udf_axpy(spark, d):
    register_all(spark)
    load(spark, d, "embeddings", "vec_id", "embedding").createOrReplaceTempView("lanes_embeddings")
    return spark.sql("""SELECT vec_id, round(aggregate(vec_axpy(2.0D, cast(embedding AS array<double>), cast(embedding AS array<double>)), 0.0D, (s, x) -> s + x), 5) AS s
        FROM lanes_embeddings""")


@rel("udaf_vec_sum", "SELECT label, round(sum(embedding[1]::DOUBLE), 6) AS first, round(sum(embedding[64]::DOUBLE), 6) AS last FROM embeddings WHERE vec_id < 100 GROUP BY 1")
def udaf_sum(spark, d):
    register_all(spark)
    e = load(spark, d, "embeddings", "vec_id", "embedding", "label").where("vec_id < 100")
    e.select("label", F.col("embedding").cast("array<double>").alias("x")).createOrReplaceTempView("lanes_vectors")
    return spark.sql("SELECT label, round(element_at(s, 1), 6) AS first, round(element_at(s, 64), 6) AS last FROM (SELECT label, vec_sum(x) AS s FROM lanes_vectors GROUP BY label)")
