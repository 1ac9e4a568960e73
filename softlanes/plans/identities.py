"""Queries over parts that SQL reaches by another way: direct solves by long iterations, estimated factors by unrolled
powers, bases and complements by their closed forms, decoders and layouts by those that must agree with them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform, hash_uniform_sql
from softlanes.operators import codes, decode, engine, metrics, systems, theory, weights
from softlanes.plans import sqlgen
from softlanes.plans.accuracy import _coded_unroll, _profile_ctes, _toy_ctes, toy_estimates
from softlanes.plans.ranking import ONE, PAIR, RHO, TOY, TWO, _dft_lane_ctes, _NATION_MATRIX, _r9, _soft, _syndrome_sql, _TOY, coded_lanes, cosine_basis, walk
from softlanes.plans.sqlgen import parity_decode, ranking_start, unroll, walk_ctes, with_
from softlanes.sources import graphs
from softlanes.sources.session import materialise
from softlanes.sources.tables import load

QUERIES: dict = {}


# ---- direct solves (SQL iterates until nothing moves)

def shifted_trade(spark, sf_dir):
    """Laplacian of the nation trade (in millions) plus the mean degree on the diagonal."""
    edges = materialise(graphs.nation_trade(spark, sf_dir).select("src", "dst", (F.col("weight") / 1e6).alias("weight")), "trade")
    lap = materialise(systems.laplacian(edges), "laplacian")
    degree = lap.where("i = j").agg(F.avg("w").alias("shift"))
    diagonal = lap.select("i").distinct().crossJoin(F.broadcast(degree)).select("i", F.col("i").alias("j"), F.col("shift").alias("w"))
    return lap.unionByName(diagonal)


def square_direct(spark, sf_dir):
    matrix = shifted_trade(spark, sf_dir)
    r = matrix.select("i").distinct().select("i", F.lit(0).alias("p"), (F.col("i") + 1).cast("double").alias("v"))
    return _r9(systems.solve_square(matrix, r))


_SHIFTED = [
    *_NATION_MATRIX[:2], "lap AS MATERIALIZED (SELECT i, j, -w AS w FROM a UNION ALL SELECT i, i, sum(w) FROM a GROUP BY i)",
    "dg AS MATERIALIZED (SELECT i, w + (SELECT avg(w) FROM lap WHERE i = j) AS d FROM lap WHERE i = j)",
]
QUERIES["square_direct"] = (square_direct, with_(
    _SHIFTED, "op AS MATERIALIZED (SELECT lap.i, j, -w / d AS w FROM lap JOIN dg USING (i) WHERE lap.i <> j)",
    "f AS MATERIALIZED (SELECT i, 0 AS p, (i + 1) / d AS v FROM dg)", "s0 AS (SELECT * FROM f)", unroll(80), select=sqlgen.ROUND9.format("s80"),
))


def _vector_rows(spark, sf_dir):
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return e.select(F.col("vec_id").alias("row"), F.posexplode("embedding").alias("col", "v0")).select("row", "col", F.col("v0").cast("double").alias("v"))


def ridge_direct(spark, sf_dir):
    """The penalty is the number of vectors, so that the SQL's gradient steps come to rest soon."""
    n = load(spark, sf_dir, "embeddings", "vec_id").count()
    return _r9(systems.solve_ridge(_vector_rows(spark, sf_dir), graphs.in_onehot(spark, sf_dir), float(n)))


_VECTORS = "m AS MATERIALIZED (SELECT vec_id AS r, unnest(range(0, len(embedding))) AS c, unnest(embedding)::DOUBLE AS v FROM embeddings)"
_GRAM = "g AS MATERIALIZED (SELECT a.c AS i, b.c AS j, sum(a.v * b.v) AS w FROM m a JOIN m b USING (r) GROUP BY 1, 2)"
QUERIES["ridge_direct"] = (ridge_direct, with_(
    _VECTORS, _GRAM, "e AS (SELECT 1 / (1.5 * count(*)) AS eps, count(*) AS lam FROM embeddings)",
    "op AS MATERIALIZED (SELECT i, j, CASE WHEN i = j THEN 1 - eps * lam ELSE 0 END - eps * w AS w FROM g, e)",
    "f AS MATERIALIZED (SELECT m.c AS i, v.label::INT AS p, sum(m.v) * max(e.eps) AS v FROM m JOIN embeddings v ON v.vec_id = m.r, e GROUP BY 1, 2)",
    "s0 AS (SELECT i, p, 0.0 AS v FROM f)", unroll(60), select=sqlgen.ROUND9.format("s60"),
))


# ---- factors and step sizes

_POWER = f"s0 AS MATERIALIZED (SELECT i, 0 AS p, 1 + {hash_uniform_sql('i', chr(39) + 'power' + chr(39))} AS v FROM (SELECT DISTINCT i FROM op))"
_GROWTH = "n AS (SELECT power((SELECT sqrt(sum(v * v)) FROM s20) / (SELECT sqrt(sum(v * v)) FROM s10), 0.1) AS factor)"


def contraction(spark, sf_dir):
    return spark.createDataFrame([(systems.contraction_estimate(walk(spark, sf_dir, "supply").op),)], "factor double").select(F.round("factor", 9).alias("factor"))


QUERIES["contraction_estimate"] = (contraction, with_(walk_ctes("supply"), _POWER, unroll(20, forcing=""), _GROWTH, select="SELECT round(factor, 9) AS factor FROM n"))


def step_size(spark, sf_dir):
    return spark.createDataFrame([(systems.safe_step(_vector_rows(spark, sf_dir), 1.0),)], "eps double").select(F.round("eps", 9).alias("eps"))


QUERIES["ridge_step_size"] = (step_size, with_(
    _VECTORS, _GRAM, "op AS (SELECT * FROM g)", _POWER, unroll(20, forcing=""), _GROWTH, select="SELECT round(1 / (factor * 1.05 + 1.0), 9) AS eps FROM n",
))


# ---- errors of the iteration

ONE_HOT = [(4, 0, 1.0), (5, 1, 1.0)]  # a supplier, a part


def _supply_walk(spark, sf_dir):
    r = spark.createDataFrame(ONE_HOT, "i bigint, p int, v double")
    system = walk(spark, sf_dir, "supply")
    return system, system.forcing(r), systems.initial_state(system, [0, 1])


_SUPPLY_START = [*walk_ctes("supply"), *ranking_start(sqlgen.values(ONE_HOT, "i, p, v"))]


def error_recursion(spark, sf_dir):
    """The starting error pushed through the operator four times."""
    system, forcing, start = _supply_walk(spark, sf_dir)
    truth = engine.run_lanes(system, forcing, start, [150] * 2)
    first = metrics.errors(start, truth).select("i", "p", F.col("e").alias("v"))
    return _r9(systems.propagate_error(system.op, materialise(first, "first"), 4))


QUERIES["error_recursion"] = (error_recursion, with_(  # SQL: the iterate's error after four steps
    _SUPPLY_START, unroll(150), select="SELECT i, p, round(a.v - b.v, 9) AS v FROM s4 a JOIN s150 b USING (i, p)",
))


def residuals(spark, sf_dir):
    system, forcing, start = _supply_walk(spark, sf_dir)
    state = engine.run_lanes(system, forcing, start, [2] * 2, "long")
    return metrics.residual(system, state, forcing).select("p", F.round(F.log10("residual"), 6).alias("log_residual"))


QUERIES["residual_walk"] = (residuals, with_(
    _SUPPLY_START, unroll(3), select="SELECT p, round(log10(sum((a.v - b.v) * (a.v - b.v))), 6) AS log_residual FROM s3 a JOIN s2 b USING (i, p) GROUP BY p",
))


def agreement(spark, sf_dir):
    found, truth = toy_estimates(spark, sf_dir, TOY)
    out = None
    for name, estimate in found.items():
        part = metrics.top_overlap(estimate, truth, 20).select(F.lit(name).alias("scheme"), "p", F.round("overlap", 6).alias("overlap"))
        out = part if out is None else out.unionByName(part)
    return out


_TOP = "SELECT {0}p, i FROM (SELECT {0}p, i, row_number() OVER (PARTITION BY {0}p ORDER BY round(v, 9) DESC, i) AS n FROM {1}) WHERE n <= 20"
QUERIES["ranking_agreement"] = (agreement, with_(
    _toy_ctes(), _coded_unroll(6), _profile_ctes(TOY), f"t AS ({_TOP.format('', 's150')})", f"e AS ({_TOP.format('scheme, ', 'est')})",
    select="SELECT e.scheme, e.p, round(count(t.i) / 20.0, 6) AS overlap FROM e LEFT JOIN t ON t.p = e.p AND t.i = e.i GROUP BY 1, 2",
))


# ---- band-limited signals

def path_projector(spark, sf_dir):
    """The four smoothest eigenvectors of a path of 25 nodes, as their projector (free of signs)."""
    path = spark.range(24).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).alias("weight"))
    u = materialise(systems.laplacian_basis(systems.laplacian(path), 4), "path")
    other = F.broadcast(u.select(F.col("i").alias("j"), F.col("u").alias("t")))
    product = F.aggregate(F.zip_with("u", "t", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return u.crossJoin(other).select("i", "j", (F.round(product, 9) + 0.0).alias("w"))


QUERIES["laplacian_basis_path"] = (path_projector, """WITH u AS (SELECT i, c, sqrt((CASE WHEN c = 0 THEN 1 ELSE 2 END) / 25.0) * cos(pi() * (i + 0.5) * c / 25) AS u FROM range(25) a(i), range(4) b(c))
    SELECT a.i, b.i AS j, round(sum(a.u * b.u), 9) + 0.0 AS w FROM u a JOIN u b USING (c) GROUP BY 1, 2""")


def completion_exact(spark, sf_dir):
    """Order totals by nation and month of the year, every fourth nation hidden: the closed form on a cosine basis."""
    orders, customer = load(spark, sf_dir, "orders", "o_custkey", "o_orderdate", "o_totalprice"), load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    seen = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).where("c_nationkey % 4 <> 0").groupBy(
        F.col("c_nationkey").cast("long").alias("i"), (F.month("o_orderdate") - 1).cast("int").alias("p")
    ).agg((F.sum("o_totalprice") / 1e6).alias("v"))
    return _r9(systems.bandlimited_exact(cosine_basis(spark), materialise(seen, "seen"), 5))


QUERIES["bandlimited_exact_cosine"] = (completion_exact, with_(  # SQL: the iteration until nothing moves
    "u AS MATERIALIZED (SELECT i, c, sqrt((CASE WHEN c = 0 THEN 1 ELSE 2 END) / 25.0) * cos(pi() * (i + 0.5) * c / 25) AS u FROM range(25) a(i), range(5) b(c))",
    """o AS MATERIALIZED (SELECT c_nationkey::BIGINT AS i, (month(o_orderdate) - 1)::INT AS p, sum(o_totalprice) / 1e6 AS v
    FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_nationkey % 4 <> 0 GROUP BY 1, 2)""",
    "s0 AS (SELECT i, p, 0.0 AS v FROM range(25) a(i), (SELECT DISTINCT p FROM o))",
    [
        x for t in range(1, 81) for x in (
            f"c{t} AS MATERIALIZED (SELECT s.p, u.c, sum(u.u * coalesce(o.v, s.v)) AS k FROM s{t - 1} s JOIN u USING (i) LEFT JOIN o ON o.i = s.i AND o.p = s.p GROUP BY 1, 2)",
            f"s{t} AS MATERIALIZED (SELECT u.i, c.p, sum(u.u * c.k) AS v FROM u JOIN c{t} c USING (c) GROUP BY 1, 2)",
        )
    ],
    select=sqlgen.ROUND9.format("s80"),
))


# ---- codes

def _entries(make):
    return lambda spark, sf_dir: codes.to_df(spark, make()).select("p", "q", (F.round("re", 9) + 0.0).alias("re"))


def _entries_sql(entry, n=12, k=10):
    return f"SELECT p::INT AS p, q::INT AS q, round({entry}, 9) + 0.0 AS re FROM range({k}) a(p), range({n}) b(q)"


def _drawn(what, seed=1):
    return hash_uniform_sql(f"'{what}'", str(seed), "0", "p", "q")


QUERIES["code_sign"] = (_entries(lambda: codes.sign_code(12, 10, 1)), _entries_sql(f"CASE WHEN {_drawn('sign')} < 0.5 THEN -1.0::DOUBLE ELSE 1.0 END"))
QUERIES["code_sparse"] = (_entries(lambda: codes.sparse_code(12, 10, 0.3, 1)), _entries_sql(f"CASE WHEN {_drawn('sparse')} < 0.3 THEN 1.0::DOUBLE ELSE 0.0 END"))


def _carried(make):
    """``(p, q, re)``: what the load of share p of all orders brings to lane q of a real code."""
    return lambda spark, sf_dir: graphs.in_load(spark, sf_dir, 10).join(F.broadcast(codes.to_df(spark, make())), "p").select(
        "p", "q", (F.round(F.col("v") * F.col("re"), 9) + 0.0).alias("re"))


def _carried_sql(entry):
    return f"SELECT p, q::INT AS q, round(v * ({entry}), 9) + 0.0 AS re FROM ({graphs.load_sql(10)}) a, range(12) b(q)"


QUERIES["code_gaussian"] = (_carried(lambda: codes.gaussian_code(12, 10, 1)), _carried_sql(f"sqrt(-2 * ln(1 - {_drawn('radius')})) * cos(2 * pi() * {_drawn('angle')})"))
QUERIES["code_hartley"] = (
    _carried(lambda: codes.orthonormal_code(codes.hartley_matrix(12), 10)), _carried_sql("(cos(2 * pi() * p * q / 12) + sin(2 * pi() * p * q / 12)) / sqrt(12)"),
)


def complement_projector(spark, sf_dir):
    """What the rows of a Fourier code leave, as the projector on it, each column times the load of its lane."""
    h = codes.complement(codes.dft_code(12, 10))
    loads = graphs.in_load(spark, sf_dir, 12).withColumnRenamed("p", "q")
    return codes.to_df(spark, h.conj().T @ h).join(F.broadcast(loads), "q").select(F.col("p").alias("a"), F.col("q").alias("b"), (F.round(F.col("v") * F.col("re"), 9) + 0.0).alias("re"))


QUERIES["code_complement"] = (complement_projector, f"""SELECT a::INT AS a, b, round(max(v) * (max(CASE WHEN a = b THEN 1.0::DOUBLE ELSE 0.0 END) - sum(cos(2 * pi() * z.p * (a - b) / 12)) / 12), 9) + 0.0 AS re
    FROM range(12) x(a), (SELECT p AS b, v FROM ({graphs.load_sql(12)})) y, range(10) z(p) GROUP BY 1, 2""")


# ---- decoders and layouts that must agree

QUERIES["soft_decode_parity_normal"] = (
    _soft(lambda s, d: graphs.in_segment(s, d, PAIR), codes.parity_code(2), TOY, "normal"), with_(*_TOY, parity_decode(TOY, RHO), select=sqlgen.ROUND9.format("x")),
)
QUERIES["soft_decode_dft_syndrome"] = (_soft(graphs.in_segment, codes.dft_code(7, 5), TWO, "syndrome"), _syndrome_sql(7, 5, TWO))


def lanes_by_snapshots(spark, sf_dir):
    """Lanes of the parity code mixed from iterates of the un-encoded problems."""
    system = walk(spark, sf_dir)
    inputs = materialise(graphs.in_segment(spark, sf_dir, PAIR), "inputs")
    forcing, start = materialise(system.forcing(inputs), "forcing"), materialise(systems.initial_state(system, [0, 1]), "start")
    return _r9(engine.lanes_from_snapshots(engine.snapshots(system, forcing, start, 2, TOY), codes.parity_code(2), TOY))


QUERIES["lanes_by_snapshots"] = (lanes_by_snapshots, with_(*_TOY, select=sqlgen.ROUND9.format("y")))


def conjugates(spark, sf_dir):
    """Fourier lanes where the slower one of a conjugate pair takes the faster one's conjugate state."""
    g = codes.dft_code(6, 5)
    state, _ = coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir), g, ONE)
    done, _ = decode.complete_conjugates(state, g, ONE)
    _, owner = codes.real_columns(g)
    columns = spark.createDataFrame([(c, q, int(c > 0 and owner[c - 1] == q)) for c, q in enumerate(owner)], "p int, q int, part int")
    return done.join(F.broadcast(columns), "p").select("i", "q", "part", (F.round("v", 9) + 0.0).alias("v"))


_AFTER = [max(s, ONE[(6 - q) % 6]) for q, s in enumerate(ONE)]
QUERIES["conjugate_completion"] = (conjugates, with_(  # lanes 0 and 3 are real
    _dft_lane_ctes(6, 5, _AFTER),
    select="SELECT i, q::INT AS q, 0 AS part, round(re, 9) + 0.0 AS v FROM yc UNION ALL SELECT i, q::INT, 1, round(im, 9) + 0.0 FROM yc WHERE q NOT IN (0, 3)",
))


def leak(spark, sf_dir):
    """Imaginary parts of the Fourier decoder's estimates, which vanish only where lanes stopped in conjugate pairs."""
    g = codes.dft_code(6, 5)
    state, _ = coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir), g, ONE)
    return decode.soft_decode(state, g, ONE, weights.tau_geometric(RHO, max(ONE))).select("i", "p", (F.round("im_leak", 9) + 0.0).alias("leak"))


QUERIES["decode_leak"] = (leak, _syndrome_sql(6, 5, ONE).rsplit("x AS (", 1)[0] + """x AS (SELECT y.i, p::INT AS p, sum((y.re - e.re) * sin(2 * pi() * p * y.q / 6) + (y.im - e.im) * cos(2 * pi() * p * y.q / 6)) / sqrt(6) AS v
    FROM yc y JOIN e ON e.i = y.i AND e.q = y.q, range(5) a(p) GROUP BY 1, 2)
SELECT i, p, round(v, 9) + 0.0 AS leak FROM x""")


# ---- gains and bounds

DRAWS, LANES = 40, 12


def spare_lane_gain(spark, sf_dir):
    """What one spare lane of a Fourier code takes away, over drawn step counts."""
    tau = weights.tau_geometric(RHO, 20)
    every = spark.range(DRAWS).crossJoin(spark.range(LANES).withColumnRenamed("id", "q"))
    drawn = every.select("id", "q", (1 + F.floor(hash_uniform(F.col("id"), F.col("q"), "gain") * 20)).cast("int").alias("s")).orderBy("id", "q").collect()
    steps = np.array([r.s for r in drawn]).reshape(DRAWS, LANES)
    return spark.createDataFrame([(theory.coding_gain(codes.dft_code(LANES, LANES - 1), tau, steps),)], "gain double").select(F.round("gain", 9).alias("gain"))


QUERIES["spare_lane_gain"] = (spare_lane_gain, f"""WITH w AS (SELECT d, power({RHO}, 2.0 * (1 + floor({hash_uniform_sql('d', 'q', chr(39) + 'gain' + chr(39))} * 20))) AS w FROM range({DRAWS}) a(d), range({LANES}) b(q)),
    g AS (SELECT var_pop(w) / avg(w) AS g FROM w GROUP BY d) SELECT round(avg(g), 9) AS gain FROM g""")


def tau_between_bounds(spark, sf_dir):
    """Exact weights under the covariance I + J / 2 (J all ones), and their bounds from its extreme eigenvalues."""
    system = walk(spark, sf_dir, "nation")
    _, b = systems.dense(system.op)
    c = np.eye(len(b)) + 0.5
    exact = weights.tau_exact(b, c, 3)
    rows = [(l, float(exact[l]), *theory.tau_bounds(b, c, l)) for l in range(4)]
    return spark.createDataFrame(rows, "l int, value double, low double, high double").select("l", *[F.round(x, 6).alias(x) for x in ("value", "low", "high")])


QUERIES["tau_bounds"] = (tau_between_bounds, with_(
    walk_ctes("nation"), "s0 AS MATERIALIZED (SELECT i, i AS p, 1.0::DOUBLE AS v FROM nodes)", unroll(3, forcing=""),
    select=" UNION ALL ".join(
        f"SELECT {l} AS l, round((SELECT sum(v * v) FROM s{l}) + 0.5 * (SELECT sum(t * t) FROM (SELECT sum(v) AS t FROM s{l} GROUP BY i)), 6) AS value, "
        f"round((SELECT sum(v * v) FROM s{l}), 6) AS low, round((SELECT sum(v * v) FROM s{l}) * (1 + 0.5 * (SELECT count(*) FROM nodes)), 6) AS high" for l in range(4)),
))
