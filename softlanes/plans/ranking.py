"""Queries over iterations: ranking walks, other systems, encoding, lanes, soft decoding, weights."""

from __future__ import annotations

from math import cos, pi, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform, hash_uniform_sql
from softlanes.operators import codes, decode, engine, halves, pieces, systems, weights
from softlanes.plans import sqlgen
from softlanes.plans.sqlgen import D, coded_start, parity_decode, parity_gen, ranking_start, stopped, unroll, walk_ctes, with_
from softlanes.sources import graphs
from softlanes.sources.session import materialise
from softlanes.sources.tables import load

QUERIES: dict = {}
RHO = 1 - D
PAIR = ["BUILDING", "MACHINERY"]
UNDIRECTED = {"purchase", "supply", "knn", "random"}  # both directions of an edge, of equal weight


def walk(spark, sf_dir, graph="purchase", d=D, **options):
    """The damped walk on a graph; edges, operator and nodes are each written once."""
    return walk_of(materialise(graphs.EDGES[graph](spark, sf_dir), "edges"), graph, d, **options)


def walk_of(edges, graph, d=D, **options):
    """The same on edges that are written already."""
    s = systems.restart_walk_system(edges, d, **options)
    # the columns of an undirected graph over their sums are similar to a symmetric matrix of norm one
    radius = 1 - d if graph in UNDIRECTED and options.get("dangling", "leak") == "leak" else None
    return systems.AffineSystem(materialise(s.op, "op"), s.drive, materialise(s.nodes, "nodes"), radius)


def coded_lanes(spark, sf_dir, inputs, g, steps, layout="auto", graph="purchase", system=None):
    """Lanes of code ``g`` stopped after ``steps``: real columns ``vec(i, p, v)`` and the system, built where none is given."""
    system = system or walk(spark, sf_dir, graph)
    m, owner = codes.real_columns(g)
    forcing = system.forcing(engine.encode_columns(systems.restart_batch(inputs), g))
    start = engine.encode_columns(systems.initial_state(system, list(range(len(g)))), g)
    return engine.run_lanes(system, forcing, start, [steps[q] for q in owner], layout), system


def _r9(df):
    return df.select("i", "p", F.round("v", 9).alias("v"))


def _plain(inputs, k, steps, layout):
    def run(spark, sf_dir):
        state, _ = coded_lanes(spark, sf_dir, inputs(spark, sf_dir), codes.identity_code(k), [steps] * k, layout)
        return _r9(state)

    return run


def restart_uniform(spark, sf_dir):
    system = walk(spark, sf_dir)
    r = systems.uniform_restart(system.nodes)
    return _r9(engine.run_lanes(system, system.forcing(r), systems.initial_state(system, [0]), [10], "wide"))


_UNIFORM_SQL = "SELECT i, 0 AS p, 1.0 / (SELECT count(*) FROM nodes) AS v FROM nodes"
QUERIES["restart_uniform_10"] = (restart_uniform, with_(walk_ctes(), ranking_start(_UNIFORM_SQL), unroll(10), select=sqlgen.ROUND9.format("s10")))
QUERIES["restart_segment_10"] = (
    _plain(graphs.in_segment, 5, 10, "wide"), with_(walk_ctes(), ranking_start(graphs.segment_sql()), unroll(10), select=sqlgen.ROUND9.format("s10")),
)
QUERIES["restart_nation_5"] = (
    _plain(graphs.in_nation, 25, 5, "block"), with_(walk_ctes(), ranking_start(graphs.NATION_SQL), unroll(5), select=sqlgen.ROUND9.format("s5")),
)


TASTES = 100


def restart_taste(spark, sf_dir):
    """The batch of the experiments: 100 customers' tastes."""
    taste = materialise(graphs.in_taste(spark, sf_dir, TASTES), "taste")
    system = walk(spark, sf_dir)
    return _r9(engine.run_lanes(system, system.forcing(taste), systems.initial_state(system, list(range(TASTES))), [5] * TASTES, "auto"))


QUERIES["restart_taste_5"] = (restart_taste, with_(walk_ctes(), ranking_start(graphs.taste_sql(TASTES)), unroll(5), select=sqlgen.ROUND9.format("s5")))


def soft_decode_many(spark, sf_dir):
    """100 problems on 120 lanes of a Fourier code, all lanes stopped at four steps: the decode must give the problems' own
    iterates. The graph goes in pieces and a task has all lanes on one; where its components are too large for that, a task
    has a few lanes on all links, and where those are too many, lanes take the wide layout."""
    g, steps = codes.dft_code(120, TASTES), [4] * 120
    taste = materialise(graphs.in_taste(spark, sf_dir, TASTES), "taste")
    edges = materialise(graphs.EDGES["purchase"](spark, sf_dir), "edges")
    m, owner = codes.real_columns(g)
    tau, cut = weights.tau_geometric(0.85, 4), pieces.cut(edges, D, taste, halves.cut)
    if cut is not None:
        r, _ = decode.real_decode(g, decode.decode_matrix(g, decode.noise_weights(tau, steps)))
        sums = cut.decoded(m, r, [steps[q] for q in owner], _sums, "p int, n long, total double, square double, mixed double")
        parts = [F.sum(c).alias(c) for c in ("n", "total", "square", "mixed")]
        return sums.groupBy("p").agg(*parts).select("p", "n", F.round("total", 9).alias("total"), F.round(F.col("square") * 1e3, 9).alias("square"), F.round("mixed", 7).alias("mixed"))
    system = walk_of(edges, "purchase")
    forcing = engine.encode_columns(taste, g)
    start = engine.encode_columns(systems.initial_state(system, list(range(TASTES))), g)
    chunks = engine.wide_lanes(system, materialise(system.forcing(forcing), "forcing"), materialise(start, "start"), [steps[q] for q in owner])
    found = decode.soft_decode_wide(engine.joined_lanes(chunks), g, steps, tau)
    rows = found.select("i", F.posexplode("x").alias("p", "v"))
    return rows.groupBy("p").agg(F.count("*").alias("n"), F.round(F.sum("v"), 9).alias("total"), F.round(F.sum(F.col("v") * F.col("v")) * 1e3, 9).alias("square"),
                                 F.round(F.sum(F.col("v") * F.pmod("i", F.lit(97))), 7).alias("mixed"))


def _sums(ids, x):
    """What the query reports of some nodes' estimates (nodes x problems)."""
    k = x.shape[1]
    columns = np.arange(k, dtype=np.int32), np.full(k, len(ids)), x.sum(axis=0), (x * x).sum(axis=0), (ids % 97).astype(float) @ x
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["p", "n", "total", "square", "mixed"])


QUERIES["soft_decode_dft_120_100"] = (soft_decode_many, with_(
    walk_ctes(), ranking_start(graphs.taste_sql(TASTES)), unroll(4),
    select="SELECT p, count(*) AS n, round(sum(v), 9) AS total, round(sum(v * v) * 1e3, 9) AS square, round(sum(v * (i % 97)), 7) AS mixed FROM s4 GROUP BY p",
))


def restart_converged(spark, sf_dir):
    system = walk(spark, sf_dir)
    r = materialise(graphs.in_segment(spark, sf_dir), "inputs")
    return _r9(engine.solve_converged(system, r, 5, tol=1e-14))


QUERIES["restart_converged_segment"] = (
    restart_converged, with_(walk_ctes(), ranking_start(graphs.segment_sql()), unroll(150), select=sqlgen.ROUND9.format("s150")),
)
QUERIES["restart_outdegree_3"] = (
    lambda spark, sf_dir: _r9((lambda s: engine.run_lanes(
        s, s.forcing(systems.uniform_restart(s.nodes)), systems.initial_state(s, [0]), [3], "long"))(walk(spark, sf_dir, "transition", orientation="outdegree"))),
    with_(walk_ctes("transition", orientation="outdegree"), ranking_start(_UNIFORM_SQL), unroll(3), select=sqlgen.ROUND9.format("s3")),
)


# ---- Jacobi

def nation_matrix(spark, sf_dir):
    """Laplacian of the nation trade (in millions) plus the identity: diagonally dominant."""
    edges = materialise(graphs.nation_trade(spark, sf_dir).select("src", "dst", (F.col("weight") / 1e6).alias("weight")), "trade")
    nodes = systems.nodes_of(edges)
    return materialise(systems.laplacian(edges).unionByName(nodes.select("i", F.col("i").alias("j"), F.lit(1.0).alias("w"))).groupBy("i", "j").agg(F.sum("w").alias("w")), "matrix")


def jacobi(spark, sf_dir):
    system = systems.jacobi_system(nation_matrix(spark, sf_dir))
    r = system.nodes.select("i", F.lit(0).alias("p"), (F.col("i") + 1).cast("double").alias("v"))
    forcing = materialise(system.forcing(r), "forcing")
    return _r9(engine.run_lanes(system, forcing, forcing, [10], "long"))


_NATION_MATRIX = [
    f"e AS (SELECT src, dst, weight / 1e6 AS w FROM ({graphs.EDGE_SQL['nation']}) WHERE src <> dst)",
    "a AS (SELECT i, j, sum(w) / 2 AS w FROM (SELECT src AS i, dst AS j, w FROM e UNION ALL SELECT dst, src, w FROM e) GROUP BY i, j)",
    "m AS MATERIALIZED (SELECT i, j, -w AS w FROM a UNION ALL SELECT i, i, sum(w) + 1 FROM a GROUP BY i)",
]
QUERIES["jacobi_nation"] = (jacobi, with_(
    _NATION_MATRIX, "dg AS (SELECT i, w AS d FROM m WHERE i = j)", "op AS MATERIALIZED (SELECT m.i, j, -w / d AS w FROM m JOIN dg USING (i) WHERE i <> j)",
    "f AS MATERIALIZED (SELECT i, 0 AS p, (i + 1) / d AS v FROM dg)", "s0 AS (SELECT * FROM f)", unroll(10), select=sqlgen.ROUND9.format("s10"),
))
QUERIES["jacobi_diag_dominant"] = (
    lambda spark, sf_dir: systems.row_dominance(nation_matrix(spark, sf_dir)).select("i", F.round("off", 9).alias("off")),
    with_(_NATION_MATRIX, select="SELECT i, round(sum(CASE WHEN i <> j THEN abs(w) ELSE 0 END) / sum(CASE WHEN i = j THEN abs(w) ELSE 0 END), 9) AS off FROM m GROUP BY i"),
)


# ---- ridge

EPS, LAM = 0.005, 1.0


def ridge(variant):
    def run(spark, sf_dir):
        e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
        rows = e.select(F.col("vec_id").alias("row"), F.posexplode("embedding").alias("col", "v0")).select("row", "col", F.col("v0").cast("double").alias("v"))
        s = systems.ridge_system(rows, LAM if variant == "corrected" else LAM * EPS, EPS, variant)
        s = systems.AffineSystem(materialise(s.op, "op"), s.drive, materialise(s.nodes, "nodes"))
        forcing = materialise(s.forcing(graphs.in_onehot(spark, sf_dir)), "forcing")
        return _r9(engine.run_lanes(s, forcing, systems.initial_state(s, [], "zero"), [20] * 10, "lane"))

    return run


def _ridge_sql(keep):
    return with_(
        "m AS MATERIALIZED (SELECT vec_id AS r, unnest(range(0, len(embedding))) AS c, unnest(embedding)::DOUBLE AS v FROM embeddings)",
        "g AS (SELECT a.c AS i, b.c AS j, sum(a.v * b.v) AS w FROM m a JOIN m b USING (r) GROUP BY 1, 2)",
        f"op AS MATERIALIZED (SELECT i, j, -{EPS} * w + CASE WHEN i = j THEN {keep} ELSE 0 END AS w FROM g)",
        f"f AS MATERIALIZED (SELECT m.c AS i, e.label::INT AS p, {EPS} * sum(m.v) AS v FROM m JOIN embeddings e ON e.vec_id = m.r GROUP BY 1, 2)",
        "s0 AS (SELECT i, p, 0.0 AS v FROM f)", unroll(20), select=sqlgen.ROUND9.format("s20"),
    )


QUERIES["ridge_gradient_20"] = (ridge("corrected"), _ridge_sql(1 - EPS * LAM))
QUERIES["ridge_gradient_as_printed_20"] = (ridge("as_printed"), _ridge_sql(1 - EPS * LAM))


# ---- band-limited signals

WIDTH = 5


def cosine_basis(spark, n=25, width=WIDTH):
    return spark.createDataFrame([
        (i, [sqrt((1 if c == 0 else 2) / n) * cos(pi * (i + 0.5) * c / n) for c in range(width)]) for i in range(n)
    ], "i bigint, u array<double>")


def month_signal(spark, sf_dir, months=None):
    """Observed nations of every month in orders, or of the first ``months``, in millions."""
    every = graphs.in_month(spark, sf_dir).where(F.col("i") % 4 != 0)
    kept = every if months is None else every.where(F.col("p") < months)
    return kept.select("i", "p", (F.col("v") / 1e6).alias("v"))


def cosine_completion(months=None):
    return lambda spark, sf_dir: _r9(systems.bandlimited_iterate(cosine_basis(spark), materialise(month_signal(spark, sf_dir, months), "seen"), WIDTH, 6))


QUERIES["bandlimited_cosine"] = (
    cosine_completion(4),  # the months of its SQL; all of them below
    with_(
        "u AS MATERIALIZED (SELECT i, c, sqrt((CASE WHEN c = 0 THEN 1 ELSE 2 END) / 25.0) * cos(pi() * (i + 0.5) * c / 25) AS u FROM range(25) a(i), range(5) b(c))",
        """o AS MATERIALIZED (SELECT c_nationkey::BIGINT AS i, ((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1)::INT AS p, sum(o_totalprice) / 1e6 AS v
        FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderdate < DATE '1995-05-01' AND c_nationkey % 4 <> 0 GROUP BY 1, 2)""",
        "s0 AS (SELECT i, p, 0.0 AS v FROM range(25) a(i), (SELECT DISTINCT p FROM o))",
        [
            x for t in range(1, 7) for x in (
                f"c{t} AS MATERIALIZED (SELECT s.p, u.c, sum(u.u * coalesce(o.v, s.v)) AS k FROM s{t - 1} s JOIN u USING (i) LEFT JOIN o ON o.i = s.i AND o.p = s.p GROUP BY 1, 2)",
                f"s{t} AS MATERIALIZED (SELECT u.i, c.p, sum(u.u * c.k) AS v FROM u JOIN c{t} c USING (c) GROUP BY 1, 2)",
            )
        ],
        select=sqlgen.ROUND9.format("s6"),
    ),
)


def bandlimited_nation(spark, sf_dir):
    """Nation trade's Laplacian basis, monthly signals, a quarter of the nations hidden: iteration and closed form."""
    trade = materialise(graphs.nation_trade(spark, sf_dir), "trade")
    basis = materialise(systems.laplacian_basis(systems.laplacian(trade), 4), "basis")
    seen = materialise(month_signal(spark, sf_dir), "seen")
    run = systems.bandlimited_iterate(basis, seen, 4, 40)
    exact = systems.bandlimited_exact(basis, seen, 4)
    return run.join(exact.withColumnRenamed("v", "exact"), ["i", "p"])


def bandlimited_knn(spark, sf_dir):
    """Label indicators on the neighbour graph, a quarter hidden, subspace basis; the estimate beside the truth."""
    edges = materialise(graphs.nearest_vectors(spark, sf_dir), "knn")
    basis = materialise(systems.laplacian_basis(systems.laplacian(edges), 10, "subspace", rounds=12), "basis")
    labels = graphs.in_onehot(spark, sf_dir)
    every = basis.select("i").crossJoin(F.broadcast(spark.range(10).select(F.col("id").cast("int").alias("p"))))
    signal = materialise(every.join(labels, ["i", "p"], "left").select("i", "p", F.coalesce("v", F.lit(0.0)).alias("v")), "labels")
    return systems.bandlimited_exact(basis, signal.where(F.col("i") % 4 != 0), 10).join(signal.withColumnRenamed("v", "truth"), ["i", "p"])


QUERIES["bandlimited_cosine_all_months"] = (cosine_completion(), None)
QUERIES["bandlimited_nation"] = (bandlimited_nation, None)
QUERIES["bandlimited_knn"] = (bandlimited_knn, None)


# ---- encoding and lanes

QUERIES["encode_parity"] = (
    lambda spark, sf_dir: engine.encode(graphs.in_segment(spark, sf_dir, PAIR), codes.parity_code(2)).select("i", "q", F.round("re", 9).alias("re"), F.round("im", 9).alias("im")),
    with_(f"r AS ({graphs.segment_sql(PAIR)})", f"gen AS ({parity_gen(2)})",
          select="SELECT i, q, round(sum(v * g), 9) AS re, 0.0 AS im FROM (SELECT r.i, q.q, r.v, coalesce(g.g, 0) AS g FROM r CROSS JOIN (SELECT DISTINCT q FROM gen) q LEFT JOIN gen g ON g.p = r.p AND g.q = q.q) GROUP BY 1, 2"),
)
QUERIES["encode_dft"] = (
    lambda spark, sf_dir: engine.encode(graphs.in_segment(spark, sf_dir), codes.dft_code(6, 5)).select(
        "i", "q", (F.round("re", 9) + 0.0).alias("re"), (F.round("im", 9) + 0.0).alias("im")),
    f"""SELECT i, q::INT AS q, round(sum(v * cos(2 * pi() * p * q / 6)) / sqrt(6), 9) + 0.0 AS re, round(-sum(v * sin(2 * pi() * p * q / 6)) / sqrt(6), 9) + 0.0 AS im
    FROM ({graphs.segment_sql()}), range(6) t(q) GROUP BY 1, 2""",
)
TOY = [4, 2, 6]
_TOY = [walk_ctes(), coded_start(graphs.segment_sql(PAIR), parity_gen(2)), unroll(6), stopped(TOY)]
QUERIES["lanes_fixed_steps"] = (
    lambda spark, sf_dir: _r9(coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir, PAIR), codes.parity_code(2), TOY, "long")[0]),
    with_(*_TOY, select=sqlgen.ROUND9.format("y")),
)


def _soft(inputs, g, steps, solver, layout="auto"):
    def run(spark, sf_dir):
        state, _ = coded_lanes(spark, sf_dir, inputs(spark, sf_dir), g, steps, layout)
        return _r9(decode.soft_decode(state, g, steps, weights.tau_geometric(RHO, max(steps)), solver=solver))

    return run


QUERIES["soft_decode_parity"] = (
    _soft(lambda s, d: graphs.in_segment(s, d, PAIR), codes.parity_code(2), TOY, "qr", "wide"), with_(*_TOY, parity_decode(TOY, RHO), select=sqlgen.ROUND9.format("x")),
)


def _dft_lane_ctes(n, k, steps):
    """Complex lanes as two real problems each: 2q holds the real part, 2q + 1 the imaginary part."""
    gen = (f"SELECT p::INT AS p, (2 * q)::INT AS q, cos(2 * pi() * p * q / {n}) / sqrt({n}) AS g FROM range({k}) a(p), range({n}) b(q) "
           f"UNION ALL SELECT p::INT, (2 * q + 1)::INT, -sin(2 * pi() * p * q / {n}) / sqrt({n}) FROM range({k}) a(p), range({n}) b(q)")
    both = [s for s in steps for _ in (0, 1)]
    return [*walk_ctes(), *coded_start(graphs.segment_sql(), gen), *unroll(max(steps)), stopped(both),
            "yc AS MATERIALIZED (SELECT i, p // 2 AS q, max(v) FILTER (p % 2 = 0) AS re, max(v) FILTER (p % 2 = 1) AS im FROM y GROUP BY 1, 2)"]


def _syndrome_sql(n, k, steps):
    """Decode with one or two spare lanes in syndrome form: spare row m of the Fourier matrix, scalar or 2 x 2 inverse."""
    spare = n - k
    h = f"SELECT m::INT AS m, q::INT AS q, cos(2 * pi() * (m + {k}) * q / {n}) / sqrt({n}) AS re, -sin(2 * pi() * (m + {k}) * q / {n}) / sqrt({n}) AS im FROM range({spare}) a(m), range({n}) b(q)"
    lanes = sqlgen.values([(q, s) for q, s in enumerate(steps)], "q, s")
    parts = [
        f"h AS MATERIALIZED ({h})", f"om AS MATERIALIZED (SELECT q, power({RHO}, 2.0 * s) AS t FROM ({lanes}))",
        # z = y hᴴ
        "z AS MATERIALIZED (SELECT y.i, h.m, sum(y.re * h.re + y.im * h.im) AS re, sum(y.im * h.re - y.re * h.im) AS im FROM yc y JOIN h USING (q) GROUP BY 1, 2)",
        # c = h om hᴴ
        "c AS MATERIALIZED (SELECT a.m AS a, b.m AS b, sum(t * (a.re * b.re + a.im * b.im)) AS re, sum(t * (a.im * b.re - a.re * b.im)) AS im FROM h a JOIN h b USING (q) JOIN om USING (q) GROUP BY 1, 2)",
    ]
    if spare == 1:
        parts.append("inv AS (SELECT a, b, 1 / re AS re, 0.0 AS im FROM c)")
    else:
        parts += [
            "cc AS (SELECT max(re) FILTER (a = 0 AND b = 0) AS p, max(re) FILTER (a = 1 AND b = 1) AS s, max(re) FILTER (a = 0 AND b = 1) AS qr, max(im) FILTER (a = 0 AND b = 1) AS qi FROM c)",
            "dt AS (SELECT p * s - qr * qr - qi * qi AS d, * FROM cc)",
            "inv AS MATERIALIZED (SELECT 0 AS a, 0 AS b, s / d AS re, 0.0 AS im FROM dt UNION ALL SELECT 1, 1, p / d, 0.0 FROM dt UNION ALL SELECT 0, 1, -qr / d, -qi / d FROM dt UNION ALL SELECT 1, 0, -qr / d, qi / d FROM dt)",
        ]
    parts += [
        "zi AS MATERIALIZED (SELECT z.i, v.b AS m, sum(z.re * v.re - z.im * v.im) AS re, sum(z.re * v.im + z.im * v.re) AS im FROM z JOIN inv v ON v.a = z.m GROUP BY 1, 2)",
        "e AS MATERIALIZED (SELECT zi.i, h.q, sum(t * (zi.re * h.re - zi.im * h.im)) AS re, sum(t * (zi.re * h.im + zi.im * h.re)) AS im FROM zi JOIN h USING (m) JOIN om USING (q) GROUP BY 1, 2)",
        f"""x AS (SELECT y.i, p::INT AS p, sum((y.re - e.re) * cos(2 * pi() * p * y.q / {n}) - (y.im - e.im) * sin(2 * pi() * p * y.q / {n})) / sqrt({n}) AS v
        FROM yc y JOIN e ON e.i = y.i AND e.q = y.q, range({k}) a(p) GROUP BY 1, 2)""",
    ]
    return with_(_dft_lane_ctes(n, k, steps), parts, select=sqlgen.ROUND9.format("x"))


ONE, TWO, SAME = [3, 5, 2, 6, 4, 5], [3, 5, 2, 6, 4, 5, 1], [4] * 6
QUERIES["soft_decode_dft_one_spare"] = (_soft(graphs.in_segment, codes.dft_code(6, 5), ONE, "qr"), _syndrome_sql(6, 5, ONE))
QUERIES["soft_decode_dft_two_spares"] = (_soft(graphs.in_segment, codes.dft_code(7, 5), TWO, "qr"), _syndrome_sql(7, 5, TWO))
QUERIES["soft_decode_equal_steps"] = (
    _soft(graphs.in_segment, codes.dft_code(6, 5), SAME, "qr"), with_(walk_ctes(), ranking_start(graphs.segment_sql()), unroll(4), select=sqlgen.ROUND9.format("s4")),
)


def correlated_parity(spark, sf_dir):
    """Two problems that share a common part, three lanes; psi of a common probe after a and b steps: rho^(a+b)."""
    g, tau = codes.parity_code(2), weights.tau_geometric(RHO, 6)
    state, _ = coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir, PAIR), g, TOY, "auto")
    steps = np.arange(7)
    psi = RHO ** (steps[:, None] + steps[None, :]) * (1 + 0.5 * np.cos(steps[:, None] - steps[None, :]))
    return _r9(decode.soft_decode(state, g, TOY, tau, psi))


def _adjugate_sql():
    """x = y om⁻¹ gᵀ (g om⁻¹ gᵀ)⁻¹ with the 3 x 3 inverse written out."""
    om = [[f"({'3.0 * power(%s, %s)' % (RHO, 2.0 * TOY[a]) if a == b else '0.0'} + {[1, 1, 2][a] * [1, 1, 2][b]}.0 * power({RHO}, {TOY[a] + TOY[b]}) * (1 + 0.5 * cos({TOY[a] - TOY[b]})))" for b in range(3)] for a in range(3)]
    names = ", ".join(f"{om[a][b]} AS o{a}{b}" for a in range(3) for b in range(3))
    minor = lambda a, b: "(o%d%d * o%d%d - o%d%d * o%d%d)" % (*[(r, c) for r in [(b + 1) % 3] for c in [(a + 1) % 3]][0], (b + 2) % 3, (a + 2) % 3, (b + 1) % 3, (a + 2) % 3, (b + 2) % 3, (a + 1) % 3)
    inv = ", ".join(f"{minor(a, b)} / det AS v{a}{b}" for a in range(3) for b in range(3))
    # rows of om⁻¹ gᵀ: lane a against problem p is v[a][p] + v[a][2]
    left = lambda a, p: f"(v{a}{p} + v{a}2)"
    gram = lambda p, r: f"({left(p, r)} + {left(2, r)})"
    det2 = f"({gram(0, 0)} * {gram(1, 1)} - {gram(0, 1)} * {gram(1, 0)})"
    y = [f"(y0 * {left(0, p)} + y1 * {left(1, p)} + y2 * {left(2, p)})" for p in (0, 1)]
    x0 = f"({y[0]} * {gram(1, 1)} - {y[1]} * {gram(1, 0)}) / {det2}"
    x1 = f"({y[1]} * {gram(0, 0)} - {y[0]} * {gram(0, 1)}) / {det2}"
    return with_(
        *_TOY, "wide AS (SELECT i, max(v) FILTER (p = 0) AS y0, max(v) FILTER (p = 1) AS y1, max(v) FILTER (p = 2) AS y2 FROM y GROUP BY i)",
        f"om AS (SELECT {names})", "omd AS (SELECT *, o00 * (o11 * o22 - o12 * o21) - o01 * (o10 * o22 - o12 * o20) + o02 * (o10 * o21 - o11 * o20) AS det FROM om)",
        f"inv AS MATERIALIZED (SELECT {inv} FROM omd)", f"x AS (SELECT i, 0 AS p, {x0} AS v FROM wide, inv UNION ALL SELECT i, 1, {x1} FROM wide, inv)", select=sqlgen.ROUND9.format("x"),
    )


QUERIES["soft_decode_correlated_parity"] = (correlated_parity, _adjugate_sql())


# ---- weights

def tau_exact(spark, sf_dir):
    system = systems.restart_walk_system(graphs.nation_trade(spark, sf_dir), weighted=True)
    _, b = systems.dense(system.op)
    tau = weights.tau_exact(b, np.eye(len(b)), 4)
    return spark.createDataFrame([(l, float(v)) for l, v in enumerate(tau)], "l int, value double").select("l", F.round("value", 9).alias("value"))


QUERIES["tau_exact_small"] = (tau_exact, with_(
    f"op AS MATERIALIZED (SELECT src AS i, dst AS j, {1 - D} * weight / sum(weight) OVER (PARTITION BY dst) AS w FROM ({graphs.EDGE_SQL['nation']}))",
    "s0 AS (SELECT n_nationkey::BIGINT AS i, n_nationkey AS p, 1.0::DOUBLE AS v FROM nation)", unroll(4, forcing=""),
    select=" UNION ALL ".join(f"SELECT {l} AS l, round(sum(v * v), 9) AS value FROM s{l}" for l in range(5)),
))


def probes(system, m, seed=31):
    ps = F.broadcast(system.op.sparkSession.range(m).select(F.col("id").cast("int").alias("p")))
    return materialise(system.nodes.crossJoin(ps).select("i", "p", (hash_uniform(F.col("i"), F.col("p"), seed) - 0.5).alias("v")), "probes")


_PROBES = lambda m: f"s0 AS MATERIALIZED (SELECT i, p::INT AS p, {hash_uniform_sql('i', 'p', '31')} - 0.5 AS v FROM nodes, range({m}) t(p))"


def tau_sampled(spark, sf_dir):
    system = walk(spark, sf_dir)
    return weights.tau_monte_carlo(system, probes(system, 10), 8).select("l", F.round("value", 9).alias("value"))


def psi_sampled(spark, sf_dir):
    system = walk(spark, sf_dir)
    return weights.psi_monte_carlo(system, probes(system, 4), 3).select("a", "b", F.round("value", 9).alias("value"))


QUERIES["tau_monte_carlo"] = (tau_sampled, with_(
    walk_ctes(), _PROBES(10), unroll(8, forcing=""), select=" UNION ALL ".join(f"SELECT {l} AS l, round(sum(v * v) / 10, 9) AS value FROM s{l}" for l in range(9)),
))
QUERIES["psi_monte_carlo"] = (psi_sampled, with_(
    walk_ctes(), _PROBES(4), unroll(3, forcing=""),
    select=" UNION ALL ".join(f"SELECT {a} AS a, {b} AS b, round(sum(x.v * y.v) / 4, 9) AS value FROM s{a} x JOIN s{b} y USING (i, p)" for a in range(4) for b in range(4)),
))
