"""Queries over baselines and accuracy measures, on small real codes that SQL can follow."""

from __future__ import annotations

from functools import reduce
from math import ceil

from pyspark.sql import functions as F

from softlanes.operators import baselines, codes, decode, engine, metrics, systems, weights
from softlanes.plans import sqlgen
from softlanes.plans.ranking import PAIR, RHO, TOY, _r9, coded_lanes, walk
from softlanes.plans.sqlgen import coded_start, parity_decode, parity_gen, ranking_start, stopped, unroll, walk_ctes, with_
from softlanes.sources import graphs
from softlanes.sources.session import materialise

QUERIES: dict = {}
SEVEN = [3, 5, 2, 6, 4, 6, 1]  # five problems, two twins
TRUTH = 150


def _twins(spark, sf_dir, steps=SEVEN):
    g = codes.twin_code(7, 5)
    state, _ = coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir), g, steps)
    return state, spark.createDataFrame([(q, s) for q, s in enumerate(steps)], "q int, steps int")


def _twins_sql(steps=SEVEN):
    """Un-encoded iterates ``s0..``: lane q works on problem ``CASE q``."""
    return [walk_ctes(), ranking_start(graphs.segment_sql()), unroll(max(steps))]


def uncoded_segment(spark, sf_dir):
    state, _ = _twins(spark, sf_dir)
    return _r9(baselines.uncoded(state, 5))


QUERIES["uncoded_segment"] = (uncoded_segment, with_(*_twins_sql(), stopped(SEVEN[:5]), select=sqlgen.ROUND9.format("y")))


def twins_best(spark, sf_dir):
    state, lanes = _twins(spark, sf_dir)
    return _r9(baselines.twins_best(state, lanes, 7, 5))


_BEST = [max(SEVEN[0], SEVEN[5]), max(SEVEN[1], SEVEN[6]), *SEVEN[2:5]]
QUERIES["twins_best"] = (twins_best, with_(*_twins_sql(), stopped(_BEST), select=sqlgen.ROUND9.format("y")))


def _weighted(rule):
    def run(spark, sf_dir):
        state, lanes = _twins(spark, sf_dir)
        tau = spark.createDataFrame([(l, RHO ** (2.0 * l)) for l in range(7)], "l int, value double")
        return _r9(baselines.twins_weighted(state, lanes, tau, 7, 5, weight=rule))

    power = 1 if rule == "inverse_root" else 2
    w = lambda s: f"power({RHO}, -{power}.0 * {s})"
    parts = []
    for p in range(5):
        own = [SEVEN[p]] + ([SEVEN[5 + p]] if p < 2 else [])
        rows = " UNION ALL ".join(f"SELECT i, {w(s)} AS w, v FROM s{s} WHERE p = {p}" for s in own)
        parts.append(f"SELECT i, {p} AS p, sum(w * v) / sum(w) AS v FROM ({rows}) GROUP BY i")
    return run, with_(*_twins_sql(), f"y AS ({' UNION ALL '.join(parts)})", select=sqlgen.ROUND9.format("y"))


QUERIES["twins_weighted"] = _weighted("inverse_root")
QUERIES["twins_weighted_inverse_mse"] = _weighted("inverse_mse")
_TOY = [walk_ctes(), coded_start(graphs.segment_sql(PAIR), parity_gen(2)), unroll(6), stopped(TOY)]
_WIDE = "wide AS (SELECT i, max(v) FILTER (p = 0) AS y0, max(v) FILTER (p = 1) AS y1, max(v) FILTER (p = 2) AS y2 FROM y GROUP BY i)"
QUERIES["fastest_k_parity"] = (
    lambda spark, sf_dir: _r9(baselines.fastest_k_decode(coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir, PAIR), codes.parity_code(2), TOY)[0], codes.parity_code(2), TOY)),
    with_(*_TOY, _WIDE, select="SELECT i, 0 AS p, round(y0, 9) AS v FROM wide UNION ALL SELECT i, 1, round(y2 - y0, 9) FROM wide"),
)
QUERIES["erasure_or_fail"] = (
    lambda spark, sf_dir: _r9(baselines.erasure_or_fail(coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir, PAIR), codes.parity_code(2), TOY)[0], codes.parity_code(2), TOY, 6)),
    with_(walk_ctes(), select="SELECT i, p::INT AS p, NULL::DOUBLE AS v FROM nodes, range(2) t(p)"),
)
QUERIES["erasure_done"] = (  # two of the three lanes are done, which is enough
    lambda spark, sf_dir: _r9(baselines.erasure_or_fail(coded_lanes(spark, sf_dir, graphs.in_segment(spark, sf_dir, PAIR), codes.parity_code(2), TOY)[0], codes.parity_code(2), TOY, 4)),
    with_(*_TOY, _WIDE, select="SELECT i, 0 AS p, round(y0, 9) AS v FROM wide UNION ALL SELECT i, 1, round(y2 - y0, 9) FROM wide"),
)


# ---- errors of schemes on the toy: two problems, three lanes

def toy_system(spark, sf_dir):
    """(system, inputs, solutions) of the toy, for any number of lanes and deadlines."""
    inputs = materialise(graphs.in_segment(spark, sf_dir, PAIR), "inputs")
    system = walk(spark, sf_dir)
    return system, inputs, engine.solve_converged(system, inputs, 2, tol=1e-17)


def toy_estimates(spark, sf_dir, steps, known=None):
    """Estimates of every scheme with the same three lanes, as ``(scheme, i, p, v)``, and the truth."""
    system, inputs, truth = known or toy_system(spark, sf_dir)
    parity, twins = codes.parity_code(2), codes.twin_code(3, 2)
    coded = materialise(coded_lanes(spark, sf_dir, inputs, parity, steps, system=system)[0], "coded")
    plain = materialise(coded_lanes(spark, sf_dir, inputs, twins, steps, system=system)[0], "plain")
    lanes = spark.createDataFrame([(q, s) for q, s in enumerate(steps)], "q int, steps int")
    tau = spark.createDataFrame([(l, RHO ** (2.0 * l)) for l in range(max(steps) + 1)], "l int, value double")
    found = {
        "uncoded": baselines.uncoded(plain, 2), "twins_best": baselines.twins_best(plain, lanes, 3, 2), "twins_weighted": baselines.twins_weighted(plain, lanes, tau, 3, 2),
        "soft": decode.soft_decode(coded, parity, steps, weights.tau_geometric(RHO, max(steps)), solver="qr").select("i", "p", "v"),
        "fastest_k": baselines.fastest_k_decode(coded, parity, steps),
    }
    return found, truth


def toy_profile(spark, sf_dir, steps, known=None):
    found, truth = toy_estimates(spark, sf_dir, steps, known)
    parts = [metrics.per_problem(est, truth).select(F.lit(name).alias("scheme"), "p", "sse") for name, est in found.items()]
    return materialise(reduce(lambda a, b: a.unionByName(b), parts), "profile")


def _profile_ctes(steps, tag=""):
    """``prof{tag}(scheme, p, sse)`` for one set of step counts, over plain iterates ``s`` and coded ones ``z``."""
    fast = sorted(sorted(range(3), key=lambda q: (-steps[q], q))[:2])
    x1 = {(0, 1): ("y0", "y1"), (0, 2): ("y0", "y2 - y0"), (1, 2): ("y2 - y1", "y1")}[tuple(fast)]
    best = [max(steps[0], steps[2]), steps[1]]
    w = lambda s: f"power({RHO}, -1.0 * {s})"
    a, b = steps[0], steps[2]
    decoded = parity_decode(steps, RHO).replace("wide AS", f"wide{tag} AS").replace("x AS", f"x{tag} AS").replace("FROM wide", f"FROM wide{tag}").replace("FROM y ", f"FROM y{tag} ")
    return [
        stopped(steps, f"y{tag}", "z"), decoded,
        f"""est{tag} AS (SELECT 'uncoded' AS scheme, i, p, v FROM s{steps[0]} WHERE p = 0 UNION ALL SELECT 'uncoded', i, p, v FROM s{steps[1]} WHERE p = 1
        UNION ALL SELECT 'twins_best', i, p, v FROM s{best[0]} WHERE p = 0 UNION ALL SELECT 'twins_best', i, p, v FROM s{best[1]} WHERE p = 1
        UNION ALL SELECT 'twins_weighted', m.i, 0, ({w(a)} * m.v + {w(b)} * n.v) / ({w(a)} + {w(b)}) FROM s{a} m JOIN s{b} n USING (i, p) WHERE p = 0
        UNION ALL SELECT 'twins_weighted', i, p, v FROM s{steps[1]} WHERE p = 1 UNION ALL SELECT 'soft', i, p, v FROM x{tag}
        UNION ALL SELECT 'fastest_k', i, 0, {x1[0]} FROM wide{tag} UNION ALL SELECT 'fastest_k', i, 1, {x1[1]} FROM wide{tag})""",
        f"prof{tag} AS MATERIALIZED (SELECT e.scheme, e.p, sum((e.v - t.v) * (e.v - t.v)) AS sse FROM est{tag} e JOIN s{TRUTH} t USING (i, p) GROUP BY 1, 2)",
    ]


def _toy_ctes(own: str | None = None, graph: str = "purchase"):
    own = own or graphs.segment_sql(PAIR)
    plain = ranking_start(own)
    coded = [x.replace("r AS", "rc AS", 1).replace("f AS", "fz AS", 1).replace("s0 AS", "z0 AS", 1).replace("FROM r JOIN", "FROM rc r JOIN") for x in coded_start(own, parity_gen(2))]
    return [*walk_ctes(graph), *plain, *unroll(TRUTH), *coded]


def _coded_unroll(most):
    return unroll(most, "z0", "fz", prefix="z")


_LOG = "round(log10(sse), 6)"


def mse_per_problem(spark, sf_dir):
    return toy_profile(spark, sf_dir, TOY).select("scheme", "p", F.round(F.log10("sse"), 6).alias("log_sse"))


QUERIES["mse_per_problem"] = (mse_per_problem, with_(_toy_ctes(), _coded_unroll(6), _profile_ctes(TOY), select=f"SELECT scheme, p, {_LOG} AS log_sse FROM prof"))
QUERIES["mse_by_scheme"] = (
    lambda spark, sf_dir: toy_profile(spark, sf_dir, TOY).groupBy("scheme").agg(F.round(F.log10(F.avg("sse")), 6).alias("log_mse")),
    with_(_toy_ctes(), _coded_unroll(6), _profile_ctes(TOY), select="SELECT scheme, round(log10(avg(sse)), 6) AS log_mse FROM prof GROUP BY 1"),
)
QUERIES["peak_to_average"] = (
    lambda spark, sf_dir: metrics.peak_to_average(toy_profile(spark, sf_dir, TOY), "scheme").select("scheme", F.round("ratio", 6).alias("ratio")),
    with_(_toy_ctes(), _coded_unroll(6), _profile_ctes(TOY), select="SELECT scheme, round(max(sse) / avg(sse), 6) AS ratio FROM prof GROUP BY 1"),
)


def ratio_query(spark, sf_dir):
    scores = toy_profile(spark, sf_dir, TOY).groupBy("scheme").agg(F.avg("sse").alias("mse"))
    wide = metrics.ratios(scores, "soft")
    return wide.select(*[F.round(F.log10(c), 6).alias(c) for c in wide.columns])


_RATIO = ", ".join(f"round(log10(avg(sse) FILTER (scheme = '{s}') / avg(sse) FILTER (scheme = 'soft')), 6) AS {s}_over_soft" for s in ["fastest_k", "twins_best", "twins_weighted", "uncoded"])
QUERIES["ratio_rep_over_coded"] = (ratio_query, with_(_toy_ctes(), _coded_unroll(6), _profile_ctes(TOY), select=f"SELECT {_RATIO} FROM prof"))
SPEEDS, DEADLINES = [1.5, 3.0, 1.0], [6.0, 12.0, 18.0]


def mse_vs_deadline(spark, sf_dir):
    parts, known = [], toy_system(spark, sf_dir)
    for t in DEADLINES:
        steps = [ceil(t / v) for v in SPEEDS]
        parts.append(toy_profile(spark, sf_dir, steps, known).groupBy("scheme").agg(F.avg("sse").alias("mse")).select("scheme", F.lit(t).alias("deadline"), F.round(F.log10("mse"), 6).alias("log_mse")))
    return reduce(lambda a, b: a.unionByName(b), parts)


QUERIES["mse_vs_deadline"] = (mse_vs_deadline, with_(
    _toy_ctes(), _coded_unroll(18), *[_profile_ctes([ceil(t / v) for v in SPEEDS], f"_{n}") for n, t in enumerate(DEADLINES)],
    select=" UNION ALL ".join(f"SELECT scheme, {t}::DOUBLE AS deadline, round(log10(avg(sse)), 6) AS log_mse FROM prof_{n} GROUP BY 1" for n, t in enumerate(DEADLINES)),
))


def measured_rate(spark, sf_dir):
    """Measured decay of the un-encoded error against what the step's factor predicts: exact on a bipartite graph."""
    inputs = materialise(graphs.in_segment(spark, sf_dir, PAIR), "inputs")
    system = walk(spark, sf_dir)
    forcing, start = materialise(system.forcing(inputs), "f"), materialise(systems.initial_state(system, [0, 1]), "s")
    shots = engine.snapshots(system, forcing, start, 2, [10, 14, 18, 22])
    truth = engine.solve_converged(system, inputs, 2, tol=1e-17)
    curve = reduce(lambda a, b: a.unionByName(b), [
        metrics.sse(shots[t], truth).select(F.lit(float(t)).alias("deadline"), F.col("sse").alias("mse")) for t in (10, 14, 18, 22)
    ])
    return metrics.measured_exponent(curve).select(F.round("exponent", 4).alias("exponent"))


QUERIES["measured_exponent"] = (measured_rate, with_(
    walk_ctes(), ranking_start(graphs.segment_sql(PAIR)), unroll(TRUTH),
    "c AS (" + " UNION ALL ".join(f"SELECT {t}.0 AS d, sum((a.v - b.v) * (a.v - b.v)) AS m FROM s{t} a JOIN s{TRUTH} b USING (i, p)" for t in (10, 14, 18, 22)) + ")",
    select="SELECT round(regr_slope(-ln(m), d), 4) AS exponent FROM c",
))
