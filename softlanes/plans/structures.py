"""Queries over graphs, operators, codes, lanes, costs and bounds."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform_sql
from softlanes.operators import codes, cost, decode, stragglers, theory
from softlanes.operators.encode_views import dft_gram, dft_table
from softlanes.operators.systems import nodes_of, normalise_columns
from softlanes.operators.weights import tau_geometric
from softlanes.plans.sqlgen import values
from softlanes.sources import graphs
from softlanes.sources.tables import load

QUERIES: dict = {}
TRACE = "2024-01-10"  # deadline of the lanes that come from events


def _edges(name, digits):
    def run(spark, sf_dir):
        return graphs.EDGES[name](spark, sf_dir).select("src", "dst", F.round("weight", digits).alias("weight"))

    return run, f"SELECT src, dst, round(weight, {digits}) AS weight FROM ({graphs.EDGE_SQL[name]})"


for _name, _digits in [("purchase", 6), ("purchase_weighted", 6), ("supply", 6), ("transition", 6), ("nation", 4), ("anchor", 6), ("knn", 6), ("random", 6)]:
    QUERIES[f"edges_{_name}"] = _edges(_name, _digits)


def _operator(graph, orientation, weighted):
    column, row = ("dst", "src") if orientation == "indegree" else ("src", "dst")
    top, total = ("weight", "sum(weight)") if weighted else ("1.0", "count(*)")

    def run(spark, sf_dir):
        return normalise_columns(graphs.EDGES[graph](spark, sf_dir), orientation, weighted).select("i", "j", F.round("w", 9).alias("w"))

    sql = f"SELECT {row} AS i, {column} AS j, round({top} / {total} OVER (PARTITION BY {column}), 9) AS w FROM ({graphs.EDGE_SQL[graph]})"
    return run, sql


QUERIES["normalised_operator_indegree"] = _operator("purchase", "indegree", False)
QUERIES["normalised_operator_outdegree"] = _operator("transition", "outdegree", False)
QUERIES["normalised_operator_weighted"] = _operator("nation", "indegree", True)


# ---- codes, each as it mixes the loads of the shares of all orders

def _gen(make):
    """``(p, q, re, im)``: what share p's load brings to lane q."""
    return lambda spark, sf_dir: _carried(spark, sf_dir, codes.to_df(spark, make()), len(make()))


def _carried(spark, sf_dir, gen, k):
    carried = lambda c: (F.round(F.col("v") * F.col(c), 9) + 0.0).alias(c)
    return graphs.in_load(spark, sf_dir, k).join(F.broadcast(gen), "p").select("p", "q", carried("re"), carried("im"))


def _gen_sql(n, k, entry):
    return f"SELECT p, q::INT AS q, round(v * ({entry[0]}), 9) + 0.0 AS re, round(v * ({entry[1]}), 9) + 0.0 AS im FROM ({graphs.load_sql(k)}) a, range({n}) b(q)"


def _entries(make):
    return lambda spark, sf_dir: codes.to_df(spark, make()).select("p", "q", F.round("re", 9).alias("re"), F.round("im", 9).alias("im"))


def _entries_sql(n, k, entry):
    return f"SELECT p::INT AS p, q::INT AS q, round({entry[0]}, 9) AS re, round({entry[1]}, 9) + 0.0 AS im FROM range({k}) a(p), range({n}) b(q)"


QUERIES["code_parity"] = (_gen(lambda: codes.parity_code(4)), _gen_sql(5, 4, ("CASE WHEN q = p OR q = 4 THEN 1.0::DOUBLE ELSE 0.0 END", "0.0::DOUBLE")))
QUERIES["code_identity"] = (_gen(lambda: codes.identity_code(5)), _gen_sql(5, 5, ("CASE WHEN q = p THEN 1.0::DOUBLE ELSE 0.0 END", "0.0::DOUBLE")))
QUERIES["code_twin"] = (_entries(lambda: codes.twin_code(12, 10)), _entries_sql(12, 10, ("CASE WHEN q = p OR (q >= 10 AND q - 10 = p) THEN 1.0::DOUBLE ELSE 0.0 END", "0.0::DOUBLE")))
QUERIES["code_dft"] = (
    lambda spark, sf_dir: _carried(spark, sf_dir, dft_table(spark, 12, 10, 15), 10),
    _gen_sql(12, 10, ("cos(2 * pi() * p * q / 12) / sqrt(12)", "-sin(2 * pi() * p * q / 12) / sqrt(12)")),
)
QUERIES["code_dft_gram"] = (
    lambda spark, sf_dir: dft_gram(spark, 12, 10, graphs.in_load(spark, sf_dir, 12).withColumnRenamed("p", "q")),
    f"""SELECT a::INT AS a, b::INT AS b, round(sum(v * cos(2 * pi() * (a - b) * p / 12)) / 12, 9) + 0.0 AS re
    FROM range(10) x(a), range(10) y(b), ({graphs.load_sql(12)}) z GROUP BY 1, 2""",
)


def code_reports(spark, sf_dir):
    """Properties of every family at (12, 10), and the median condition of the columns that were left to invert in practice:
    workers of the trace stand in teams of twelve, and of those of a team that have a lane the ten with most beats by the deadline are inverted."""
    own = stragglers.steps_from_events(load(spark, sf_dir, "events", "user_id", "ts"), TRACE)
    teams = own.groupBy(F.floor(F.col("q") / 12).alias("team")).agg(F.array_sort(F.collect_list(F.struct((-F.col("steps")).alias("s"), (F.col("q") % 12).alias("lane")))).alias("lanes"))
    fastest = lambda n: F.array_sort(F.slice(F.filter(F.transform("lanes", lambda x: x["lane"]), lambda q: q < n), 1, 10))
    sizes = F.explode(F.array(*[F.struct(F.lit(n).alias("n"), fastest(n).alias("lanes")) for n in (10, 11, 12)])).alias("x")
    seen = teams.select(sizes).where(F.size("x.lanes") == 10).groupBy("x.n", "x.lanes").agg(F.count("*").alias("teams")).collect()  # sets of ten lanes: at most 1 + 11 + 66
    made = {
        "dft": codes.dft_code(12, 10), "sign": codes.sign_code(12, 10, 1), "sparse": codes.sparse_code(12, 10, 0.3, 1), "gaussian": codes.gaussian_code(12, 10, 1),
        "parity": codes.parity_code(10), "hartley": codes.orthonormal_code(codes.hartley_matrix(12), 10), "identity": codes.identity_code(10), "twin": codes.twin_code(12, 10),
    }
    finite = lambda v: float(v) if np.isfinite(v) else None
    rows = []
    for name, g in made.items():
        r = codes.code_report(g)
        conds = [c for s in seen if s.n == g.shape[1] for c in [codes.condition(g, s.lanes)] * s.teams]
        rows.append((name, r["n"], r["rank"], r["orthonormal"], r["sigma_max"], r["s_min"], r["mds"], finite(r["median_cond"]), len(conds), finite(np.median(conds)) if conds else None))
    return spark.createDataFrame(rows, "code string, n int, rank int, orthonormal boolean, sigma_max double, s_min double, mds boolean, median_cond double, teams int, team_cond double")


QUERIES["code_reports"] = (code_reports, None)


# ---- lanes

def _u(seed):
    return hash_uniform_sql("q", str(seed))


def _lanes(run, steps_sql, speed_sql="NULL::DOUBLE", n=120):
    def go(spark, sf_dir):
        return run(spark).select("q", "steps", F.round("speed", 9).alias("speed"))

    return go, f"SELECT q::INT AS q, ({steps_sql})::INT AS steps, round({speed_sql}, 9) AS speed FROM range({n}) t(q)"


QUERIES["lane_exponential"] = _lanes(
    lambda s: stragglers.steps_from_speed(stragglers.exponential_speeds(s, 120, 1.0, 11), 20.0), f"ceil(20.0 / -ln(1 - {_u(11)}))", f"-ln(1 - {_u(11)})"
)
QUERIES["lane_startup_floor"] = _lanes(
    lambda s: stragglers.steps_from_speed(stragglers.exponential_speeds(s, 120, 2.0, 12, least=0.5), 20.0, "floor", 1.5),
    f"floor(18.5 / (0.5 - ln(1 - {_u(12)}) / 2))", f"0.5 - ln(1 - {_u(12)}) / 2",
)
QUERIES["lane_uniform"] = _lanes(lambda s: stragglers.uniform_steps(s, 120, 1, 20, 13), f"1 + floor({_u(13)} * 20)")
QUERIES["lane_two_point"] = _lanes(lambda s: stragglers.two_point_steps(s, 120, 5, 20, 0.5, 14), f"CASE WHEN {_u(14)} < 0.5 THEN 5 ELSE 20 END")
QUERIES["lane_table_law"] = _lanes(
    lambda s: stragglers.table_steps(s.createDataFrame([(2, 0.25), (7, 0.5), (19, 0.25)], "steps int, probability double"), 120, 15),
    f"CASE WHEN {_u(15)} < 0.25 THEN 2 WHEN {_u(15)} < 0.75 THEN 7 ELSE 19 END",
)
QUERIES["lane_from_events"] = (
    lambda spark, sf_dir: stragglers.steps_from_events(load(spark, sf_dir, "events", "user_id", "ts"), "2024-01-20").select("q", "steps"),
    "SELECT user_id::INT AS q, (count(*) FILTER (ts <= TIMESTAMP '2024-01-20'))::INT AS steps FROM events GROUP BY 1",
)
QUERIES["lane_order_stat"] = (
    lambda spark, sf_dir: stragglers.order_statistics(stragglers.exponential_speeds(spark, 120, 1.0, 11)).select("q", "place"),
    f"SELECT q::INT AS q, row_number() OVER (ORDER BY -ln(1 - {_u(11)}), q) AS place FROM range(120) t(q)",
)
QUERIES["lane_kth_fastest"] = (
    lambda spark, sf_dir: stragglers.kth_fastest(stragglers.exponential_speeds(spark, 120, 1.0, 11), 100).select("q", F.round("speed", 9).alias("speed")),
    f"SELECT q::INT AS q, round(-ln(1 - {_u(11)}), 9) AS speed FROM range(120) t(q) ORDER BY -ln(1 - {_u(11)}), q LIMIT 1 OFFSET 99",
)


# ---- bounds

RHO = 0.85
_UNIFORM = np.full(21, 1 / 20.0)
_UNIFORM[0] = 0.0


def _row(spark, *pairs):
    return spark.createDataFrame([(n, float(v)) for n, v in pairs], "name string, value double").select("name", F.round("value", 9).alias("value"))


def _steps(spark, n, seed):
    return stragglers.collected_steps(stragglers.uniform_steps(spark, n, 1, 20, seed))


def _tau_steps(n, seed):
    return f"(SELECT q, power({RHO}, 2.0 * (1 + floor({_u(seed)} * 20))) AS tau FROM range({n}) t(q))"


def _trace(spark, sf_dir, n):
    return stragglers.collected_steps(stragglers.team_steps(load(spark, sf_dir, "events", "user_id", "ts"), TRACE, n))


def _trace_sql(n):
    """``(q, l)``: steps of the teams, by the table of weights at most twenty."""
    return f"""(SELECT (q % {n})::INT AS q, least(20, min(l)) AS l FROM (SELECT user_id AS q, count(*) FILTER (ts <= TIMESTAMP '{TRACE}') AS l FROM events GROUP BY 1) GROUP BY 1)"""


def _tau_trace(n):
    return f"(SELECT q, power({RHO}, 2.0 * l) AS tau FROM {_trace_sql(n)})"


QUERIES["bound_uncoded"] = (
    lambda spark, sf_dir: _row(spark, ("uncoded", theory.uncoded_mse(tau_geometric(RHO, 20), _trace(spark, sf_dir, 10)))),
    f"SELECT 'uncoded' AS name, round(sum(tau), 9) AS value FROM {_tau_trace(10)}",
)
QUERIES["bound_coded_parity"] = (
    lambda spark, sf_dir: _row(spark, ("coded", theory.coded_bound(codes.parity_code(2), tau_geometric(RHO, 20), _trace(spark, sf_dir, 3)))),
    f"""WITH w AS (SELECT 1 / max(tau) FILTER (q = 0) AS a, 1 / max(tau) FILTER (q = 1) AS b, 1 / max(tau) FILTER (q = 2) AS c FROM {_tau_trace(3)})
    SELECT 'coded' AS name, round(3.0 * (a + b + 2 * c) / ((a + c) * (b + c) - c * c), 9) AS value FROM w""",
)


def schur_of_trace(spark, sf_dir):
    steps, tau, g = _trace(spark, sf_dir, 6), tau_geometric(RHO, 20), codes.dft_code(6, 5)
    return _row(spark, ("schur", theory.schur_bound(g, tau, steps)), ("direct", theory.coded_bound(g, tau, steps)))


QUERIES["bound_schur_one_spare"] = (
    schur_of_trace,
    f"""WITH m AS (SELECT avg(tau) AS m1, avg(tau * tau) AS m2 FROM {_tau_trace(6)}), b AS (SELECT 5 * m1 - (m2 - m1 * m1) / m1 AS v FROM m)
    SELECT 'schur' AS name, round(v, 9) AS value FROM b UNION ALL SELECT 'direct', round(v, 9) FROM b""",
)
# Inputs with a common part, parity code: sigma times the own weights, plus u uT with u = (G'alpha) * rho^l.
_ALPHA, _BETA, _STOPS = (1.0, 0.5), (2.0, 1.0), (4, 2, 6)


def _scaled_weights(stops=_STOPS) -> np.ndarray:
    own, l = tau_geometric(RHO, 20), np.minimum(stops, 20)
    return decode.correlated_weights(codes.parity_code(2), own[l], 0.3 * RHO ** (l[:, None] + l[None, :]), _ALPHA, _BETA)


_SCALED_CTES = f"""b AS (SELECT pow({_BETA[0]}, 2) AS x, pow({_BETA[1]}, 2) AS y), s AS (SELECT x + y + sqrt(pow(x - y, 2) + x * y) AS sigma FROM b),
    w AS (SELECT q, sigma * pow({RHO}, 2.0 * l) AS d, sqrt(0.3) * h * pow({RHO}, l) AS u FROM l, s)"""
_SCALED_SQL = f"""l AS (SELECT * FROM (VALUES (0, {_STOPS[0]}, {_ALPHA[0]}), (1, {_STOPS[1]}, {_ALPHA[1]}), (2, {_STOPS[2]}, {_ALPHA[0] + _ALPHA[1]})) t(q, l, h)),
    {_SCALED_CTES}"""
QUERIES["weights_scaled_common"] = (
    lambda spark, sf_dir: spark.createDataFrame([(a, b, float(v)) for (a, b), v in np.ndenumerate(_scaled_weights())], "a int, b int, v double").select("a", "b", F.round("v", 9).alias("v")),
    f"WITH {_SCALED_SQL} SELECT m.q::INT AS a, n.q::INT AS b, round(m.u * n.u + CASE WHEN m.q = n.q THEN m.d ELSE 0 END, 9) AS v FROM w m, w n",
)
QUERIES["bound_correlated"] = (
    lambda spark, sf_dir: _row(spark, ("correlated", theory.coded_bound_correlated(codes.parity_code(2), _scaled_weights(_trace(spark, sf_dir, 3))))),
    f"""WITH l AS (SELECT q, l, h FROM {_trace_sql(3)} JOIN (VALUES (0, {_ALPHA[0]}), (1, {_ALPHA[1]}), (2, {_ALPHA[0] + _ALPHA[1]})) t(q, h) USING (q)), {_SCALED_CTES}, c AS (SELECT 1 + sum(u * u / d) AS c FROM w),
    inv AS (SELECT m.q AS a, n.q AS b, (CASE WHEN m.q = n.q THEN 1 / m.d ELSE 0 END) - m.u * n.u / (m.d * n.d * c) AS v FROM w m, w n, c),
    e AS (SELECT sum(v) FILTER (a IN (0, 2) AND b IN (0, 2)) AS p, sum(v) FILTER (a IN (1, 2) AND b IN (1, 2)) AS s, sum(v) FILTER (a IN (0, 2) AND b IN (1, 2)) AS r FROM inv)
    SELECT 'correlated' AS name, round((p + s) / (p * s - r * r), 9) AS value FROM e""",
)
_LAW = f"(SELECT l, power({RHO}, 2.0 * l) AS tau FROM range(1, 21) t(l))"
QUERIES["replication_floor"] = (
    lambda spark, sf_dir: _row(spark, ("floor", theory.replication_lower_bound(tau_geometric(RHO, 20), _UNIFORM, 120, 100))),
    f"SELECT 'floor' AS name, round(80 * (SELECT avg(tau) FROM {_LAW}), 9) AS value",
)
QUERIES["heavy_tail"] = (
    lambda spark, sf_dir: _row(
        spark, ("rho", theory.heavy_tail_rho(tau_geometric(RHO, 20), _UNIFORM)), ("gain", theory.asymptotic_gain(tau_geometric(RHO, 20), _UNIFORM))
    ),
    f"SELECT 'rho' AS name, round(var_pop(tau) / (avg(tau) * avg(tau)), 9) AS value FROM {_LAW} UNION ALL SELECT 'gain', round(var_pop(tau) / avg(tau), 9) FROM {_LAW}",
)


def exponents(spark, sf_dir):
    lanes = stragglers.exponential_speeds(spark, 120, 1.0, 24, least=0.5).orderBy("q").collect()
    coded, plain = theory.error_exponents([r.speed for r in lanes], 120, 100, RHO)
    return _row(spark, ("coded", coded), ("uncoded", plain))


QUERIES["exponents"] = (
    exponents,
    f"""WITH s AS (SELECT q, 0.5 - ln(1 - {_u(24)}) AS v FROM range(120) t(q)), o AS (SELECT v, row_number() OVER (ORDER BY v, q) AS place FROM s)
    SELECT 'coded' AS name, round(2 * ln(1 / {RHO}) / (SELECT v FROM o WHERE place = 100), 9) AS value
    UNION ALL SELECT 'uncoded', round(2 * ln(1 / {RHO}) / (SELECT max(v) FROM s WHERE q < 100), 9)""",
)
QUERIES["p_unprotected"] = (
    lambda spark, sf_dir: spark.createDataFrame([(n, k, theory.p_slowest_unprotected(n, k)) for n, k in [(120, 100), (12, 10), (15, 10), (240, 200)]], "n int, k int, value double").select("n", "k", F.round("value", 9).alias("value")),
    f"SELECT n::INT AS n, k::INT AS k, round((2.0 * k - n) / k, 9) AS value FROM ({values([(120, 100), (12, 10), (15, 10), (240, 200)], 'n, k')})",
)


def toeplitz(spark, sf_dir):
    w = np.array([0.85 ** (2.0 * s) for s in _steps(spark, 8, 25)])
    t = theory.toeplitz_of_tau(w)
    rows = [(a, b, float(t[a, b].real), float(t[a, b].imag)) for a in range(8) for b in range(8)]
    return spark.createDataFrame(rows, "a int, b int, re double, im double").select("a", "b", (F.round("re", 9) + 0.0).alias("re"), (F.round("im", 9) + 0.0).alias("im"))


QUERIES["toeplitz_entries"] = (
    toeplitz,
    f"""SELECT a::INT AS a, b::INT AS b, round(sum(tau * cos(2 * pi() * (a - b) * q / 8)) / 8, 9) + 0.0 AS re, round(-sum(tau * sin(2 * pi() * (a - b) * q / 8)) / 8, 9) + 0.0 AS im
    FROM {_tau_steps(8, 25)}, range(8) x(a), range(8) y(b) GROUP BY 1, 2""",
)


def concentration(spark, sf_dir):
    r = theory.concentration_report(tau_geometric(RHO, 20), _UNIFORM, 60, 50)
    return spark.createDataFrame(sorted((k, float(v)) for k, v in r.items()), "name string, value double")


QUERIES["concentration"] = (concentration, None)


# ---- costs

def _costs(spark, sf_dir):
    edges = graphs.purchase(spark, sf_dir)
    return edges.select(F.col("src").alias("i"), F.col("dst").alias("j")), nodes_of(edges)


def cost_lane(spark, sf_dir):
    op, nodes = _costs(spark, sf_dir)
    return cost.lane_cost(op, nodes, stragglers.uniform_steps(spark, 12, 1, 20, 26), codes.dft_code(12, 10)).select("metric", "lane", F.round("value", 6).alias("value"))


_SIZE = f"(SELECT count(*)::DOUBLE AS e FROM ({graphs.EDGE_SQL['purchase']})) x, (SELECT count(*)::DOUBLE AS n FROM (SELECT DISTINCT src FROM ({graphs.EDGE_SQL['purchase']}))) y"
_COLUMNS = "CASE WHEN q IN (0, 6) THEN 1.0 ELSE 2.0 END"
QUERIES["cost_lane"] = (
    cost_lane,
    f"""WITH b AS (SELECT q::INT AS lane, 1 + floor({_u(26)} * 20) AS s, {_COLUMNS} AS c, e, n FROM range(12) t(q), {_SIZE})
    SELECT 'sparse_operations' AS metric, lane, round((2 * e * s * c)::DOUBLE, 6) AS value FROM b UNION ALL SELECT 'dense_operations', lane, round((n * n * s * c)::DOUBLE, 6) FROM b
    UNION ALL SELECT 'values_in', lane, round((n * c)::DOUBLE, 6) FROM b UNION ALL SELECT 'values_out', lane, round((n * c)::DOUBLE, 6) FROM b
    UNION ALL SELECT 'operations_per_value', lane, round((s * e / n)::DOUBLE, 6) FROM b""",
)
QUERIES["cost_ratio"] = (
    lambda spark, sf_dir: cost_lane(spark, sf_dir).where("metric = 'operations_per_value'").agg(F.round(F.avg("value"), 6).alias("operations_per_value")),
    f"WITH b AS (SELECT 1 + floor({_u(26)} * 20) AS s, e, n FROM range(12) t(q), {_SIZE}) SELECT round(avg(round((s * e / n)::DOUBLE, 6)), 6) AS operations_per_value FROM b",
)


def cost_encode_decode(spark, sf_dir):
    n = _costs(spark, sf_dir)[1].count()
    return cost.encode_decode_cost(spark, n, codes.parity_code(10)).select("metric", "value")


QUERIES["cost_encode_decode"] = (
    cost_encode_decode,
    f"""WITH b AS (SELECT n FROM {_SIZE}) SELECT 'encode' AS metric, 2.0 * 110 * n AS value FROM b UNION ALL SELECT 'decode', 110.0 * n FROM b
    UNION ALL SELECT 'decode_matrix', 1000.0 + 1100.0 FROM b UNION ALL SELECT 'encode_decode_order', 110.0 * n FROM b""",
)
QUERIES["cost_weights"] = (
    lambda spark, sf_dir: cost.weight_cost(spark, 1000, 100, 10, 64).select("metric", "value"),
    "SELECT 'probe_solves' AS metric, 2.0 * 1000 * 100 * 10 AS value UNION ALL SELECT 'tau_sweep', 2.0 * 1000 * 64 * 10 UNION ALL SELECT 'psi_products', 10.0 * 65 * 65 * 100",
)
