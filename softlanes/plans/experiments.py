"""The experiment workloads on the given tables. Rows carry mean squared error for each problem and each entry."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform
from softlanes.operators import codes, cost, decode, engine, halves, metrics, pieces, scoring, systems, theory, weights
from softlanes.operators.stragglers import draw_steps
from softlanes.plans import accuracy, ranking, sqlgen
from softlanes.sources import graphs
from softlanes.sources.session import materialise, release
from softlanes.sources.tables import load

QUERIES: dict = {}
PROBES = 10
TOL, CONVERGE = 1e-17, 400
FAMILIES = {
    "dft": lambda n, k: codes.dft_code(n, k), "sign": lambda n, k: codes.sign_code(n, k, 1),
    "sparse": lambda n, k: codes.sparse_code(n, k, 0.1, 1), "gaussian": lambda n, k: codes.gaussian_code(n, k, 1),
}


class Bench:
    """One graph and input law: weights from probes, and scores of plans over problems run once.

    The graph goes in pieces where its components fit tasks, and no residual is written. Else residual blocks are.
    ``inputs`` hold ``columns`` problems that plans use, then the probes.
    """

    def __init__(self, spark, sf_dir, graph, inputs, k, most, probes=PROBES, columns=None):
        self.k, self.most, self.columns = k, most, columns or k
        every = self.columns + probes
        edges = materialise(graphs.EDGES[graph](spark, sf_dir), "edges")
        self.cut = pieces.cut(edges, ranking.D, inputs, halves.cut if probes else None)
        if self.cut is not None:
            release(edges)
            self.n_nodes = self.cut.n_nodes
            self.tau = self.cut.tau(list(range(self.columns, every)), most, TOL, CONVERGE) if probes else None
        else:
            system = ranking.walk_of(edges, graph)
            table = graphs.in_hash(system.nodes, inputs.k, inputs.seed, inputs.power) if isinstance(inputs, pieces.HashInputs) else inputs.where(F.col("p") < every)
            self.n_nodes, self.problems = system.nodes.count(), every
            self.blocks = scoring.error_blocks(system, table, every, most)
            self.tau = scoring.moments(self.blocks, every, most, list(range(self.columns, every)))[0] if probes else None

    def profile(self, plans, names) -> DataFrame:
        if self.cut is not None:
            return scoring.labelled(self.cut.score(self.columns, self.most, plans, TOL, CONVERGE), plans, names)
        return scoring.score(self.blocks, self.problems, self.most, plans, names)

    def scores(self, plans, names) -> DataFrame:
        return mean_scores(self.profile(plans, names), names, self.n_nodes)


def mean_scores(profile: DataFrame, names: list[str], n_nodes: int) -> DataFrame:
    """Mean and median over draws of the error for each problem, and its mean for each entry."""
    by = [n for n in names if n != "draw"]
    draw = profile.groupBy(*names).agg(F.avg("sse").alias("mse"))
    return draw.groupBy(*by).agg(F.avg("mse").alias("mse_problem"), F.median("mse").alias("median_mse"), (F.avg("mse") / n_nodes).alias("mse_entry"))


def supply_bench(spark, sf_dir, k=100, most=40):
    return Bench(spark, sf_dir, "supply", pieces.HashInputs(k + PROBES), k, most)


def purchase_bench(spark, sf_dir, k=100, most=40):
    return Bench(spark, sf_dir, "purchase", materialise(graphs.in_taste(spark, sf_dir, k + PROBES), "taste"), k, most)


def random_bench(spark, k=200, most=20):
    return Bench(spark, "", "random", pieces.HashInputs(k + PROBES), k, most)


def deadline_curve(bench, n, law="shifted", deadlines=(5.0, 10.0, 20.0, 40.0), draws=4, schemes=("uncoded", "twins_best", "twins_weighted", "soft")):
    g = codes.dft_code(n, bench.k)
    plans = []
    for t in deadlines:
        for d in range(draws):
            plans += scoring.scheme_plans(g, draw_steps(law, n, 100 + d, t), bench.tau, (t, d), schemes)
    return bench.scores(plans, ["scheme", "deadline", "draw"])


def x1(spark, sf_dir):
    """Error against the deadline, smaller graph: 100 problems, 120 lanes, Fourier code."""
    return deadline_curve(supply_bench(spark, sf_dir), 120)


def x2(spark, sf_dir):
    """Error against the deadline, larger graph."""
    return deadline_curve(purchase_bench(spark, sf_dir), 120)


def x3(spark, sf_dir):
    """Soft decoding against inverting the fastest k lanes."""
    return deadline_curve(purchase_bench(spark, sf_dir, most=20), 120, "uniform", (20.0,), 4, ("soft", "fastest_k", "uncoded"))


def x4(spark, sf_dir):
    """Four code families, smaller graph."""
    bench = supply_bench(spark, sf_dir, most=20)
    plans = []
    for name, make in FAMILIES.items():
        g = make(120, 100)
        for d in range(4):
            plans += scoring.scheme_plans(g, draw_steps("uniform", 120, 100 + d), bench.tau, (name, d), ("soft", "uncoded"))
    return bench.scores(plans, ["scheme", "code", "draw"])


def x5(spark, sf_dir):
    """Correlated inputs, smaller graph: the plain decoder and the one for a common part, whose cross moments come from
    probes of the common part alone."""
    k, most = 100, 20
    tastes = materialise(graphs.in_taste(spark, sf_dir, k + PROBES), "taste")
    topics = materialise(graphs.in_topics(spark, sf_dir, 1 + PROBES), "topics")
    # problem p is a mix of its taste, column p, and the batch's own topic, column k: both are run once; probes of both kinds follow
    behind = lambda inputs, first, to: inputs.where(F.col("p") >= first).select("i", (F.col("p") + (to - first)).alias("p"), "v")
    columns = tastes.where(F.col("p") < k).unionByName(behind(topics, 0, k).where(F.col("p") == k))
    columns = columns.unionByName(behind(tastes, k, k + 1)).unionByName(behind(topics, 1, k + 1 + PROBES))
    bench = Bench(spark, sf_dir, "supply", materialise(columns, "columns"), k, most, probes=0, columns=k + 1)
    if bench.cut is not None:
        own, common = ([k + 1 + kind * PROBES + n for n in range(PROBES)] for kind in (0, 1))
        moments = bench.cut.moments(own, common, most, TOL, CONVERGE)
        weights_of = lambda rho: weights.mixed_weights(moments, PROBES, rho)
    else:
        system = ranking.walk(spark, sf_dir, "supply")
        own = materialise(weights.error_probes(system, behind(tastes, k, 0), PROBES), "own-probes")
        common = materialise(weights.error_probes(system, behind(topics, 1, 0), PROBES), "common-probes")
        weights_of = lambda rho: weights.stationary_weights(system, own, common, rho, most)
    g, plans = codes.dft_code(120, k), []
    for rho in (0.0, 0.5, 0.8):
        spread, psi = weights_of(rho)
        tau, mix = spread + np.diag(psi), np.vstack([(1 - rho) * np.eye(k), np.full((1, k), rho)])
        for d in range(3):
            drawn = scoring.scheme_plans(g, draw_steps("uniform", 120, 100 + d), tau, (rho, d), ("uncoded", "twins_best", "soft", "soft_correlated"), spread, psi)
            plans += [replace(p, mix=mix) for p in drawn]
    return bench.scores(plans, ["scheme", "rho", "draw"])


def x6(spark, sf_dir):
    """Error of every problem on the random graph, one draw; peaks against averages."""
    bench = random_bench(spark)
    plans = scoring.scheme_plans(codes.dft_code(240, 200), draw_steps("uniform", 240, 100), bench.tau, (), ("uncoded", "twins_best", "soft"))
    profile = materialise(bench.profile(plans, ["scheme"]), "profile")
    return profile.join(metrics.peak_to_average(profile, "scheme").select("scheme", "ratio"), "scheme")


def x7(spark, sf_dir):
    """Average error under three laws of speed, all schemes; the literal decoder beside the stable one."""
    bench = random_bench(spark)
    g, plans = codes.dft_code(240, 200), []
    for law in ("exponential", "uniform", "two_point"):
        for d in range(3):
            plans += scoring.scheme_plans(g, draw_steps(law, 240, 100 + d, 10.0), bench.tau, (law, d),
                                          ("uncoded", "twins_best", "twins_weighted", "twins_inverse_mse", "soft", "soft_literal", "fastest_k", "no_straggler"))
    return bench.scores(plans, ["scheme", "law", "draw"])


def x8(spark, sf_dir):
    """Speed over time of every worker: how straight its count of iterations runs."""
    from pyspark.sql import Window

    e = load(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")) / 1e6)
    done = F.count("*").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).cast("double")
    t0 = 1704067200.0
    return e.select("user_id", (F.col("s") - t0).alias("s"), done.alias("n")).groupBy("user_id").agg(
        F.round(F.regr_r2("n", "s"), 6).alias("r2"), F.round(F.regr_slope("n", "s") * 86400, 6).alias("per_day"))


def x9(spark, sf_dir, n: int = 12, k: int = 10):
    """Time and Spark's counters of encoding, iterating and decoding ``n`` lanes on the larger graph: not reproducible."""
    g = codes.dft_code(n, k)
    inputs = materialise(graphs.in_taste(spark, sf_dir, k), "taste")
    system, counters = ranking.walk(spark, sf_dir), cost.PhaseCounters(spark)
    with counters.phase("encode"):
        forcing = materialise(system.forcing(engine.encode_columns(inputs, g)), "forcing")
        start = materialise(engine.encode_columns(systems.initial_state(system, list(range(k))), g), "start")
    _, owner = codes.real_columns(g)
    steps = draw_steps("uniform", n, 100).tolist()
    with counters.phase("iterate"):
        state = materialise(engine.run_lanes(system, forcing, start, [steps[q] for q in owner]), "lanes")
    with counters.phase("decode"):
        materialise(decode.soft_decode(state, g, steps, weights.tau_geometric(0.85, 20)), "decoded")
    return counters.table()


def x16(spark, sf_dir, deadline_s: float = 3.0, n: int = 12, k: int = 10):
    """A run against the clock: lanes iterate on the larger graph until the deadline, then what they have is decoded.
    Steps of the slowest and fastest lane, and how much of the time went into encoding and decoding: not reproducible."""
    g = codes.dft_code(n, k)
    inputs = materialise(graphs.in_taste(spark, sf_dir, k), "taste")
    system, counters = ranking.walk(spark, sf_dir), cost.PhaseCounters(spark)
    with counters.phase("encode"):
        forcing = materialise(system.forcing(engine.encode_columns(inputs, g)), "forcing")
        start = materialise(engine.encode_columns(systems.initial_state(system, list(range(k))), g), "start")
    m, owner = codes.real_columns(g)
    with counters.phase("iterate"):
        ran = engine.run_until(system, forcing, start, m.shape[1], deadline_s)
    steps = [min(s for s, o in zip(ran.steps, owner) if o == q) for q in range(n)]
    with counters.phase("decode"):
        found = materialise(decode.soft_decode(ran.state, g, steps, weights.tau_geometric(0.85, max(steps))), "decoded")
    error = metrics.residual(system, found.select("i", "p", "v"), system.forcing(inputs)).agg(F.avg("residual")).first()[0]
    seconds = {r[0]: r[1] for r in counters.rows}
    share = (seconds["encode"] + seconds["decode"]) / sum(seconds.values())
    updates = system.op.count() * sum(ran.steps)
    row = (deadline_s, min(steps), max(steps), seconds["encode"], seconds["iterate"], seconds["decode"], share, updates / seconds["iterate"], error)
    return spark.createDataFrame([row], "deadline_s double, fewest_steps int, most_steps int, encode_s double, iterate_s double, decode_s double, "
                                 "overhead_share double, edge_updates_per_s double, residual_problem double")


def x11(spark, sf_dir):
    """Ridge problems for ten labels on twelve lanes."""
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    rows = e.select(F.col("vec_id").alias("row"), F.posexplode("embedding").alias("col", "v0")).select("row", "col", F.col("v0").cast("double").alias("v"))
    s = systems.ridge_system(rows, 1.0, min(0.02, systems.safe_step(rows, 1.0)))  # more vectors need shorter steps
    s = systems.AffineSystem(materialise(s.op, "op"), s.drive, materialise(s.nodes, "nodes"))
    bench_blocks = scoring.error_blocks(s, graphs.in_onehot(spark, sf_dir), 10, 20, 0.0, converge=4000)
    tau, _, _ = scoring.moments(bench_blocks, 10, 20, list(range(10)))
    plans = []
    for d in range(4):
        plans += scoring.scheme_plans(codes.dft_code(12, 10), draw_steps("two_point", 12, 100 + d), tau, (d,), ("uncoded", "twins_best", "soft"))
    return scoring.score(bench_blocks, 10, 20, plans, ["scheme", "draw"]).groupBy("scheme").agg(F.avg("sse").alias("mse_problem"))


def x12(spark, sf_dir):
    """Exponents: measured slopes of the error over the deadline beside the predicted ones, 100 problems on 120 lanes."""
    bench = purchase_bench(spark, sf_dir, most=60)
    speeds = np.array([1 + 0.5 * -np.log1p(-u) for u in [_u(q) for q in range(120)]])
    plans = []
    for t in (10.0, 20.0, 30.0, 40.0, 50.0, 60.0):
        plans += scoring.scheme_plans(codes.dft_code(120, 100), np.ceil(t / speeds).astype(int), bench.tau, (t,), ("uncoded", "twins_best", "soft"))
    curve = bench.profile(plans, ["scheme", "deadline"]).groupBy("scheme", "deadline").agg(F.avg("sse").alias("mse"))
    coded, plain = theory.error_exponents(speeds, 120, 100, 0.85)
    predicted = spark.createDataFrame([("soft", coded), ("uncoded", plain), ("twins_best", plain)], "scheme string, predicted double")
    return metrics.measured_exponent(curve, "scheme").join(predicted, "scheme")


def _u(q, seed=77):
    from softlanes.functions.hashing import hash_uniform_value

    return hash_uniform_value(q, seed)


def x13(spark, sf_dir, draws: int = 40):
    """Gain of each spare lane as lanes grow, against the limit and against what replication can save; draws are tasks."""
    law = np.zeros(21)
    law[5], law[20] = 0.1, 0.9
    tau = weights.tau_geometric(0.85, 20)
    value = tau[[5, 20]]

    def work(batches):
        for pdf in batches:
            gains = []
            for n, d in zip(pdf["n"], pdf["draw"]):
                spare = int(n**0.4)
                h = np.exp(-2j * np.pi * np.outer(np.arange(n - spare, n), np.arange(n)) / n) / np.sqrt(n)
                w = np.random.default_rng([4, n, d]).choice(value, size=n, p=[0.1, 0.9])
                j4 = (h * w) @ h.conj().T
                gains.append(float(np.trace(np.linalg.solve(j4, (h * w**2) @ h.conj().T - j4 @ j4)).real) / spare)
            yield pdf.assign(gain=gains)[["n", "gain"]]

    sizes = [32, 64, 128, 256, 512, 1024]
    every = spark.createDataFrame([(n, d) for n in sizes for d in range(draws)], "n int, draw int").repartition(2 * len(sizes), "n", "draw")
    known = spark.createDataFrame([(n, n - int(n**0.4), theory.asymptotic_gain(tau, law), float(law @ tau), theory.heavy_tail_rho(tau, law)) for n in sizes],
                                  "n int, k int, limit double, replication_at_most double, rho double")
    gains = every.mapInPandas(work, "n int, gain double").groupBy("n").agg(F.avg("gain").alias("gain_per_spare"))
    return gains.join(F.broadcast(known), "n").select("n", "k", "gain_per_spare", "limit", "replication_at_most", "rho")


def x14(spark, sf_dir):
    """Monte-Carlo weights against exact ones on the transition graph: error by number of probes, and its bound."""
    system = ranking.walk(spark, sf_dir, "transition")
    n, norms = system.nodes.count(), weights.power_norms(system, 3)
    exact = norms / 12  # uniforms on (-1/2, 1/2) are independent, of variance 1/12
    fourth = n / 80 + n * (n - 1) / 144  # mean fourth power of the norm of n of them
    out = []
    for m in (1, 10, 100):
        ps = F.broadcast(spark.range(m).select(F.col("id").cast("int").alias("p")))
        probes = system.nodes.crossJoin(ps).select("i", "p", (hash_uniform(F.col("i"), F.col("p"), 9) - 0.5).alias("v"))
        got = weights.table_of(weights.tau_monte_carlo(system, probes, 3))
        out += [(m, l, float(got[l]), float(exact[l]), float(norms[l] ** 2 * fourth / m)) for l in range(4)]
    return spark.createDataFrame(out, "probes int, l int, value double, exact double, variance_bound double")


def x15(spark, sf_dir):
    """Graceful degradation: error as slow lanes go from none to all."""
    bench = purchase_bench(spark, sf_dir, most=20)
    g, plans = codes.dft_code(120, 100), []
    for p in (0.0, 0.1, 0.25, 0.5, 1.0):
        for d in range(2):
            plans += scoring.scheme_plans(g, draw_steps("two_point", 120, 100 + d, p_slow=p), bench.tau, (p, d), ("uncoded", "twins_best", "soft", "fastest_k"))
    return bench.scores(plans, ["scheme", "p_slow", "draw"])


# ---- the same schemes on two problems and three lanes, where SQL can follow every one of them

def toy_scores(spark, sf_dir, sets: dict[str, list[int]], graph: str = "purchase"):
    """``(setting, scheme, log_mse)`` of each set of step counts, by the scoring that the experiments use."""
    inputs = materialise(graphs.in_segment(spark, sf_dir, ranking.PAIR) if graph == "purchase" else graphs.in_taste(spark, sf_dir, 2), "inputs")
    most = max(map(max, sets.values()))
    bench = Bench(spark, sf_dir, graph, inputs, 2, most, probes=0)
    tau, g, plans = weights.tau_geometric(ranking.RHO, most), codes.parity_code(2), []
    for name, steps in sets.items():
        plans += scoring.scheme_plans(g, np.array(steps), tau, (name,))
    profile = bench.profile(plans, ["scheme", "setting"])
    return profile.groupBy("setting", "scheme").agg(F.round(F.log10(F.avg("sse")), 6).alias("log_mse"))


def toy_sql(sets: dict[str, list[int]], graph: str = "purchase") -> str:
    own = graphs.segment_sql(ranking.PAIR) if graph == "purchase" else graphs.taste_sql(2)
    parts = [accuracy._profile_ctes(steps, f"_{n}") for n, steps in enumerate(sets.values())]
    rows = [f"SELECT '{name}' AS setting, scheme, round(log10(avg(sse)), 6) AS log_mse FROM prof_{n} GROUP BY 2" for n, name in enumerate(sets)]
    return sqlgen.with_(accuracy._toy_ctes(own, graph), accuracy._coded_unroll(max(map(max, sets.values()))), *parts, select=" UNION ALL ".join(rows))


_LANE_SPEEDS = [1.5, 3.0, 1.0]
TOYS = {
    "x1_toy_deadlines_smaller": ({f"deadline {t}": [int(np.ceil(t / v)) for v in _LANE_SPEEDS] for t in (6, 12, 18)}, "supply"),
    "x3_toy_fastest_k": ({f"draw {d}": draw_steps("uniform", 3, 100 + d).tolist() for d in range(4)}, "purchase"),
    "x7_toy_laws": ({law: draw_steps(law, 3, 100, 10.0).tolist() for law in ("exponential", "uniform", "two_point")}, "purchase"),
    "x15_toy_degradation": ({f"{slow} slow": [5] * slow + [20] * (3 - slow) for slow in range(4)}, "purchase"),
}
X8_SQL = """WITH c AS (SELECT user_id, epoch_us(ts) / 1e6 - 1704067200.0 AS s, (count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING))::DOUBLE AS n FROM events)
    SELECT user_id, round(regr_r2(n, s), 6) AS r2, round(regr_slope(n, s) * 86400, 6) AS per_day FROM c GROUP BY 1"""
QUERIES = {
    "x1_deadline_smaller": (x1, None), "x2_deadline_larger": (x2, None), "x3_fastest_k": (x3, None), "x4_codes": (x4, None), "x5_correlated": (x5, None),
    "x6_profile": (x6, None), "x7_laws": (x7, None), "x8_speed": (x8, X8_SQL), "x9_overhead": (x9, None), "x11_ridge": (x11, None),
    "x16_clock": (x16, None), "x12_exponents": (x12, None), "x13_heavy_tail": (x13, None), "x14_tau_quality": (x14, None), "x15_degradation": (x15, None),
}
QUERIES |= {name: (lambda spark, sf_dir, a=args: toy_scores(spark, sf_dir, *a), toy_sql(*args)) for name, args in TOYS.items()}
