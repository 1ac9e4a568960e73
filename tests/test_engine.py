"""Systems, layouts and schemes on Spark, against dense numpy."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from softlanes import schemas
from softlanes.operators import baselines, codes, decode, engine, metrics, scoring, stragglers, systems, weights
from softlanes.plans import catalogue, ranking
from softlanes.sources import graphs, tables
from softlanes.sources.session import materialise


def frame(df, k=None):
    pdf = df.select("i", "p", "v").toPandas()
    return pdf.pivot_table(index="i", columns="p", values="v", aggfunc="sum", fill_value=0.0)


@pytest.fixture(scope="module")
def ring(spark):
    edges = [(a, (a + 1) % 8, 1.0) for a in range(8)] + [(a, (a + 3) % 8, 1.0) for a in range(8)] + [(0, 4, 1.0)]
    return materialise(spark.createDataFrame(edges, schemas.EDGE), "ring")


@pytest.fixture(scope="module")
def inputs(spark):
    return materialise(spark.createDataFrame([(0, 0, 1.0), (3, 1, 0.5), (5, 1, 0.5)], "i long, p int, v double"), "inputs")


def dense_walk(system, inputs, steps, k=2):
    ids, b = systems.dense(system.op)
    f = 0.15 * frame(inputs).reindex(index=ids, columns=range(k), fill_value=0.0).to_numpy()
    x = np.full((len(ids), k), 1 / len(ids))
    for _ in range(steps):
        x = b @ x + f
    return ids, b, f, x


@pytest.mark.parametrize("layout", ["long", "wide", "lane", "block"])
def test_layouts_agree(spark, ring, inputs, layout):
    system = systems.restart_walk_system(ring)
    g, steps = codes.dft_code(3, 2), [4, 0, 6]
    m, owner = codes.real_columns(g)
    got = frame(engine.run_lanes(system, system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(systems.initial_state(system, [0, 1]), g), [steps[q] for q in owner], layout))
    for c, q in enumerate(owner):
        ids, _, _, x = dense_walk(system, inputs, steps[q])
        assert np.allclose(got.reindex(index=ids, columns=[c], fill_value=0.0)[c], x @ m[:, c], atol=1e-12), (layout, c)


def test_snapshots_mix_to_lanes(spark, ring, inputs):
    system = systems.restart_walk_system(ring)
    g, steps = codes.parity_code(2), [4, 2, 6]
    forcing, start = system.forcing(inputs), systems.initial_state(system, [0, 1])
    mixed = frame(engine.lanes_from_snapshots(engine.snapshots(system, forcing, start, 2, steps), g, steps))
    direct = frame(engine.run_lanes(system, system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(start, g), steps, "lane"))
    assert np.allclose(mixed, direct, atol=1e-12)


def test_converged_lanes_decode_exactly_and_mass_is_one(spark, ring, inputs):
    system = systems.restart_walk_system(ring)
    truth = frame(engine.solve_converged(system, inputs, 2))
    ids, b, f, _ = dense_walk(system, inputs, 0)
    assert np.allclose(truth, np.linalg.solve(np.eye(len(ids)) - b, f), atol=1e-10)
    assert np.allclose(truth.sum(), 1, atol=1e-10)
    g, steps = codes.dft_code(3, 2), [250] * 3
    _, owner = codes.real_columns(g)
    state = engine.run_lanes(system, system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(systems.initial_state(system, [0, 1]), g), [250] * len(owner), "lane")
    est = decode.soft_decode(state, g, steps, weights.tau_geometric(0.85, 250))
    assert np.allclose(frame(est), truth, atol=1e-9)
    assert est.agg(F.max(F.abs("im_leak"))).first()[0] < 1e-9


def test_conventions_and_dangling(spark):
    edges = spark.createDataFrame([(0, 1, 2.0), (0, 2, 1.0), (1, 2, 1.0)], schemas.EDGE)
    a = {(r.i, r.j): r.w for r in systems.normalise_columns(edges).collect()}
    assert a == {(0, 1): 1.0, (0, 2): 0.5, (1, 2): 0.5}
    a = {(r.i, r.j): r.w for r in systems.normalise_columns(edges, "outdegree", weighted=True).collect()}
    assert a[(1, 0)] == pytest.approx(2 / 3) and a[(2, 1)] == 1.0
    for how, total in [("leak", 3), ("self", 4), ("uniform", 6)]:
        assert systems.restart_walk_system(edges, dangling=how).op.count() == total


def test_jacobi_and_ridge_fixed_points(spark):
    matrix = spark.createDataFrame([(0, 0, 4.0), (0, 1, 1.0), (1, 1, 3.0), (1, 0, -1.0), (2, 2, 2.0), (2, 0, 0.5)], schemas.OP)
    s = systems.jacobi_system(matrix)
    r = spark.createDataFrame([(0, 0, 1.0), (1, 0, 2.0), (2, 0, 3.0)], "i long, p int, v double")
    got = frame(engine.run_lanes(s, s.forcing(r), s.forcing(r), [60], "lane"))[0].to_numpy()
    _, m = systems.dense(matrix)
    assert np.allclose(got, systems.solve_square_exact(m, np.array([1.0, 2, 3])), atol=1e-10)
    assert systems.row_dominance(matrix).agg(F.max("off")).first()[0] < 1

    dense = np.random.default_rng(0).normal(size=(12, 3))
    rows = spark.createDataFrame([(a, b, float(dense[a, b])) for a in range(12) for b in range(3)], "row long, col int, v double")
    target = np.random.default_rng(1).normal(size=12)
    t = spark.createDataFrame([(a, 0, float(target[a])) for a in range(12)], "i long, p int, v double")
    eps = systems.safe_step(rows, 0.7, 12)
    for variant, lam in [("corrected", 0.7), ("as_printed", 0.7 / eps)]:
        s = systems.ridge_system(rows, 0.7, eps, variant)
        got = frame(engine.run_lanes(s, s.forcing(t), systems.initial_state(s, [0], "zero"), [800], "lane"))[0].to_numpy()
        assert np.allclose(got, systems.solve_ridge_exact(dense, target, lam), atol=1e-8), variant


def test_large_operators_run_without_being_collected(spark, ring, inputs, monkeypatch):
    system = systems.restart_walk_system(ring)
    probes = materialise(system.nodes.crossJoin(spark.range(2)).select("i", F.col("id").cast("int").alias("p"), (F.col("i") - 3.0 * F.col("id")).alias("v")), "probes")

    def results():
        blocks = scoring.error_blocks(system, inputs, 2, 4, converge=200)
        return [*scoring.moments(blocks, 2, 4, [0, 1]), weights.table_of(weights.tau_monte_carlo(system, probes, 3)), weights.square_of(weights.psi_monte_carlo(system, probes, 3))]

    want = results()

    def refuse(*a):
        raise ValueError("collected")

    monkeypatch.setattr(engine, "choose_layout", lambda *a: "wide")
    for module in (engine, scoring, weights):
        monkeypatch.setattr(module, "shared_csr", refuse)
    for got, right in zip(results(), want):
        assert np.allclose(got, right, atol=1e-12)


def test_nearest_vectors_in_several_matrices(spark, small, monkeypatch):
    want = sorted(map(tuple, graphs.nearest_vectors(spark, small).collect()))
    monkeypatch.setattr(graphs, "MOST_VECTORS", 150)
    assert sorted(map(tuple, graphs.nearest_vectors(spark, small).collect())) == want


def test_bandlimited_queries_cover_every_month(spark, small):
    month = graphs.in_month(spark, small).where("i % 4 <> 0").toPandas()
    nation = catalogue.queries()["bandlimited_nation"](spark, small).toPandas()
    assert set(nation.p) == set(month.p) and len(nation) == 25 * month.p.nunique()
    u = np.array(ranking.cosine_basis(spark).orderBy("i").toPandas()["u"].tolist())
    got = frame(catalogue.queries()["bandlimited_cosine_all_months"](spark, small))
    for p, own in month.groupby("p"):
        x = np.zeros(25)
        for _ in range(6):
            x[own.i] = own.v / 1e6
            x = u @ (u.T @ x)
        assert np.allclose(got[p], x, atol=1e-8)


def test_bandlimited_completion(spark):
    q, _ = np.linalg.qr(np.random.default_rng(3).normal(size=(10, 2)))
    basis = spark.createDataFrame([(i, q[i].tolist()) for i in range(10)], "i long, u array<double>")
    signal = q @ np.array([1.5, -0.5])
    seen = spark.createDataFrame([(i, 0, float(signal[i])) for i in range(8)], "i long, p int, v double")
    assert np.allclose(frame(systems.bandlimited_exact(basis, seen, 2))[0], signal, atol=1e-10)
    assert np.allclose(frame(systems.bandlimited_iterate(basis, seen, 2, 25, cut=10))[0], signal, atol=1e-3)
    s = systems.bandlimited_operator(basis, spark.createDataFrame([(8,), (9,)], "i long"))
    f = s.forcing(seen)
    assert np.allclose(frame(engine.run_lanes(s, f, systems.initial_state(s, [0], "zero"), [300], "lane"))[0], signal, atol=1e-6)


def test_laplacian_basis_methods_span_the_same(spark, ring):
    lap = systems.laplacian(ring)
    a = np.array([r.u for r in systems.laplacian_basis(lap, 2).orderBy("i").collect()])
    b = np.array([r.u for r in systems.laplacian_basis(lap, 2, "subspace", rounds=40).orderBy("i").collect()])
    _, m = systems.dense(lap)
    assert np.isclose(np.trace(a.T @ m @ a), np.trace(b.T @ m @ b), rtol=0.05)


def test_salted_product_equals_plain(spark, ring, inputs):
    a = systems.normalise_columns(ring)
    assert np.allclose(frame(systems.salted_multiply(a, inputs, hot=1, salts=3)), frame(systems.multiply(a, inputs)))


def test_error_recursion_and_contraction(spark, ring):
    system = systems.restart_walk_system(ring)
    ids, b = systems.dense(system.op)
    e = spark.createDataFrame([(int(ids[0]), 0, 1.0)], "i long, p int, v double")
    got = frame(systems.propagate_error(system.op, e, 3)).reindex(ids, fill_value=0.0)[0]
    assert np.allclose(got, np.linalg.matrix_power(b, 3)[:, 0])
    assert systems.contraction_estimate(system.op, 20) == pytest.approx(0.85, abs=0.02)


def test_weights(spark, ring):
    system = systems.restart_walk_system(ring)
    _, b = systems.dense(system.op)
    probes = spark.createDataFrame([(i, p, float(np.random.default_rng(100 * p + i).normal())) for i in range(8) for p in range(200)], "i long, p int, v double")
    a, c = weights.table_of(weights.tau_monte_carlo(system, probes, 3)), weights.table_of(weights.tau_monte_carlo(system, probes, 3, "long"))
    exact = weights.tau_exact(b, np.eye(8), 3)
    assert np.allclose(a, c) and np.allclose(a, exact, rtol=0.15)
    psi = weights.square_of(weights.psi_monte_carlo(system, probes, 2))
    assert np.allclose(np.diag(psi), a[:3]) and np.allclose(psi, psi.T)


def test_baselines_and_failure(spark, ring, inputs):
    system = systems.restart_walk_system(ring)
    g, steps = codes.parity_code(2), [4, 2, 6]
    state = materialise(engine.run_lanes(system, system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(systems.initial_state(system, [0, 1]), g), steps, "lane"), "s")
    assert baselines.erasure_or_fail(state, g, steps, 6).where("v IS NOT NULL").count() == 0
    assert np.allclose(frame(baselines.erasure_or_fail(state, g, steps, 4)), frame(baselines.fastest_k_decode(state, g, steps)))
    truth = engine.solve_converged(system, inputs, 2)
    assert metrics.sse(truth, truth).first()[0] == 0
    assert metrics.mse(baselines.uncoded(state, 2), truth, 8).first().mse_entry > 0
    assert metrics.residual(system, truth, system.forcing(inputs)).agg(F.max("residual")).first()[0] < 1e-20


def test_scored_plans_match_direct_decoding(spark, ring, inputs):
    system = systems.restart_walk_system(ring)
    blocks = scoring.error_blocks(system, inputs, 2, 6)
    g, steps, tau = codes.parity_code(2), np.array([4, 2, 6]), weights.tau_geometric(0.85, 6)
    scored = {(r.scheme, r.p): r.sse for r in scoring.score(blocks, 2, 6, scoring.scheme_plans(g, steps, tau, ()), ["scheme"]).collect()}
    state = engine.run_lanes(system, system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(systems.initial_state(system, [0, 1]), g), steps.tolist(), "lane")
    truth = engine.solve_converged(system, inputs, 2, tol=1e-16)
    direct = {r.p: r.sse for r in metrics.per_problem(decode.soft_decode(state, g, steps.tolist(), tau, solver="qr"), truth).collect()}
    for p in (0, 1):
        assert scored[("soft", p)] == pytest.approx(direct[p], rel=1e-6)
    assert scored[("twins_best", 0)] <= scored[("uncoded", 0)] + 1e-15


def test_validation_and_restart_check(spark):
    with pytest.raises(schemas.InvalidTable):
        schemas.validated(spark.createDataFrame([(1, 2, 1.0), (1, 2, 3.0)], schemas.EDGE), "edge")
    with pytest.raises(schemas.InvalidTable):
        schemas.validated(spark.createDataFrame([(None, 2, 1.0)], schemas.EDGE), "edge")
    with pytest.raises(ValueError):
        systems.restart_batch(spark.createDataFrame([(0, 0, 0.5)], "i long, p int, v double"))
    ok = spark.createDataFrame([(1, 2, 1.0)], schemas.EDGE)
    assert schemas.validated(ok, "edge") is ok


def test_edge_lists_and_bucketed_store(spark, tmp_path):
    (tmp_path / "e.csv").write_text("src,dst,weight\n0,1,2.5\n1,2,\n")
    (tmp_path / "e.json").write_text('{"src":0,"dst":1}\n')
    assert [r.weight for r in tables.read_edges_csv(spark, str(tmp_path / "e.csv")).orderBy("src").collect()] == [2.5, 1.0]
    assert tables.read_edges_json(spark, str(tmp_path / "e.json")).first().weight == 1.0
    op = spark.createDataFrame([(0, 1, 0.5), (1, 0, 0.5)], schemas.OP)
    stored = tables.save_edges(op, "edge_store_test", 4)
    assert stored.count() == 2
    assert "Exchange" not in stored.groupBy("j").count()._jdf.queryExecution().executedPlan().toString().split("HashAggregate")[1]
    spark.sql("DROP TABLE edge_store_test")


def test_lane_laws(spark):
    lanes = stragglers.uniform_steps(spark, 50, 1, 20, 3)
    assert stragglers.collected_steps(lanes) == stragglers.draw_steps("uniform", 50, 3).tolist()
    two = stragglers.collected_steps(stragglers.two_point_steps(spark, 50, seed=4))
    assert two == stragglers.draw_steps("two_point", 50, 4).tolist()
    speeds = stragglers.exponential_speeds(spark, 50, seed=5)
    assert stragglers.collected_steps(stragglers.steps_from_speed(speeds, 20.0)) == stragglers.draw_steps("exponential", 50, 5, 20.0).tolist()
    assert stragglers.collected_steps(stragglers.steps_from_speed(speeds, 1.0, startup=2.0)) == [0] * 50


def test_time_slices_give_the_global_order(spark, small):
    one = {(r.src, r.dst) for r in graphs.transition(spark, small, slices=1).collect()}
    assert one == {(r.src, r.dst) for r in graphs.transition(spark, small, slices=37).collect()}


def test_clock_deadline(spark, ring, inputs):
    system = systems.restart_walk_system(ring)
    got = engine.run_until(system, system.forcing(inputs), systems.initial_state(system, [0, 1]), 2, 0.05)
    assert len(got.steps) == 2 and min(got.steps) >= 1 and got.state.count() == 16


def test_caps_are_errors(spark, ring, inputs):
    system = systems.restart_walk_system(ring)
    with pytest.raises(engine.NotConverged):
        engine.solve_converged(system, inputs, 2, tol=0.0, most=20)
    with pytest.raises(Exception, match="still change"):
        scoring.error_blocks(system, inputs, 2, 4, converge=10).count()


def test_node_and_entry_bounds_choose_the_wide_layout(spark, ring, monkeypatch):
    system = systems.restart_walk_system(ring)
    assert engine.choose_layout(system.op, system.nodes) == "lane"
    assert engine.choose_layout(system.op, system.nodes, most_nodes=7) == engine.choose_layout(system.op, system.nodes, most=16) == "wide"
    monkeypatch.setattr(engine, "LANE_NODES", 7)
    with pytest.raises(ValueError, match="nodes"):
        engine.csr(system.op, system.nodes)


def test_hub_columns_are_kept_out_of_buckets(spark, monkeypatch):
    star = spark.createDataFrame([(a, 0, 1.0) for a in range(1, 30)] + [(0, a, 1.0) for a in range(1, 30)] + [(a, a + 1, 1.0) for a in range(1, 29)], schemas.EDGE)
    system = systems.restart_walk_system(materialise(star, "star"))
    r = spark.createDataFrame([(3, 0, 1.0), (0, 1, 1.0), (7, 2, 1.0)], "i long, p int, v double")
    start, steps = systems.initial_state(system, [0, 1, 2]), [5, 0, 7]
    want = frame(engine.run_lanes(system, system.forcing(r), start, steps, "lane"))
    monkeypatch.setattr(engine, "HOT_ENTRIES", 10)
    monkeypatch.setattr(engine, "MOST_HOT", 1000)
    monkeypatch.setattr(engine, "CHUNK", 2)
    assert [x.j for x in engine._hubs(system.op, system.op.count()).collect()] == [0]
    assert np.allclose(frame(engine.run_lanes(system, system.forcing(r), start, steps, "wide")), want, atol=1e-14)


def test_wide_decoding_equals_the_long_one_without_a_shuffle(spark, ring, inputs, monkeypatch):
    monkeypatch.setattr(engine, "CHUNK", 3)
    system, g, steps = systems.restart_walk_system(ring), codes.dft_code(5, 2), [4, 1, 6, 3, 2]
    _, owner = codes.real_columns(g)
    forcing, start = system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(systems.initial_state(system, [0, 1]), g)
    chunks = engine.wide_lanes(system, forcing, start, [steps[q] for q in owner])
    assert len(chunks) == 3
    tau = weights.tau_geometric(0.85, 6)
    lanes = engine.joined_lanes(chunks)
    got = decode.soft_decode_wide(lanes, g, steps, tau)
    want = frame(decode.soft_decode(engine.run_lanes(system, forcing, start, [steps[q] for q in owner], "lane"), g, steps, tau))
    for r in got.collect():
        assert np.allclose(r.x, want.loc[r.i].to_numpy(), atol=1e-12) and np.abs(r.im_leak).max() < 1
    stored = materialise(lanes, "lanes")
    assert "Exchange" not in decode.soft_decode_wide(stored, g, steps, tau)._jdf.queryExecution().executedPlan().toString()


def test_slower_lane_of_a_pair_takes_the_conjugate(spark, ring, inputs):
    system, g, steps = systems.restart_walk_system(ring), codes.dft_code(5, 2), [4, 1, 6, 3, 2]
    _, owner = codes.real_columns(g)
    forcing, start = system.forcing(engine.encode_columns(inputs, g)), engine.encode_columns(systems.initial_state(system, [0, 1]), g)
    run = lambda s: engine.run_lanes(system, forcing, start, [s[q] for q in owner], "lane")
    state, after = decode.complete_conjugates(run(steps), g, steps)
    assert after == [4, 2, 6, 6, 2]
    assert np.allclose(frame(state), frame(run(after)), atol=1e-14)


def test_intermediate_tables_are_deleted_and_a_cluster_needs_a_shared_folder(spark, monkeypatch, tmp_path):
    from softlanes.sources import session

    a, b = session.materialise(spark.range(3), "gone"), session.bucketed(spark.range(5), "id", 2, "gone")
    assert a.count() == 3 and b.count() == 5
    table, paths = session._WRITTEN[spark.sparkContext.applicationId][b._lanes_path], [a._lanes_path, b._lanes_path]
    session.release(a, None, b, spark.range(1))
    assert not spark.catalog.tableExists(table) and not any(Path(p.removeprefix("file:")).exists() for p in paths)

    class Far:
        class conf:
            get = staticmethod(lambda key, default: default)

        class sparkContext:
            master = "spark://host:7077"

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        session.shared_folder(Far())


@pytest.mark.parametrize("layout", ["long", "wide", "lane", "block"])
def test_inputs_at_no_node_are_left_out(spark, ring, inputs, layout):
    system = systems.restart_walk_system(ring)
    start, more = systems.initial_state(system, [0, 1]), inputs.unionByName(spark.createDataFrame([(99, 0, 0.5)], "i long, p int, v double"))
    assert np.allclose(frame(engine.run_lanes(system, system.forcing(more), start, [2, 3], layout)), frame(engine.run_lanes(system, system.forcing(inputs), start, [2, 3], "wide")))


def test_packed_blocks_equal_the_other_layouts(spark, small, monkeypatch):
    """Blocks, chunks of columns and the accelerated solution, with every bound lowered."""
    system = ranking.walk(spark, small)
    inputs = materialise(graphs.in_segment(spark, small), "inputs")
    forcing, start, steps = system.forcing(inputs), systems.initial_state(system, list(range(5))), [3, 0, 2, 5, 1]
    want = frame(engine.run_lanes(system, forcing, start, steps, "lane"))
    truth = frame(engine.run_lanes(system, forcing, start, [230] * 5, "lane"))
    solved = frame(engine.solve_converged(system, inputs, 5, tol=1e-16))
    monkeypatch.setattr(engine, "PACKED_ENTRIES", 900)
    monkeypatch.setattr(engine, "PACKED_STATE", 800)
    assert len(engine.packed(system).chunks(5)) == 3
    assert np.allclose(frame(engine.run_lanes(system, forcing, start, steps, "packed")), want, atol=1e-15, rtol=0)
    monkeypatch.setattr(engine, "choose_layout", lambda *a: "wide")
    again = frame(engine.solve_converged(system, inputs, 5, tol=1e-16))
    assert np.allclose(solved, truth, atol=1e-14, rtol=0) and np.allclose(again, truth, atol=1e-14, rtol=0)
    with pytest.raises(engine.NotConverged):
        engine.solve_converged(system, inputs, 5, tol=1e-16, most=5)


def test_block_layout_cuts_large_operators_finer(spark, small, monkeypatch):
    system = ranking.walk(spark, small)
    inputs = materialise(graphs.in_segment(spark, small), "inputs")
    forcing, start = system.forcing(inputs), systems.initial_state(system, list(range(5)))
    want = frame(engine.run_lanes(system, forcing, start, [2, 0, 1, 2, 2], "lane"))
    monkeypatch.setattr(engine, "BLOCK_ENTRIES", system.op.count() / 36)
    seen, real = [], engine.materialise
    monkeypatch.setattr(engine, "materialise", lambda df, label: seen.append(df.select("bi", "bj").distinct().count()) or real(df, label) if label == "blocks" else real(df, label))
    assert np.allclose(frame(engine.run_lanes(system, forcing, start, [2, 0, 1, 2, 2], "block")), want, atol=1e-15, rtol=0) and 16 < seen[0] <= 36


def test_sampled_weights_over_packed_blocks(spark, small, monkeypatch):
    system = ranking.walk(spark, small)
    drawn = ranking.probes(system, 4)
    want = weights.table_of(weights.tau_monte_carlo(system, drawn, 3, "lane"))
    monkeypatch.setattr(engine, "PACKED_STATE", 800)
    monkeypatch.setattr(engine, "choose_layout", lambda *a: "wide")
    monkeypatch.setattr(weights, "multiply", None)  # no join of rows and probes
    assert np.allclose(weights.table_of(weights.tau_monte_carlo(system, drawn, 3)), want, rtol=1e-12)
