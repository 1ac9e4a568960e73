"""Codes, decode matrices, bounds: invariants on numpy alone."""

import numpy as np
import pytest

from softlanes.operators import baselines, codes, decode, theory
from softlanes.operators.weights import tau_exact, tau_geometric

FAMILIES = {
    "dft": codes.dft_code(12, 9), "sign": codes.sign_code(12, 9, 3), "gaussian": codes.gaussian_code(12, 9, 3), "sparse": codes.sparse_code(12, 9, 0.3, 3),
    "parity": codes.parity_code(9), "hartley": codes.orthonormal_code(codes.hartley_matrix(12), 9), "twin": codes.twin_code(12, 9), "identity": codes.identity_code(9),
}


@pytest.mark.parametrize("name", FAMILIES)
@pytest.mark.parametrize("solver", ["qr", "normal"])
def test_decode_inverts_the_code(name, solver):
    g = FAMILIES[name]
    tau = np.random.default_rng(1).uniform(0.01, 1, g.shape[1])
    assert np.allclose(g @ decode.decode_matrix(g, tau, solver), np.eye(len(g)), atol=1e-9)


def test_solvers_agree_and_scaling_and_order_do_not_matter():
    g, tau = codes.dft_code(12, 9), np.random.default_rng(2).uniform(0.001, 1, 12)
    r = decode.decode_matrix(g, tau, "qr")
    assert np.allclose(r, decode.decode_matrix(g, tau, "syndrome"), atol=1e-9)
    assert np.allclose(r, decode.decode_matrix(g, tau, "normal"), atol=1e-9)
    assert np.allclose(r, decode.decode_matrix(g, 7 * tau, "qr"), atol=1e-9)
    order = np.random.default_rng(3).permutation(12)
    assert np.allclose(decode.decode_matrix(g[:, order], tau[order], "qr"), r[order], atol=1e-9)


def test_equal_steps_give_the_conjugate_transpose():
    g = codes.dft_code(12, 9)
    assert np.allclose(decode.decode_matrix(g, np.ones(12), "qr"), g.conj().T, atol=1e-12)


def test_weights_over_thirty_decades():
    g = codes.dft_code(24, 20)
    tau = 10.0 ** -np.random.default_rng(4).uniform(0, 30, 24)
    for solver in ("qr", "syndrome"):
        r = decode.decode_matrix(g, tau, solver)
        assert np.allclose(g @ r, np.eye(20), atol=1e-6)


def test_garbage_lanes_are_ignored_like_the_fastest_k():
    g = codes.dft_code(6, 5)
    x = np.random.default_rng(5).normal(size=(4, 5))
    y = x @ g
    y[:, 2] += 100
    tau = np.full(6, 1e-12)
    tau[2] = 1e12
    assert np.allclose((y @ decode.decode_matrix(g, tau)).real, x, atol=1e-6)
    assert np.allclose((y @ baselines.fastest_k_matrix(g, [9, 9, 0, 9, 9, 9])).real, x, atol=1e-9)


def test_full_weights_reduce_to_plain_without_a_common_part():
    g, own = codes.dft_code(12, 9), np.random.default_rng(6).uniform(0.1, 1, 12)
    full = decode.correlated_weights(g, own, np.zeros((12, 12)))
    assert np.allclose(decode.decode_matrix(g, full), decode.decode_matrix(g, own), atol=1e-8)
    alpha, beta = np.ones(9), np.ones(9)
    assert np.allclose(decode.correlated_weights(g, own, np.ones((12, 12)), alpha, beta), decode.correlated_weights(g, own, np.ones((12, 12))))


def test_orientation_of_the_common_part():
    """With exact weights of a common error the right orientation decodes better than its conjugate."""
    rng, g = np.random.default_rng(7), codes.dft_code(12, 9)
    steps = rng.integers(1, 12, 12)
    scale = 0.6**steps
    h = g.T @ np.ones(9)
    psi = np.outer(scale, scale)
    own = 1e-4 * scale**2
    good = decode.decode_matrix(g, np.diag(own).astype(complex) + np.conj(h)[:, None] * h[None, :] * psi)
    bad = decode.decode_matrix(g, np.diag(own).astype(complex) + h[:, None] * np.conj(h)[None, :] * psi)
    error = np.ones((1, 9)) @ g * scale
    assert np.abs(error @ good).sum() < 0.5 * np.abs(error @ bad).sum()


def test_rank_deficient_code_is_refused():
    with pytest.raises(codes.BadCode):
        decode.decode_matrix(np.array([[1.0, 0, 1], [1.0, 0, 1]]), np.ones(3))


def test_code_report():
    r = codes.code_report(codes.dft_code(12, 9))
    assert r["orthonormal"] and r["mds"] and r["entry_modulus_equal"] and abs(r["sigma_max"] - 1) < 1e-12
    assert not codes.code_report(np.hstack([np.eye(3), np.zeros((3, 1))]))["mds"]
    assert abs(codes.code_report(codes.parity_code(2))["sigma_max"] - 3) < 1e-12
    h = codes.complement(codes.dft_code(12, 9))
    assert np.allclose(codes.dft_code(12, 9) @ h.conj().T, 0, atol=1e-12)


def test_bounds_agree_and_hold():
    g, tau = codes.dft_code(12, 9), tau_geometric(0.85, 20)
    steps = np.random.default_rng(8).integers(1, 21, 12)
    assert np.isclose(theory.coded_bound(g, tau, steps), theory.schur_bound(g, tau, steps))
    rng, total = np.random.default_rng(9), []
    r = decode.decode_matrix(g, decode.noise_weights(tau, steps))
    for _ in range(300):
        e = rng.normal(size=(1, 9)) @ g * 0.85**steps
        total.append((np.abs(e @ r) ** 2).sum())
    se = np.std(total) / np.sqrt(len(total))
    assert np.mean(total) <= theory.coded_bound(g, tau, steps) + 3 * se
    assert theory.uncoded_mse(tau, steps[:9]) > 0
    law = np.full(21, 1 / 20.0)
    law[0] = 0
    assert theory.coding_gain(g, tau, [steps]) > 0
    assert np.isclose(theory.heavy_tail_rho(tau, law), 2.2, atol=0.1)
    assert np.isclose(theory.p_slowest_unprotected(120, 100), 0.8)


def test_fourier_weights_are_toeplitz_with_parseval():
    w = np.random.default_rng(10).uniform(size=8)
    f = np.exp(-2j * np.pi * np.outer(np.arange(8), np.arange(8)) / 8) / np.sqrt(8)
    t = theory.toeplitz_of_tau(w)
    assert np.allclose(t, (f * w) @ f.conj().T)
    assert np.isclose((np.abs(t[0]) ** 2).sum() * 8, (w**2).sum())


def test_identities():
    rng = np.random.default_rng(11)
    assert theory.vec_identity_gap(rng.normal(size=(3, 4)), rng.normal(size=(4, 2)), rng.normal(size=(2, 5))) < 1e-12
    m = rng.normal(size=(6, 6))
    assert np.isclose(np.trace(theory.block_trace(m, 2)), np.trace(m))
    b = rng.normal(size=(4, 4)) * 0.3
    c = np.cov(rng.normal(size=(4, 50)))
    low, high = theory.tau_bounds(b, c, 3)
    assert low <= tau_exact(b, c, 3)[3] <= high


def test_concentration():
    law = np.full(21, 1 / 20.0)
    law[0] = 0
    r = theory.concentration_report(tau_geometric(0.85, 20), law, 60, 50, trials=300)
    assert np.isclose(r["mean_cross"], r["expected_cross"], rtol=0.1)


def test_twins():
    assert codes.twin_choice(12, 10, "first") == [0, 1] and codes.twin_choice(12, 10, "last") == [8, 9] and len(codes.twin_choice(12, 10, "random")) == 2
    r = baselines.twin_matrix(2, 3, [4, 2, 6], tau_geometric(0.85, 6), "best")
    assert r[0, 0] == 0 and r[2, 0] == 1 and r[1, 1] == 1
    with pytest.raises(codes.BadCode):
        codes.twin_choice(30, 10)


def test_conjugate_partners():
    source, steps = decode.conjugate_complete([5, 1, 3, 9])
    assert source == [0, 3, 2, 3] and steps == [5, 9, 3, 9]
    g = codes.dft_code(6, 5)
    y = np.random.default_rng(1).normal(size=(3, 5)) @ g
    assert np.allclose(y[:, 2], np.conj(y[:, 4]))


def test_complex_lanes_round_trip():
    g = codes.dft_code(6, 5)
    m, _ = codes.real_columns(g)
    x = np.random.default_rng(2).normal(size=(3, 5))
    assert np.allclose(codes.complex_lanes(x @ m, g), x @ g)
    re, im = decode.real_decode(g, g.conj().T)
    assert np.allclose(x @ m @ re, x) and np.allclose(x @ m @ im, 0, atol=1e-12)
