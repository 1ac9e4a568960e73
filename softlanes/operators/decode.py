"""Decoders: from lanes that stopped anywhere to estimates of every problem.

Lane values are rows times lanes, ``Y = X G + E``. With the noise weights ``Om`` of the lanes' residuals the
estimate is ``Re(Y R)``, ``R`` being the weighted least-squares inverse of ``G``: slow lanes count less, none
is dropped. Weights may span tens of decades, so their inverse is never formed in the default solvers.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.operators.codes import complement, has_orthonormal_rows, real_columns, require_decodable, sigma_max

ROUND_OFF = float(np.finfo(float).eps) ** 2


def floor_tau(tau: np.ndarray, mean_square: float = 0.0) -> np.ndarray:
    """Round-off puts a floor under any lane's error: ``eps**2`` times the mean squared norm of a lane."""
    tau = np.asarray(tau, float)
    top = float(tau.max(initial=0.0)) or 1.0
    return np.maximum(tau, max(ROUND_OFF * mean_square, top * 1e-60))


def noise_weights(tau: np.ndarray, steps: list[int]) -> np.ndarray:
    """``tau`` by step count at every lane's count; counts past the table take its last value."""
    tau = np.asarray(tau, float)
    return tau[np.minimum(np.asarray(steps, int), len(tau) - 1)]


def correlated_weights(g: np.ndarray, own: np.ndarray, psi: np.ndarray, alpha: np.ndarray | None = None, beta: np.ndarray | None = None) -> np.ndarray:
    """Noise weights where inputs share a common part: n x n.

    ``own`` are the lanes' weights for the parts of their own, ``psi[a, b]`` the cross moments of the common
    part's residual at the counts of lanes a and b. Problem p is ``alpha[p]`` times the common part plus
    ``beta[p]`` times its own (ones by default).
    """
    k = len(g)
    alpha = np.ones(k) if alpha is None else np.asarray(alpha, float)
    beta = np.ones(k) if beta is None else np.asarray(beta, float)
    h = g.T @ alpha
    return sigma_max(beta[:, None] * g) * np.diag(own) + np.conj(h)[:, None] * h[None, :] * psi


def _qr(g: np.ndarray, om: np.ndarray) -> np.ndarray:
    if om.ndim == 1:
        root = np.sqrt(om / om.min())
        order = np.argsort(root)  # heavy rows first keep the reflections accurate
        a = (g.conj().T / root[:, None])[order]
        q, r = np.linalg.qr(a)
        out = np.empty_like(a)
        out[order] = np.linalg.solve(r, q.conj().T).conj().T
        return out / root[:, None]
    # a full weight matrix: its own factor, with a floor relative to its size
    om = (om + om.conj().T) / 2
    factor = np.linalg.cholesky(om + np.eye(len(om)) * np.trace(om).real / len(om) * 1e-15)
    a = np.linalg.solve(factor, g.conj().T)
    q, r = np.linalg.qr(a)
    return np.linalg.solve(factor.conj().T, np.linalg.solve(r, q.conj().T).conj().T)


def _normal(g: np.ndarray, om: np.ndarray) -> np.ndarray:
    inverse = np.diag(1 / om) if om.ndim == 1 else np.linalg.inv(om)
    return inverse @ g.conj().T @ np.linalg.inv(g @ inverse @ g.conj().T)


def _syndrome(g: np.ndarray, om: np.ndarray) -> np.ndarray:
    n, k = g.shape[1], g.shape[0]
    if n == k:
        return g.conj().T
    h = complement(g)
    if om.ndim == 1:
        root = np.sqrt(om / om.max())
        q, r = np.linalg.qr(root[:, None] * h.conj().T)
        fix = np.linalg.solve(r, q.conj().T * root[None, :])
    else:
        om = om / np.abs(om).max()
        fix = np.linalg.solve(h @ om @ h.conj().T, h @ om)
    return (np.eye(n) - h.conj().T @ fix) @ g.conj().T


def decode_matrix(g: np.ndarray, om: np.ndarray, solver: str = "auto") -> np.ndarray:
    """``R`` (n x k) with ``G R = I``.

    "qr" factors the whitened generator; "syndrome" inverts only as many rows as there are spare lanes and needs
    orthonormal rows; "normal" is the literal formula, kept to compare. "auto": syndrome for a full ``om`` over
    orthonormal rows, else qr.
    """
    require_decodable(g)
    om = np.asarray(om)
    if om.ndim == 1:
        om = floor_tau(om)
    if solver == "auto":
        solver = "syndrome" if om.ndim == 2 and has_orthonormal_rows(g) else "qr"
    if solver == "syndrome" and not has_orthonormal_rows(g):
        raise ValueError("the syndrome form needs orthonormal rows")
    return {"qr": _qr, "normal": _normal, "syndrome": _syndrome}[solver](g, om)


def real_decode(g: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The decode matrix over real columns (C x k): for the real part, and for the imaginary part that should vanish."""
    _, lanes = real_columns(g)
    re, im, seen = [], [], set()
    for q in lanes:
        row = r[q]
        re.append(-row.imag if q in seen else row.real)
        im.append(row.real if q in seen else row.imag)
        seen.add(q)
    return np.array(re, float), np.array(im, float)


def apply_decode(state: DataFrame, g: np.ndarray, r: np.ndarray) -> DataFrame:
    """``estimate(i, p, v, im_leak)`` from ``state(i, p = real column, v)``: broadcast matrix, partial sums."""
    re, im = real_decode(g, r)
    spark = state.sparkSession
    m = spark.createDataFrame([(c, p, float(re[c, p]), float(im[c, p])) for c in range(len(re)) for p in range(re.shape[1])], "c int, k int, re double, im double")
    return state.join(F.broadcast(m), state["p"] == m["c"]).groupBy("i", F.col("k").alias("p")).agg(
        F.sum(F.col("v") * F.col("re")).alias("v"), F.sum(F.col("v") * F.col("im")).alias("im_leak")
    )


def soft_decode(state: DataFrame, g: np.ndarray, steps: list[int], tau: np.ndarray, psi: np.ndarray | None = None, solver: str = "auto") -> DataFrame:
    """The weighted decoder; with ``psi`` (by step counts, a square table) the one for correlated inputs."""
    own = noise_weights(tau, steps)
    if psi is None:
        om = own
    else:
        at = np.minimum(np.asarray(steps, int), len(psi) - 1)
        om = correlated_weights(g, own, psi[np.ix_(at, at)])
    return apply_decode(state, g, decode_matrix(g, om, solver))


def decode_wide(lanes: DataFrame, g: np.ndarray, r: np.ndarray) -> DataFrame:
    """``(i, x, im_leak)``, arrays over the problems, from ``lanes(i, x)`` over real columns: a product inside each
    node's row, so nothing is shuffled."""
    from softlanes.operators.engine import matmul_wide

    re, im = real_decode(g, r)
    k = re.shape[1]
    both = matmul_wide(lanes, np.hstack([re, im]))
    return both.select("i", F.slice("x", 1, k).alias("x"), F.slice("x", k + 1, k).alias("im_leak"))


def soft_decode_wide(lanes: DataFrame, g: np.ndarray, steps: list[int], tau: np.ndarray, solver: str = "auto") -> DataFrame:
    """The weighted decoder on the wide layout."""
    return decode_wide(lanes, g, decode_matrix(g, noise_weights(tau, steps), solver))


def conjugate_partner(n: int, q: int) -> int:
    return (n - q) % n


def conjugate_complete(steps: list[int]) -> tuple[list[int], list[int]]:
    """For real inputs under a Fourier code lane n-q is the conjugate of lane q: (source lane, steps) of every lane
    after the slower one of each pair takes its partner's state."""
    n = len(steps)
    source = [q if steps[q] >= steps[conjugate_partner(n, q)] else conjugate_partner(n, q) for q in range(n)]
    return source, [steps[s] for s in source]


def complete_conjugates(state: DataFrame, g: np.ndarray, steps: list[int]) -> tuple[DataFrame, list[int]]:
    """``state(i, p = real column, v)`` of a Fourier code over real inputs where the slower lane of each conjugate pair
    takes the conjugate of the faster one's state, and the step counts after that."""
    _, owner = real_columns(g)
    columns = {}
    for c, q in enumerate(owner):
        columns.setdefault(q, []).append(c)
    source, after = conjugate_complete(steps)
    moves = [(columns[s][part], columns[q][part], -1.0 if part and s != q else 1.0) for q, s in enumerate(source) for part in range(len(columns[q]))]
    table = state.sparkSession.createDataFrame(moves, "p int, into int, sign double")
    return state.join(F.broadcast(table), "p").select("i", F.col("into").alias("p"), (F.col("v") * F.col("sign")).alias("v")), after
