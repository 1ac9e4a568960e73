"""Generator matrices: how k problems are mixed into n lanes. Small dense numpy, and tables for joins."""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from softlanes import schemas
from softlanes.functions.hashing import hash_uniform_value

EXHAUSTIVE = 100_000


class BadCode(ValueError):
    """A generator that cannot be decoded."""


def dft_code(n: int, k: int) -> np.ndarray:
    """The first k rows of the unitary n-point Fourier matrix; complex, orthonormal rows, any k columns independent."""
    p, q = np.arange(k)[:, None], np.arange(n)[None, :]
    return np.exp(-2j * np.pi * p * q / n) / np.sqrt(n)


def _hashed(what: str, k: int, n: int, seed: int, attempt: int) -> np.ndarray:
    """Uniform numbers by problem and lane, the same in Spark and SQL."""
    return np.array([[hash_uniform_value(what, seed, attempt, p, q) for q in range(n)] for p in range(k)]).reshape(k, n)


def _redrawn(draw, k: int, what: str, tries: int = 200) -> np.ndarray:
    """The first draw of full rank; draws are numbered from 0."""
    for attempt in range(tries):
        g = draw(attempt)
        if np.linalg.matrix_rank(g) == k:
            return g
    raise BadCode(f"no full-rank {what} in {tries} draws")


def sign_code(n: int, k: int, seed: int = 0) -> np.ndarray:
    """Random signs, drawn again while rank deficient."""
    return _redrawn(lambda t: np.where(_hashed("sign", k, n, seed, t) < 0.5, -1.0, 1.0), k, "sign code")


def sparse_code(n: int, k: int, density: float = 0.1, seed: int = 0) -> np.ndarray:
    """Random 0/1 generator, drawn again while rank deficient (every problem must be in some lane)."""
    return _redrawn(lambda t: (_hashed("sparse", k, n, seed, t) < density).astype(float), k, f"0/1 code of density {density}")


def gaussian_code(n: int, k: int, seed: int = 0) -> np.ndarray:
    """Standard normal entries, from two uniform numbers each."""
    radius, angle = _hashed("radius", k, n, seed, 0), _hashed("angle", k, n, seed, 0)
    return np.sqrt(-2 * np.log(1 - radius)) * np.cos(2 * np.pi * angle)


def parity_code(k: int) -> np.ndarray:
    """Each problem alone, and their sum."""
    return np.hstack([np.eye(k), np.ones((k, 1))])


def orthonormal_code(q: np.ndarray, k: int) -> np.ndarray:
    """The first k rows of an orthonormal matrix."""
    if not np.allclose(q @ q.conj().T, np.eye(len(q)), atol=1e-9):
        raise BadCode("not an orthonormal matrix")
    return q[:k]


def hartley_matrix(n: int) -> np.ndarray:
    """A real orthonormal matrix with Fourier-like rows."""
    angle = 2 * np.pi * np.outer(np.arange(n), np.arange(n)) / n
    return (np.cos(angle) + np.sin(angle)) / np.sqrt(n)


def complement(g: np.ndarray) -> np.ndarray:
    """Orthonormal rows that span what the (orthonormal) rows of ``g`` leave: (n-k) x n."""
    k = len(g)
    _, _, vh = np.linalg.svd(g, full_matrices=True)
    return vh[k:]


def identity_code(k: int) -> np.ndarray:
    return np.eye(k)


def twin_choice(n: int, k: int, policy: str = "first", seed: int = 0) -> list[int]:
    """Which problems the lanes k..n-1 repeat."""
    spare = n - k
    if not 0 <= spare <= k:
        raise BadCode("between k and 2k lanes are needed for twins")
    if policy == "first":
        return list(range(spare))
    if policy == "last":
        return list(range(k - spare, k))
    if policy == "random":
        return sorted(sorted(range(k), key=lambda p: (hash_uniform_value("twin", p, seed), p))[:spare])
    raise ValueError(policy)


def twin_code(n: int, k: int, policy: str = "first", seed: int = 0) -> np.ndarray:
    g = np.zeros((k, n))
    g[:, :k] = np.eye(k)
    for lane, p in enumerate(twin_choice(n, k, policy, seed), start=k):
        g[p, lane] = 1
    return g


def sigma_max(g: np.ndarray) -> float:
    """Largest eigenvalue of the Gram matrix of the columns."""
    return float(np.linalg.norm(g, 2) ** 2)


def has_orthonormal_rows(g: np.ndarray) -> bool:
    return bool(np.allclose(g @ g.conj().T, np.eye(len(g)), atol=1e-9))


def _subsets(n: int, k: int, seed: int, sample: int):
    if comb(n, k) <= EXHAUSTIVE:
        return combinations(range(n), k), True
    rng = np.random.default_rng(seed)
    return (np.sort(rng.choice(n, k, replace=False)) for _ in range(sample)), False


def code_report(g: np.ndarray, seed: int = 0, sample: int = 200) -> dict:
    """Rank, orthonormality, sigma_max, and over k-subsets of columns (all of them where few, else a sample):
    smallest singular value, whether every subset is invertible, and condition numbers."""
    k, n = g.shape
    subsets, exhaustive = _subsets(n, k, seed, sample)
    low, conds = np.inf, []
    for s in subsets:
        sv = np.linalg.svd(g[:, list(s)], compute_uv=False)
        low = min(low, float(sv[-1]))
        conds.append(float(sv[0] / sv[-1]) if sv[-1] > 0 else np.inf)
    return {
        "k": k, "n": n, "rank": int(np.linalg.matrix_rank(g)), "orthonormal": has_orthonormal_rows(g), "sigma_max": sigma_max(g),
        "s_min": low, "mds": bool(low > 1e-10), "exhaustive": exhaustive, "median_cond": float(np.median(conds)), "worst_cond": float(np.max(conds)),
        "entry_modulus_equal": bool(np.allclose(np.abs(g), 1 / np.sqrt(n))),
    }


def condition(g: np.ndarray, lanes) -> float:
    """Condition number of the columns of some lanes, infinite where they are dependent."""
    sv = np.linalg.svd(g[:, list(lanes)], compute_uv=False)
    return float(sv[0] / sv[-1]) if sv[-1] > 1e-10 else np.inf


def require_decodable(g: np.ndarray) -> np.ndarray:
    if np.linalg.matrix_rank(g) < len(g):
        raise BadCode("the generator's rows are dependent: some problem cannot be recovered")
    return g


def to_df(spark: SparkSession, g: np.ndarray) -> DataFrame:
    """``gen(p, q, re, im)``: k x n rows, a parameter-sized table that joins broadcast."""
    c = np.asarray(g, complex)
    return spark.createDataFrame([(p, q, float(c[p, q].real), float(c[p, q].imag)) for p in range(c.shape[0]) for q in range(c.shape[1])], schemas.GEN)


def real_columns(g: np.ndarray) -> tuple[np.ndarray, list[int]]:
    """The code over real columns: a complex lane is two of them. Returns (k x C matrix, lane of each column)."""
    if not np.iscomplexobj(g) or np.allclose(g.imag, 0):
        return np.ascontiguousarray(g.real), list(range(g.shape[1]))
    columns, lanes = [], []
    for q in range(g.shape[1]):
        columns.append(g[:, q].real)
        lanes.append(q)
        if not np.allclose(g[:, q].imag, 0):
            columns.append(g[:, q].imag)
            lanes.append(q)
    return np.stack(columns, axis=1), lanes


def complex_lanes(y: np.ndarray, g: np.ndarray) -> np.ndarray:
    """Lane values (rows x n, complex where the code is) from values of its real columns (rows x C)."""
    _, lanes = real_columns(g)
    out = np.zeros((len(y), g.shape[1]), complex if len(lanes) != g.shape[1] else float)
    seen: set[int] = set()
    for c, q in enumerate(lanes):
        out[:, q] += y[:, c] * (1j if q in seen else 1)
        seen.add(q)
    return out
