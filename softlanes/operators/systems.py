"""Linear systems and their stationary iterations ``x <- B x + K r`` as tables.

An operator is ``op(i, j, w)``: row i gets ``w`` times the value of node j. Vectors are ``vec(i, p, v)``
with a missing row meaning 0.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.functions.hashing import hash_uniform
from softlanes.sources.session import materialise, release

EXACT_NODES = 5000


@dataclass
class AffineSystem:
    """``op`` is B; ``drive`` is K, a number for a multiple of the identity or a table like ``op``; ``nodes(i)`` all nodes.

    ``radius``: B's eigenvalues are known to be real and at most that in size, so that solutions may be accelerated.
    """

    op: DataFrame
    drive: float | DataFrame
    nodes: DataFrame
    radius: float | None = None

    def forcing(self, inputs: DataFrame) -> DataFrame:
        """K r for every problem: ``vec(i, p, v)``."""
        if isinstance(self.drive, (int, float)):
            return inputs.select("i", "p", (F.col("v") * float(self.drive)).alias("v"))
        return multiply(self.drive, inputs)

    def step(self, state: DataFrame, forcing: DataFrame) -> DataFrame:
        """One iteration: the products and the forcing meet in one aggregation, with map-side partial sums."""
        return _add(multiply_terms(self.op, state), forcing)


def multiply_terms(op: DataFrame, x: DataFrame) -> DataFrame:
    m = op.select(F.col("i").alias("_i"), F.col("j").alias("_j"), "w")
    return m.join(x, m["_j"] == x["i"]).select(F.col("_i").alias("i"), "p", (F.col("w") * F.col("v")).alias("v"))


def _add(*terms: DataFrame) -> DataFrame:
    both = terms[0]
    for t in terms[1:]:
        both = both.unionByName(t.select("i", "p", "v"))
    return both.groupBy("i", "p").agg(F.sum("v").alias("v"))


def multiply(op: DataFrame, x: DataFrame) -> DataFrame:
    """``op`` times every column of ``x``."""
    return _add(multiply_terms(op, x))


def salted_multiply(op: DataFrame, x: DataFrame, hot: int = 100_000, salts: int = 32) -> DataFrame:
    """``multiply`` for operators with rows of very many entries: rows with over ``hot`` entries sum in two levels.

    The list of such rows has at most (entries / hot) of them; it is joined, not collected.
    """
    heavy = op.groupBy("i").count().where(F.col("count") > hot).select("i", F.lit(salts).alias("s"))
    salted = op.join(heavy, "i", "left").select(
        "i", "j", "w", F.when(F.col("s").isNull(), 0).otherwise(F.pmod(F.xxhash64("j"), F.col("s"))).cast("int").alias("salt")
    )
    m = salted.select(F.col("i").alias("_i"), F.col("j").alias("_j"), "w", "salt")
    terms = m.join(x, m["_j"] == x["i"]).select(F.col("_i").alias("i"), "salt", "p", (F.col("w") * F.col("v")).alias("v"))
    return terms.groupBy("i", "salt", "p").agg(F.sum("v").alias("v")).groupBy("i", "p").agg(F.sum("v").alias("v"))


# ---- ranking

def normalise_columns(edges: DataFrame, orientation: str = "indegree", weighted: bool = False) -> DataFrame:
    """Adjacency ``op`` with columns scaled.

    "indegree": entry (i, j) of edge i -> j is 1 over the in-degree of j. "outdegree": entry (j, i) is 1 over the
    out-degree of i. Weighted: degrees are sums of weights and entries are weights over them.
    """
    column, row = ("dst", "src") if orientation == "indegree" else ("src", "dst")
    amount = F.col("weight") if weighted else F.lit(1.0)
    degree = edges.groupBy(column).agg(F.sum(amount).alias("_d"))
    return edges.join(degree, column).select(F.col(row).alias("i"), F.col(column).alias("j"), (amount / F.col("_d")).alias("w"))


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("i")).unionByName(edges.select(F.col("dst").alias("i"))).distinct()


def restart_walk_system(edges: DataFrame, d: float = 0.15, orientation: str = "indegree", weighted: bool = False, dangling: str = "leak") -> AffineSystem:
    """``x = d r + (1-d) A x``.

    Nodes whose column is empty: "leak" leaves it so, "self" gives it a loop, "uniform" spreads it over all nodes
    (only for graphs of a checked size: it adds a row per node for each such node).
    """
    nodes = nodes_of(edges)
    a = normalise_columns(edges, orientation, weighted)
    if dangling != "leak":
        empty = nodes.join(a.select(F.col("j").alias("i")).distinct(), "i", "left_anti")
        if dangling == "self":
            more = empty.select("i", F.col("i").alias("j"), F.lit(1.0).alias("w"))
        elif dangling == "uniform":
            n, m = nodes.count(), empty.count()
            if n * m > 50_000_000:
                raise ValueError("too many empty columns to spread; use 'self' or 'leak'")
            more = nodes.crossJoin(F.broadcast(empty.select(F.col("i").alias("j")))).select("i", "j", F.lit(1.0 / max(1, n)).alias("w"))
        else:
            raise ValueError(dangling)
        a = a.unionByName(more)
    return AffineSystem(a.select("i", "j", (F.col("w") * (1 - d)).alias("w")), d, nodes)


def uniform_restart(nodes: DataFrame) -> DataFrame:
    n = max(1, nodes.count())
    return nodes.select("i", F.lit(0).alias("p"), F.lit(1.0 / n).alias("v"))


def restart_batch(inputs: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """``inputs`` after checking that every problem sums to 1."""
    bad = inputs.groupBy("p").agg(F.sum("v").alias("t")).where(F.abs(F.col("t") - 1) > tolerance).limit(1).collect()
    if bad:
        raise ValueError(f"problem {bad[0].p} sums to {bad[0].t}, not 1")
    return inputs


def initial_state(system: AffineSystem, problems: list[int], kind: str = "uniform", solutions: DataFrame | None = None) -> DataFrame:
    """Starting point of every problem: 1/N, the mean of known ``solutions``, or nothing (zero)."""
    spark = system.nodes.sparkSession
    ps = F.broadcast(spark.createDataFrame([(int(p),) for p in problems], "p int"))
    if kind == "zero":
        return spark.createDataFrame([], "i bigint, p int, v double")
    if kind == "mean":
        return solutions.groupBy("i").agg(F.avg("v").alias("v")).crossJoin(ps).select("i", "p", "v")
    n = max(1, system.nodes.count())
    return system.nodes.crossJoin(ps).select("i", "p", F.lit(1.0 / n).alias("v"))


# ---- square and regularised systems

def jacobi_system(matrix: DataFrame) -> AffineSystem:
    """Diagonal splitting of ``matrix(i, j, w)``: B = -(rest / diagonal), K = 1 / diagonal."""
    diagonal = matrix.where("i = j").groupBy("i").agg(F.sum("w").alias("_d"))
    op = matrix.where("i <> j").join(diagonal, "i").select("i", "j", (-F.col("w") / F.col("_d")).alias("w"))
    drive = diagonal.select("i", F.col("i").alias("j"), (1 / F.col("_d")).alias("w"))
    return AffineSystem(op, drive, matrix.select("i").distinct())


def row_dominance(matrix: DataFrame) -> DataFrame:
    """``(i, off)``: sum of the absolute off-diagonal entries over the diagonal's; all below 1 means it converges."""
    return matrix.groupBy("i").agg(
        (F.sum(F.when(F.col("i") != F.col("j"), F.abs("w")).otherwise(0.0)) / F.sum(F.when(F.col("i") == F.col("j"), F.abs("w")).otherwise(0.0))).alias("off")
    )


def gram(rows: DataFrame) -> DataFrame:
    """``MᵀM`` as ``op`` from ``rows(row, col, v)``; pairs are formed within a row, whose columns are few."""
    a = rows.select("row", F.col("col").alias("i"), F.col("v").alias("a"))
    b = rows.select("row", F.col("col").alias("j"), F.col("v").alias("b"))
    return a.join(b, "row").groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("w"))


def ridge_system(rows: DataFrame, lam: float, eps: float, variant: str = "corrected") -> AffineSystem:
    """Gradient iteration for regularised least squares over ``rows(row, col, v)``.

    "corrected": B = (1 - eps lam) I - eps MᵀM, whose fixed point is the ridge solution with ``lam``. "as_printed":
    B = (1 - lam) I - eps MᵀM, whose fixed point has the penalty lam / eps.
    """
    keep = 1 - eps * lam if variant == "corrected" else 1 - lam
    g = gram(rows)
    nodes = rows.select(F.col("col").cast("long").alias("i")).distinct()
    op = g.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), (F.lit(-eps) * F.col("w")).alias("w")).unionByName(
        nodes.select("i", F.col("i").alias("j"), F.lit(keep).alias("w"))
    ).groupBy("i", "j").agg(F.sum("w").alias("w"))
    drive = rows.select(F.col("col").cast("long").alias("i"), F.col("row").cast("long").alias("j"), (F.lit(eps) * F.col("v")).alias("w"))
    return AffineSystem(op, drive, nodes)


def safe_step(rows: DataFrame, lam: float, rounds: int = 20) -> float:
    """A step size below 1 / (largest eigenvalue of MᵀM + lam)."""
    return 1.0 / (contraction_estimate(gram(rows).select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "w"), rounds) * 1.05 + lam)


def contraction_estimate(op: DataFrame, rounds: int = 20, cut: int = 5) -> float:
    """Largest modulus of an eigenvalue, by power iteration; growth averaged over the second half of the rounds, the
    vector written and scaled every ``cut`` of them."""
    x = op.select("i").distinct().select("i", F.lit(0).alias("p"), (1 + hash_uniform(F.col("i"), "power")).alias("v"))
    growth, before = [], None
    for at in range(0, rounds, cut):
        y = x
        for _ in range(min(cut, rounds - at)):
            y = multiply(op, y)
        y = materialise(y, "power")
        release(before)
        norm = y.agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("n")).first().n
        if not norm:
            return 0.0
        growth.append((min(cut, rounds - at), np.log(norm)))
        x, before = y.withColumn("v", F.col("v") / norm), y
    tail = growth[len(growth) // 2 :]
    return float(np.exp(sum(g for _, g in tail) / sum(n for n, _ in tail)))


def dense(op: DataFrame, columns: tuple[str, str, str] = ("i", "j", "w")) -> tuple[np.ndarray, np.ndarray]:
    """(node ids, dense matrix) of a small operator, for exact answers in tests; the size is checked."""
    i, j, w = columns
    ids = sorted({r[0] for r in op.select(i).union(op.select(j)).distinct().limit(EXACT_NODES + 1).collect()})
    if len(ids) > EXACT_NODES:
        raise ValueError(f"more than {EXACT_NODES} nodes: use the iteration")
    place = {n: k for k, n in enumerate(ids)}
    m = np.zeros((len(ids), len(ids)))
    for r in op.select(i, j, w).collect():
        m[place[r[0]], place[r[1]]] += r[2]
    return np.array(ids), m


def solve_square_exact(m: np.ndarray, r: np.ndarray) -> np.ndarray:
    return np.linalg.solve(m, r)


def solve_ridge_exact(m: np.ndarray, r: np.ndarray, lam: float) -> np.ndarray:
    return np.linalg.solve(m.T @ m + lam * np.eye(m.shape[1]), m.T @ r)


def solve_square(matrix: DataFrame, inputs: DataFrame) -> DataFrame:
    """Direct solutions of a small square system ``matrix(i, j, w)`` for every problem of ``inputs(i, p, v)``; the
    number of nodes is checked, inputs at no node are left out."""
    ids, m = dense(matrix)
    spark = matrix.sparkSession
    known = F.broadcast(spark.createDataFrame([(int(n), k) for k, n in enumerate(ids)], "i bigint, k int"))
    rows = inputs.join(known, "i").groupBy("k", "p").agg(F.sum("v").alias("v")).collect()  # nodes of a checked size times problems
    problems = sorted({r.p for r in rows})
    place = {p: c for c, p in enumerate(problems)}
    right = np.zeros((len(ids), len(problems)))
    for r in rows:
        right[r.k, place[r.p]] = r.v
    x = solve_square_exact(m, right)
    return spark.createDataFrame([(int(n), int(p), float(x[k, c])) for k, n in enumerate(ids) for c, p in enumerate(problems)], "i bigint, p int, v double")


def solve_ridge(rows: DataFrame, inputs: DataFrame, lam: float) -> DataFrame:
    """Direct ridge solutions over ``rows(row, col, v)``: the Gram matrix and the right-hand sides are distributed sums,
    only they (columns of a checked number) reach the driver."""
    g = gram(rows).select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "w")
    ridge = rows.select(F.col("col").cast("long").alias("i")).distinct().select("i", F.col("i").alias("j"), F.lit(float(lam)).alias("w"))
    m, r = rows.withColumnRenamed("v", "m"), inputs.select(F.col("i").alias("row"), "p", "v")
    right = m.join(r, "row").groupBy(F.col("col").cast("long").alias("i"), "p").agg(F.sum(F.col("m") * F.col("v")).alias("v"))
    return solve_square(g.unionByName(ridge), right)


def propagate_error(op: DataFrame, error: DataFrame, steps: int, cut: int = 4) -> DataFrame:
    """``B**steps`` applied to ``error``."""
    for t in range(1, steps + 1):
        error = multiply(op, error)
        if t % cut == 0:
            error = materialise(error, "error")
    return error


# ---- band-limited graph signals

def laplacian(edges: DataFrame) -> DataFrame:
    """Degree minus adjacency of the symmetrised weights (loops dropped), as ``op``."""
    both = edges.where("src <> dst").select(F.col("src").alias("i"), F.col("dst").alias("j"), "weight").unionByName(
        edges.where("src <> dst").select(F.col("dst").alias("i"), F.col("src").alias("j"), "weight")
    ).groupBy("i", "j").agg((F.sum("weight") / 2).alias("w"))
    degree = both.groupBy("i").agg(F.sum("w").alias("w")).select("i", F.col("i").alias("j"), "w")
    return both.select("i", "j", (-F.col("w")).alias("w")).unionByName(degree)


def laplacian_basis(lap: DataFrame, width: int, method: str = "eigh", rounds: int = 60, seed: int = 5) -> DataFrame:
    """``basis(i, u)``: the ``width`` eigenvectors of smallest eigenvalue.

    "eigh": dense on the driver, for a checked number of nodes. "subspace": orthogonal iteration with distributed
    products; what reaches the driver is a width x width Gram matrix each round.
    """
    spark = lap.sparkSession
    if method == "eigh":
        ids, m = dense(lap)
        _, vec = np.linalg.eigh(m)
        return spark.createDataFrame([(int(n), vec[k, :width].tolist()) for k, n in enumerate(ids)], "i bigint, u array<double>")
    top = lap.groupBy("i").agg(F.sum(F.abs("w")).alias("s")).agg(F.max("s")).first()[0]
    nodes = lap.select("i").distinct()
    shifted = lap.select("i", "j", (-F.col("w")).alias("w")).unionByName(nodes.select("i", F.col("i").alias("j"), F.lit(float(top)).alias("w"))).groupBy("i", "j").agg(F.sum("w").alias("w"))
    shifted = materialise(shifted, "shifted")
    x = nodes.select("i", *[(F.pmod(F.xxhash64("i", F.lit(seed + c)), F.lit(100_003)) / 100_003.0 - 0.5).alias(f"u{c}") for c in range(width)])
    pairs = [(a, b) for a in range(width) for b in range(a, width)]

    def orthonormal(df):
        got = df.agg(*[F.sum(F.col(f"u{a}") * F.col(f"u{b}")).alias(f"g{a}_{b}") for a, b in pairs]).first()
        g = np.zeros((width, width))
        for (a, b), v in zip(pairs, got):
            g[a, b] = g[b, a] = v
        t = np.linalg.inv(np.linalg.cholesky(g)).T
        return df.select("i", *[sum(F.col(f"u{a}") * float(t[a, c]) for a in range(width)).alias(f"u{c}") for c in range(width)])

    m = shifted.select(F.col("i").alias("_i"), F.col("j").alias("_j"), "w")
    for _ in range(rounds):
        x = orthonormal(materialise(x, "subspace"))
        x = m.join(x, m["_j"] == x["i"]).groupBy(F.col("_i").alias("i")).agg(*[F.sum(F.col("w") * F.col(f"u{c}")).alias(f"u{c}") for c in range(width)])
    x = orthonormal(materialise(x, "subspace"))
    return x.select("i", F.array(*[f"u{c}" for c in range(width)]).alias("u"))


def bandlimited_step(basis: DataFrame, observed: DataFrame, signal: DataFrame, width: int) -> DataFrame:
    """One projection step: put observed values in, project on the basis.

    Never forms the projector: the coefficients are ``width`` sums for each instant, which join back broadcast.
    ``observed(i, p, v)`` holds the known values, ``signal(i, p, v)`` the present estimate of all nodes.
    """
    mixed = signal.join(observed.select("i", "p", F.col("v").alias("o")), ["i", "p"], "left").select("i", "p", F.coalesce("o", "v").alias("v"))
    coef = mixed.join(basis, "i").groupBy("p").agg(F.array(*[F.sum(F.get("u", F.lit(c)) * F.col("v")) for c in range(width)]).alias("c"))
    return basis.crossJoin(F.broadcast(coef)).select(
        "i", "p", F.aggregate(F.zip_with("u", "c", lambda a, b: a * b), F.lit(0.0), lambda s, t: s + t).alias("v")
    )


def bandlimited_iterate(basis: DataFrame, observed: DataFrame, width: int, steps: int, cut: int = 5) -> DataFrame:
    problems = observed.select("p").distinct()
    signal = basis.select("i").crossJoin(F.broadcast(problems)).select("i", "p", F.lit(0.0).alias("v"))
    for t in range(1, steps + 1):
        signal = bandlimited_step(basis, observed, signal, width)
        if t % cut == 0:
            signal = materialise(signal, "signal")
    return signal


def bandlimited_operator(basis: DataFrame, hidden: DataFrame) -> AffineSystem:
    """The same iteration as an affine system, dense in the nodes: for small graphs that feed coded lanes.

    ``hidden(i)`` are the unobserved nodes: B keeps their columns of the projector, K the others.
    """
    n = basis.count()
    if n > EXACT_NODES:
        raise ValueError(f"more than {EXACT_NODES} nodes: use the two-sum steps")
    a, b = basis.select("i", "u"), F.broadcast(basis.select(F.col("i").alias("j"), F.col("u").alias("t")))
    projector = a.crossJoin(b).select("i", "j", F.aggregate(F.zip_with("u", "t", lambda x, y: x * y), F.lit(0.0), lambda s, t: s + t).alias("w"))
    marked = hidden.select(F.col("i").alias("j"))
    return AffineSystem(projector.join(marked, "j", "left_semi").select("i", "j", "w"), projector.join(marked, "j", "left_anti").select("i", "j", "w"), basis.select("i"))


def bandlimited_exact(basis: DataFrame, observed: DataFrame, width: int) -> DataFrame:
    """Closed form: coefficients that fit the observed rows by least squares, applied to all nodes; the smallest
    such coefficients, to which the iteration from zero tends too, where fewer rows than ``width`` are observed.

    The Gram matrix of the observed rows is ``width**2`` sums for each instant; only those reach the driver.
    """
    spark = basis.sparkSession
    seen = observed.join(basis, "i")
    sums = [F.sum(F.get("u", F.lit(a)) * F.get("u", F.lit(b))).alias(f"g{a}_{b}") for a in range(width) for b in range(width)]
    rhs = [F.sum(F.get("u", F.lit(a)) * F.col("v")).alias(f"r{a}") for a in range(width)]
    rows = []
    for r in seen.groupBy("p").agg(*sums, *rhs).collect():
        g = np.array(r[1 : 1 + width * width]).reshape(width, width)
        rows.append((r[0], np.linalg.lstsq(g, np.array(r[1 + width * width :]), rcond=1e-12)[0].tolist()))
    coef = spark.createDataFrame(rows, "p int, c array<double>")
    return basis.crossJoin(F.broadcast(coef)).select(
        "i", "p", F.aggregate(F.zip_with("u", "c", lambda a, b: a * b), F.lit(0.0), lambda s, t: s + t).alias("v")
    )
