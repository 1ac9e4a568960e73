"""SQL text of unrolled iterations and small closed-form decoders, for comparison with the engine."""

from __future__ import annotations

from softlanes.sources.graphs import EDGE_SQL

D = 0.15


def walk_ctes(edges: str = "purchase", d: float = D, orientation: str = "indegree") -> list[str]:
    """``edges``, ``op(i, j, w)`` of the damped walk and ``nodes(i)``."""
    column, row = ("dst", "src") if orientation == "indegree" else ("src", "dst")
    return [
        f"edges AS MATERIALIZED ({EDGE_SQL[edges]})",
        f"op AS MATERIALIZED (SELECT {row} AS i, {column} AS j, {1 - d} / count(*) OVER (PARTITION BY {column}) AS w FROM edges)",
        "nodes AS MATERIALIZED (SELECT src AS i FROM edges UNION SELECT dst FROM edges)",
    ]


def unroll(steps: int, start: str = "s0", forcing: str = "f", op: str = "op", prefix: str = "s") -> list[str]:
    """``s1 .. s{steps}`` from ``s0(i, p, v)``."""
    out, before = [], start
    for t in range(1, steps + 1):
        push = f" UNION ALL SELECT i, p, v FROM {forcing}" if forcing else ""
        out.append(
            f"{prefix}{t} AS MATERIALIZED (SELECT i, p, sum(v) AS v FROM (SELECT o.i, s.p, o.w * s.v AS v FROM {op} o JOIN {before} s ON o.j = s.i{push}) GROUP BY i, p)"
        )
        before = f"{prefix}{t}"
    return out


def ranking_start(inputs: str, d: float = D) -> list[str]:
    """Inputs ``r``, forcing ``f`` and the uniform start ``s0`` of every problem."""
    return [
        f"r AS MATERIALIZED ({inputs})", f"f AS MATERIALIZED (SELECT i, p, {d} * v AS v FROM r WHERE i IN (SELECT i FROM nodes))",
        "ps AS (SELECT DISTINCT p FROM r)", "s0 AS MATERIALIZED (SELECT i, p, 1.0 / (SELECT count(*) FROM nodes) AS v FROM nodes, ps)",
    ]


def coded_start(inputs: str, gen: str, d: float = D) -> list[str]:
    """The same with inputs mixed by ``gen(p, q, g)``: problems of the iteration are the lanes."""
    return [
        f"r AS MATERIALIZED ({inputs})", f"gen AS MATERIALIZED ({gen})",
        f"f AS MATERIALIZED (SELECT r.i, g.q AS p, {d} * sum(r.v * g.g) AS v FROM r JOIN gen g ON r.p = g.p WHERE r.i IN (SELECT i FROM nodes) GROUP BY 1, 2)",
        "s0 AS MATERIALIZED (SELECT i, q AS p, gs / (SELECT count(*) FROM nodes) AS v FROM nodes, (SELECT q, sum(g) AS gs FROM gen GROUP BY q))",
    ]


def stopped(steps: list[int], name: str = "y", prefix: str = "s", columns: list[int] | None = None) -> str:
    """``y(i, p, v)``: lane q as it was after ``steps[q]``."""
    parts = [f"SELECT i, p, v FROM {prefix}{t} WHERE p = {q}" for q, t in enumerate(steps)]
    return f"{name} AS MATERIALIZED ({' UNION ALL '.join(parts)})"


def values(rows: list[tuple], names: str) -> str:
    return f"SELECT * FROM (VALUES {', '.join(str(tuple(r)).replace('None', 'NULL') for r in rows)}) t({names})"


def parity_gen(k: int) -> str:
    rows = [(p, p, 1.0) for p in range(k)] + [(p, k, 1.0) for p in range(k)]
    return values(rows, "p, q, g")


def parity_decode(steps: list[int], rho: float) -> str:
    """Estimates of two problems from three lanes by the 2 x 2 normal equations, weights 1 / rho^(2 steps)."""
    w = [f"power({rho}, -2.0 * {s})" for s in steps]
    det = f"(({w[0]} + {w[2]}) * ({w[1]} + {w[2]}) - {w[2]} * {w[2]})"
    a = f"({w[0]} * y0 + {w[2]} * y2)"
    b = f"({w[1]} * y1 + {w[2]} * y2)"
    x0, x1 = f"(({w[1]} + {w[2]}) * {a} - {w[2]} * {b}) / {det}", f"(({w[0]} + {w[2]}) * {b} - {w[2]} * {a}) / {det}"
    return (
        "wide AS (SELECT i, max(v) FILTER (p = 0) AS y0, max(v) FILTER (p = 1) AS y1, max(v) FILTER (p = 2) AS y2 FROM y GROUP BY i), "
        f"x AS (SELECT i, 0 AS p, {x0} AS v FROM wide UNION ALL SELECT i, 1, {x1} FROM wide)"
    )


def with_(*parts: str | list[str], select: str) -> str:
    flat = [x for p in parts for x in (p if isinstance(p, list) else [p])]
    return "WITH " + ",\n".join(flat) + "\n" + select


ROUND9 = "SELECT i, p, round(v, 9) AS v FROM {}"
