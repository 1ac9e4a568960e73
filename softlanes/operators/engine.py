"""Encoding, running lanes to their step counts, and the layouts that do it.

A lane is one or two real columns (a complex code has two), each column has a step count, and all columns
share the operator. Layouts:

* ``long``: rows (node, column); a join and an aggregation per step.
* ``wide``: one row per node with the columns as an array. The operator carries a row per node for itself,
  with the forcing and a flag, so a step is one join and one aggregation: running columns add products and
  forcing, frozen ones copy themselves. Operator and state are bucketed by node, the lineage is cut every few
  steps by writing the state in the same buckets, and only partial sums are shuffled. Columns of very many entries
  (hub nodes) are kept apart in files of even size and meet the few hub rows of the state broadcast, so that no
  bucket holds a hub's column.
* ``packed``: row blocks of the operator, written once as arrays, meet the state of a few columns broadcast; a step is
  one pass over the blocks and no shuffle. For operators beyond the tasks and nodes of a checked number.
* ``lane``: every task has the whole operator and iterates its columns alone, for operators of a checked size.
* ``block``: two-dimensional blocks of the operator meet blocks of the state, cogrouped.
* ``snapshot``: by linearity, the un-encoded problems are run once and every lane is mixed from their iterates
  at its step count; for comparing schemes.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.operators.codes import real_columns, to_df
from softlanes.operators.systems import AffineSystem, multiply_terms
from softlanes.sources.session import bucketed, materialise, release

LANE_EDGES = 20_000_000
LANE_NODES = 5_000_000
CHUNK = 64
BUCKET_ENTRIES = 100_000
ROUND_OFF, SLACK = 4e-16, 1e-12
HOT_ENTRIES = 200_000  # a column with more is a hub's ...
MOST_HOT = 10_000  # ... but no more columns than these are
PACKED_ENTRIES = 1_000_000  # of a block
PACKED_STATE = 6_000_000  # nodes times columns that go to every task at once
PACKED_COLUMNS = 32


class NotConverged(RuntimeError):
    """The iteration cap was reached while entries still changed."""


@dataclass
class LaneResult:
    """What a run left: ``state(i, p = real column, v)``, distributed, and how many steps each column made."""

    state: DataFrame
    steps: list[int]


# ---- encoding

def encode(vec: DataFrame, g: np.ndarray) -> DataFrame:
    """Mix problems into lanes: ``(i, q, re, im)``; the generator joins broadcast, sums are partial before the shuffle."""
    gen = to_df(vec.sparkSession, g)
    return vec.join(F.broadcast(gen), "p").groupBy("i", "q").agg(F.sum(F.col("v") * F.col("re")).alias("re"), F.sum(F.col("v") * F.col("im")).alias("im"))


def encode_columns(vec: DataFrame, g: np.ndarray) -> DataFrame:
    """Mix problems into real columns: ``vec(i, p = column, v)``."""
    m, _ = real_columns(g)
    spark = vec.sparkSession
    mix = spark.createDataFrame([(p, c, float(m[p, c])) for p in range(m.shape[0]) for c in range(m.shape[1]) if m[p, c]], "p int, c int, g double")
    return vec.join(F.broadcast(mix), "p").groupBy("i", F.col("c").alias("p")).agg(F.sum(F.col("v") * F.col("g")).alias("v"))


def to_wide(vec: DataFrame, nodes: DataFrame, width: int) -> DataFrame:
    """``(i, x)`` with an array of ``width`` for every node of ``nodes``."""
    cells = vec.groupBy("i").agg(F.map_from_entries(F.collect_list(F.struct("p", "v"))).alias("m"))  # at most width entries a node
    filled = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda c: F.coalesce(F.try_element_at("m", c), F.lit(0.0)))
    return nodes.join(cells, "i", "left").select("i", F.coalesce(F.when(F.col("m").isNotNull(), filled), F.array_repeat(F.lit(0.0), width)).alias("x"))


def to_long(wide: DataFrame) -> DataFrame:
    return wide.select("i", F.posexplode("x").alias("p", "v"))


def matmul_wide(wide: DataFrame, m: np.ndarray) -> DataFrame:
    """``x @ m`` of every node's array, in Arrow batches; nothing is shuffled."""
    m = np.ascontiguousarray(m, np.float64)

    def run(batches):
        for b in batches:
            if b.num_rows:
                flat = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, m.shape[0])
                out = (flat @ m).ravel()
                offsets = pa.array(np.arange(0, len(out) + 1, m.shape[1]), pa.int32())
                yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, pa.array(out))], names=["i", "x"])

    return wide.mapInArrow(run, "i long, x array<double>")


# ---- running

def run_lanes(system: AffineSystem, forcing: DataFrame, start: DataFrame, steps: list[int], layout: str = "auto", cut: int = 4) -> DataFrame:
    """Run every real column c from ``start`` for ``steps[c]`` iterations: ``vec(i, p = column, v)``.

    ``forcing`` is K times the encoded inputs, ``start`` the encoded starting points; inputs at what is no node of the
    system are left out.
    """
    if layout == "auto":
        layout = choose_layout(system.op, system.nodes)
        if layout == "wide" and fits_packed(system, len(steps)):
            layout = "packed"
    return {"long": _run_long, "wide": _run_wide, "lane": _run_lane, "block": _run_block, "packed": _run_packed}[layout](system, forcing, start, list(steps), cut)


def choose_layout(op: DataFrame, nodes: DataFrame, most: int = LANE_EDGES, most_nodes: int = LANE_NODES) -> str:
    """``lane`` where operator and nodes fit each task, else ``wide``. Counting written tables reads only their footers."""
    return "lane" if op.count() <= most and nodes.count() <= most_nodes else "wide"


def _column_steps(spark, steps):
    return F.broadcast(spark.createDataFrame([(c, int(s)) for c, s in enumerate(steps)], "p int, steps int"))


def _run_long(system, forcing, start, steps, cut):
    spark = system.op.sparkSession
    lane = _column_steps(spark, steps)
    op = materialise(system.op.select("i", "j", "w"), "op")
    force = materialise(forcing.select("i", "p", "v").join(system.nodes.select("i"), "i", "left_semi"), "forcing")
    state, done = materialise(start.select("i", "p", "v"), "state"), None
    for t in range(1, max(steps, default=0) + 1):
        ended = state.join(lane.where(F.col("steps") == t - 1), "p").select("i", "p", "v")
        done = ended if done is None else done.unionByName(ended)
        going = state.join(lane.where(F.col("steps") >= t), "p").select("i", "p", "v")
        pushed = force.join(lane.where(F.col("steps") >= t), "p").select("i", "p", "v")
        state = multiply_terms(op, going).unionByName(pushed).groupBy("i", "p").agg(F.sum("v").alias("v"))
        state = materialise(state, "state")  # it is read twice, and a plan that doubles must not grow
    last = state.join(lane.where(F.col("steps") == max(steps, default=0)), "p").select("i", "p", "v")
    return last if done is None else done.unionByName(last)


def _run_wide(system, forcing, start, steps, cut):
    out = None
    for first, state in wide_lanes(system, forcing, start, steps, cut):
        part = to_long(state).select("i", (F.col("p") + first).cast("int").alias("p"), "v")
        out = part if out is None else out.unionByName(part)
    return out


def _hubs(op: DataFrame, entries: int) -> DataFrame | None:
    """``(j)``: nodes whose column has very many entries, at most ``MOST_HOT`` of them; None where there is none."""
    most = max(HOT_ENTRIES, entries // MOST_HOT)
    if entries <= most:
        return None
    hot = materialise(op.groupBy("j").count().where(F.col("count") > most).select("j"), "hubs")
    return None if hot.isEmpty() else hot


def wide_lanes(system: AffineSystem, forcing: DataFrame, start: DataFrame, steps: list[int], cut: int = 4) -> list[tuple[int, DataFrame]]:
    """(first column, ``(i, x)``) of each run of at most ``CHUNK`` columns; the operator is written once for all.

    Each state is partitioned by node in the same way, so that runs join without a shuffle.
    """
    spark = system.op.sparkSession
    size = system.op.count()
    # as many buckets as shuffles have partitions, so that sums meet them in place; fewer for a small operator
    parts = min(int(spark.conf.get("spark.sql.shuffle.partitions")), 1 + size // BUCKET_ENTRIES)
    nodes, width = system.nodes.select("i"), len(steps)
    op, hubs, heavy = system.op.select("j", "i", "w"), _hubs(system.op, size), None
    if hubs is not None:
        heavy = materialise(op.join(F.broadcast(hubs), "j", "left_semi").repartition(parts), "heavy")
        op = op.join(F.broadcast(hubs), "j", "left_anti")
        cut = 1  # the state is read twice a step, so it is written every step
    own_rows = to_wide(forcing, nodes, width).select(F.col("i").alias("j"), "i", F.lit(0.0).alias("w"), F.col("x").alias("f"))
    entries = bucketed(op.withColumn("f", F.lit(None).cast("array<double>")).unionByName(own_rows), "j", parts, "operator")
    out = []
    for a in range(0, width, CHUNK):  # few enough columns for one generated aggregation
        own = steps[a : a + CHUNK]
        pick = start.where((F.col("p") >= a) & (F.col("p") < a + len(own))).select("i", (F.col("p") - a).alias("p"), "v")
        state = written = bucketed(to_wide(pick, nodes, len(own)), "i", parts, "state")
        for t in range(1, max(own) + 1):
            known = state.select(F.col("i").alias("k"), "x").hint("shuffle_hash")  # a bucket of the state is small; the operator is not sorted
            joined = entries.join(known, F.col("j") == F.col("k")).select("i", "w", "f", "x")
            if hubs is not None:
                few = F.broadcast(known.join(F.broadcast(hubs), known["k"] == hubs["j"], "left_semi"))
                joined = joined.unionByName(heavy.join(few, F.col("j") == F.col("k")).select("i", "w", F.lit(None).cast("array<double>").alias("f"), "x"))
            mine = F.col("f").isNotNull()
            sums = [
                F.sum(F.col("w") * F.get("x", F.lit(c)) + F.coalesce(F.get("f", F.lit(a + c)), F.lit(0.0))) if own[c] >= t
                else F.sum(F.when(mine, F.get("x", F.lit(c))))
                for c in range(len(own))
            ]
            state = joined.groupBy("i").agg(*[x.alias(f"c{c}") for c, x in enumerate(sums)]).select("i", F.array(*[f"c{c}" for c in range(len(own))]).alias("x"))
            if t % cut == 0 and t < max(own):
                state = bucketed(state, "i", parts, "state", placed=True)
                release(written)
                written = state
        out.append((a, state))
    return out


def joined_lanes(chunks: list[tuple[int, DataFrame]]) -> DataFrame:
    """``(i, x)`` with all columns of ``wide_lanes`` side by side."""
    out = chunks[0][1]
    for _, state in chunks[1:]:
        out = out.join(state.select("i", F.col("x").alias("more")), "i").select("i", F.concat("x", "more").alias("x"))
    return out


def csr(op: DataFrame, nodes: DataFrame, most: int = LANE_EDGES) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(node ids, row starts, column places, weights) of an operator of a checked size."""
    if op.count() > most:
        raise ValueError(f"over {most} entries: the whole operator does not go to every task; use layout 'wide' or 'block'")
    if nodes.count() > LANE_NODES:
        raise ValueError(f"over {LANE_NODES} nodes: the state does not go to every task; use layout 'wide' or 'block'")
    entries = op.select("i", "j", "w").toArrow()
    ids = np.sort(nodes.select("i").toArrow()["i"].to_numpy())
    row, col, w = np.searchsorted(ids, entries["i"].to_numpy()), np.searchsorted(ids, entries["j"].to_numpy()), entries["w"].to_numpy()
    order = np.argsort(row, kind="stable")
    starts = np.searchsorted(row[order], np.arange(len(ids) + 1))
    return ids, starts, col[order], w[order]


def shared_csr(system: AffineSystem):
    """``csr`` of the system's operator as a broadcast, made once for each system."""
    if getattr(system, "_csr", None) is None:
        system._csr = system.op.sparkSession.sparkContext.broadcast(csr(system.op, system.nodes))
    return system._csr


def shared_columns(system: AffineSystem):
    """(column starts, row places, weights) of the system's operator as a broadcast."""
    turned = system.op.select(F.col("j").alias("i"), F.col("i").alias("j"), "w")
    _, starts, row, w = csr(turned, system.nodes)
    return system.op.sparkSession.sparkContext.broadcast((starts, row.astype(np.int32), w))


def csr_apply(matrix, x: np.ndarray, most: int = 1_000_000) -> np.ndarray:
    """Operator times a dense block (nodes x columns): runs of rows of about ``most`` entries, one column after the other."""
    _, starts, col, w = matrix
    full = np.flatnonzero(np.diff(starts))
    first, last = starts[full], starts[full + 1]
    columns, out = np.ascontiguousarray(x.T), np.zeros((x.shape[1], x.shape[0]))
    a = 0
    while a < len(full):
        b = max(a + 1, int(np.searchsorted(last, first[a] + most, side="right")))
        lo, hi = first[a], last[b - 1]
        for c, own in enumerate(columns):
            terms = np.take(own, col[lo:hi])
            terms *= w[lo:hi]
            out[c, full[a:b]] = np.add.reduceat(terms, first[a:b] - lo)
        a = b
    return np.ascontiguousarray(out.T)


def chebyshev_weight(radius: float, before: float | None) -> float:
    """Next weight of the semi-iteration for real eigenvalues within ``radius`` of zero: 1, then 1 / (1 - radius² / 2) ..."""
    if before is None:
        return 1.0
    return 1 / (1 - radius**2 / 2) if before == 1.0 else 1 / (1 - radius**2 * before / 4)


def _block_of(pdf, ids, cols):
    x = np.zeros((len(ids), len(cols)))
    place = {c: k for k, c in enumerate(cols)}
    if len(pdf) and len(ids):
        at = np.minimum(np.searchsorted(ids, pdf["i"].to_numpy()), len(ids) - 1)
        known = ids[at] == pdf["i"].to_numpy()  # rows at no node of the system are left out
        x[at[known], pdf["p"].map(place).to_numpy()[known]] = pdf["v"].to_numpy()[known]
    return x


def _run_lane(system, forcing, start, steps, cut):
    """One task for every eight columns, in order of their step counts; each holds the operator and iterates alone."""
    spark = system.op.sparkSession
    shared = shared_csr(system)
    tagged = start.select("i", "p", "v", F.lit(0).alias("kind")).unionByName(forcing.select("i", "p", "v", F.lit(1).alias("kind")))
    every = spark.createDataFrame([(-1, c, 0.0, 0) for c in range(len(steps))], "i long, p int, v double, kind int")
    limits = list(steps)

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        matrix = shared.value
        ids = matrix[0]
        cols = sorted(pdf["p"].unique().tolist())
        real = pdf[pdf["i"] >= 0]
        x, f = _block_of(real[real["kind"] == 0], ids, cols), _block_of(real[real["kind"] == 1], ids, cols)
        budget = np.array([limits[c] for c in cols])
        for t in range(1, int(budget.max(initial=0)) + 1):
            run = budget >= t
            x[:, run] = csr_apply(matrix, x[:, run]) + f[:, run]
        return pd.DataFrame({"i": np.repeat(ids, len(cols)), "p": np.tile(np.array(cols, np.int32), len(ids)), "v": x.ravel()})

    by_steps = sorted(range(len(steps)), key=lambda c: (limits[c], c))
    groups = F.broadcast(spark.createDataFrame([(c, n // 8) for n, c in enumerate(by_steps)], "p int, g int"))
    return tagged.unionByName(every).join(groups, "p").groupBy("g").applyInPandas(work, "i long, p int, v double")


def fits_packed(system: AffineSystem, columns: int) -> bool:
    return columns <= PACKED_COLUMNS and system.nodes.count() <= LANE_NODES


class Packed:
    """An operator as row blocks of arrays, and what steps over it need; made once for each system."""

    def __init__(self, system: AffineSystem):
        self.spark = spark = system.op.sparkSession
        self.ids = np.sort(system.nodes.select("i").toArrow()["i"].to_numpy())
        self.shared_ids = shared = spark.sparkContext.broadcast(self.ids)

        def pack(batches):
            batches = [b for b in batches if b.num_rows]
            if not batches:
                return
            t, ids = pa.Table.from_batches(batches), shared.value
            row, col = (np.searchsorted(ids, t[c].to_numpy()).astype(np.int32) for c in ("i", "j"))
            order = np.argsort(row, kind="stable")
            row = row[order]
            starts = np.flatnonzero(np.diff(row, prepend=-1))
            arrays = row[starts], np.append(starts, len(row)).astype(np.int32), col[order], t["w"].to_numpy()[order]
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in arrays], names=["rows", "starts", "cols", "w"])

        parts = 1 + system.op.count() // PACKED_ENTRIES
        self.blocks = materialise(system.op.select("i", "j", "w").repartition(parts, "i").mapInArrow(pack, "rows binary, starts binary, cols binary, w binary"), "packed")

    def product(self, x: np.ndarray) -> np.ndarray:
        """Operator times ``x`` (columns x nodes)."""
        shared = self.spark.sparkContext.broadcast(x)

        def work(batches):
            for b in batches:
                for n in range(b.num_rows):
                    rows, starts, cols = (np.frombuffer(b.column(c)[n].as_buffer(), np.int32) for c in range(3))
                    w = np.frombuffer(b.column(3)[n].as_buffer(), np.float64)
                    y = np.stack([np.add.reduceat(np.take(own, cols) * w, starts[:-1]) for own in shared.value])
                    yield pa.RecordBatch.from_arrays([pa.array([rows.tobytes()], pa.binary()), pa.array([y.tobytes()], pa.binary())], names=["rows", "y"])

        got, out = self.blocks.mapInArrow(work, "rows binary, y binary").toArrow(), np.zeros_like(x)
        for rows, y in zip(got["rows"], got["y"]):
            rows = np.frombuffer(rows.as_buffer(), np.int32)
            out[:, rows] = np.frombuffer(y.as_buffer(), np.float64).reshape(len(x), len(rows))
        shared.destroy()
        return out

    def dense(self, vec: DataFrame, first: int, count: int) -> np.ndarray:
        """Columns ``first`` and on of ``vec(i, p, v)`` (columns x nodes); rows at no node of the system are left out."""
        t = vec.where((F.col("p") >= first) & (F.col("p") < first + count)).select("i", "p", "v").toArrow()
        out, i = np.zeros((count, len(self.ids))), t["i"].to_numpy()
        if len(self.ids) and len(i):
            at = np.minimum(np.searchsorted(self.ids, i), len(self.ids) - 1)
            known = self.ids[at] == i
            out[t["p"].to_numpy()[known] - first, at[known]] = t["v"].to_numpy()[known]
        return out

    def vec(self, x: np.ndarray, first: int) -> DataFrame:
        shared, ids = self.spark.sparkContext.broadcast(x), self.shared_ids

        def work(batches):
            for b in batches:
                at, own = b.column(0).to_numpy(), shared.value
                p = np.repeat(np.arange(first, first + len(own), dtype=np.int32), len(at))
                yield pa.RecordBatch.from_arrays([pa.array(np.tile(ids.value[at], len(own))), pa.array(p), pa.array(own[:, at].ravel())], names=["i", "p", "v"])

        return materialise(self.spark.range(len(self.ids)).mapInArrow(work, "i long, p int, v double"), "packed-state")

    def chunks(self, columns: int):
        width = max(1, PACKED_STATE // max(1, len(self.ids)))
        return [(a, min(width, columns - a)) for a in range(0, columns, width)]


def packed(system: AffineSystem) -> Packed:
    if getattr(system, "_packed", None) is None:
        system._packed = Packed(system)
    return system._packed


def _run_packed(system, forcing, start, steps, cut):
    """A few columns at a time; a column that has made its steps stays as it is."""
    own, out = packed(system), None
    for first, count in own.chunks(len(steps)):
        x, f, budget = own.dense(start, first, count), own.dense(forcing, first, count), np.array(steps[first : first + count])
        for t in range(1, int(budget.max(initial=0)) + 1):
            run = budget >= t
            x[run] = own.product(x[run]) + f[run]
        part = own.vec(x, first)
        out = part if out is None else out.unionByName(part)
    return out


def _solve_packed(system, force, problems, tol, most):
    own, out = packed(system), None
    for first, count in own.chunks(problems):
        f = own.dense(force, first, count)
        x, change, top = iterate_to_rest(own.product, f, system.radius, tol, most)
        _check_rest(change, top, tol, most)
        part = own.vec(x, first)
        out = part if out is None else out.unionByName(part)
    return out


def _solve_lane(system, force, problems, tol, most):
    """Eight problems in a task, iterated there until they rest."""
    shared, radius = shared_csr(system), system.radius
    every = force.sparkSession.createDataFrame([(-1, p, 0.0) for p in range(problems)], "i long, p int, v double")

    def work(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        matrix, cols = shared.value, sorted(pdf["p"].unique().tolist())
        f = _block_of(pdf[pdf["i"] >= 0], matrix[0], cols)
        x, change, top = iterate_to_rest(lambda y: csr_apply(matrix, y), f, radius, tol, most)
        ids = matrix[0]
        return pd.DataFrame({"i": np.repeat(ids, len(cols)), "p": np.tile(np.array(cols, np.int32), len(ids)), "v": x.ravel(), "change": change, "top": top})

    rows = force.select("i", "p", "v").unionByName(every).withColumn("g", F.floor(F.col("p") / 8))
    out = materialise(rows.groupBy("g").applyInPandas(work, "i long, p int, v double, change double, top double"), "truth")
    worst = out.groupBy("change", "top").count().orderBy(F.desc(F.col("change") / F.greatest("top", F.lit(1e-300)))).first()
    if worst is not None:
        _check_rest(worst.change, worst.top, tol, most)
    return out.select("i", "p", "v")


def iterate_to_rest(product, f: np.ndarray, radius: float | None, tol: float, most: int) -> tuple[np.ndarray, float, float]:
    """(solution, last change, largest entry) of ``x = B x + f`` from zero, accelerated where B's ``radius`` is known."""
    x, before, weight, change, top = np.zeros_like(f), None, None, 0.0, 0.0
    for _ in range(most):
        new = product(x) + f
        change, top = float(np.abs(new - x).max(initial=0)), float(np.abs(new).max(initial=0))
        if change <= max(tol, ROUND_OFF * top):
            return new, change, top
        if radius is not None:
            weight = chebyshev_weight(radius, weight)
            new = before + weight * (new - before) if weight != 1.0 else new
        before, x = x, new
    return x, change, top


def _check_rest(change: float, top: float, tol: float, most: int) -> None:
    if change > max(tol, SLACK * top):
        raise NotConverged(f"entries still change by {change} after {most} steps")


BLOCK_ENTRIES = 1_000_000  # of a two-dimensional block, about; at least four blocks a side


def _run_block(system, forcing, start, steps, cut, side: int | None = None):
    """State in ``side`` node blocks, operator in side x side blocks; a step cogroups each block with the state
    block of its columns and adds the partial products by row block: each state block travels ``side`` times."""
    width = len(steps)
    side = side or max(4, int((system.op.count() / BLOCK_ENTRIES) ** 0.5))
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(side)).cast("int")
    nodes = system.nodes.select("i")
    op = materialise(system.op.select("i", "j", "w", block("i").alias("bi"), block("j").alias("bj")), "blocks")
    force = materialise(to_wide(forcing, nodes, width).select("i", F.col("x").alias("f")), "forcing")
    state = materialise(to_wide(start, nodes, width), "state")
    budget = list(steps)
    copies = F.explode(F.sequence(F.lit(0), F.lit(side - 1))).alias("bi")

    def product(left: pa.Table, right: pa.Table) -> pa.Table:
        kind = pa.schema([("i", pa.int64()), ("x", pa.list_(pa.float64()))])
        if not left.num_rows or not right.num_rows:
            return kind.empty_table()
        ids = right["i"].to_numpy()
        order = np.argsort(ids)
        x = np.stack(right["x"].to_numpy())[order]
        at = np.searchsorted(ids[order], left["j"].to_numpy())
        rows, place = np.unique(left["i"].to_numpy(), return_inverse=True)
        by_row = np.argsort(place, kind="stable")
        starts = np.searchsorted(place[by_row], np.arange(len(rows)))
        at, w, out = at[by_row], left["w"].to_numpy()[by_row], np.empty((len(rows), width))
        for c in range(width):  # one column's terms at a time: those of all columns are many times the block
            out[:, c] = np.add.reduceat(x[at, c] * w, starts)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, out.size + 1, width), pa.int32()), pa.array(out.ravel()))
        return pa.table([pa.array(rows), lists], schema=kind)

    for t in range(1, max(budget, default=0) + 1):
        going = state.select("i", "x", block("i").alias("bj"), copies)
        partial = op.groupBy("bi", "bj").cogroup(going.groupBy("bi", "bj")).applyInArrow(product, "i long, x array<double>")
        sums = partial.groupBy("i").agg(*[F.sum(F.get("x", F.lit(c))).alias(f"c{c}") for c in range(width)])
        value = [
            (F.coalesce(F.col(f"c{c}"), F.lit(0.0)) + F.get("f", F.lit(c))) if budget[c] >= t else F.get("x", F.lit(c)) for c in range(width)
        ]
        state = materialise(force.join(state, "i").join(sums, "i", "left").select("i", F.array(*value).alias("x")), "state")
    return to_long(state)


# ---- snapshots, truth, clock

def snapshots(system: AffineSystem, forcing: DataFrame, start: DataFrame, problems: int, marks: list[int]) -> dict[int, DataFrame]:
    """Iterates of the un-encoded problems at the step counts ``marks``: ``{steps: vec(i, p, v)}``, from one run
    whose columns are (mark, problem) only where the operator goes to tasks, else step by step."""
    out, state, at = {}, start, 0
    for mark in sorted(set(marks)):
        if mark > at:
            state = materialise(run_lanes(system, forcing, state, [mark - at] * problems), "snapshot")
            at = mark
        out[mark] = state
    return out


def lanes_from_snapshots(shots: dict[int, DataFrame], g: np.ndarray, steps: list[int]) -> DataFrame:
    """Every lane as the mix of the problems' iterates at its step count: ``vec(i, p = column, v)``."""
    m, lanes = real_columns(g)
    out = None
    for mark, shot in sorted(shots.items()):
        own = [c for c, q in enumerate(lanes) if steps[q] == mark]
        if not own:
            continue
        mix = shot.sparkSession.createDataFrame([(p, c, float(m[p, c])) for p in range(len(m)) for c in own], "p int, c int, g double")
        part = shot.join(F.broadcast(mix), "p").groupBy("i", F.col("c").alias("p")).agg(F.sum(F.col("v") * F.col("g")).alias("v"))
        out = part if out is None else out.unionByName(part)
    return out


def solve_converged(system: AffineSystem, inputs: DataFrame, problems: int, tol: float = 1e-12, most: int = 2000, every: int = 20) -> DataFrame:
    """Iterate from zero until no entry changes by more than ``tol`` in a step, or by more than round-off of the
    largest entry; after ``most`` steps changes of a millionth millionth of that are taken, larger ones are NotConverged."""
    force = materialise(system.forcing(inputs).select("i", "p", "v"), "forcing")
    if choose_layout(system.op, system.nodes) == "lane":
        return _solve_lane(system, force, problems, tol, most)
    if fits_packed(system, problems):
        return _solve_packed(system, force, problems, tol, most)
    state = materialise(force, "truth")
    for _ in range(0, most, every):
        before, state = state, materialise(run_lanes(system, force, state, [every] * problems), "truth")
        release(before)
        after = run_lanes(system, force, state, [1] * problems)
        r = state.join(after.withColumnRenamed("v", "n"), ["i", "p"], "full").agg(
            F.max(F.abs(F.coalesce("v", F.lit(0.0)) - F.coalesce("n", F.lit(0.0)))).alias("d"), F.max(F.abs("v")).alias("top")
        ).first()
        if r.d is None or r.d <= max(tol, ROUND_OFF * (r.top or 0.0)):
            return state
    if r.d > SLACK * (r.top or 0.0):
        raise NotConverged(f"entries still change by {r.d} after {most} steps")
    return state


def run_until(system: AffineSystem, forcing: DataFrame, start: DataFrame, columns: int, deadline_s: float) -> LaneResult:
    """Iterate each group of columns until the clock passes the deadline; the step counts are what came out.

    Not reproducible by nature: for timing, not for comparison with SQL. An operator that does not go to tasks takes all
    columns step by step; the step under way at the deadline is finished and counts.
    """
    spark = system.op.sparkSession
    if choose_layout(system.op, system.nodes) != "lane":
        end, state, steps = time.monotonic() + deadline_s, start, 0
        while steps == 0 or time.monotonic() < end:
            before, state = state, materialise(run_lanes(system, forcing, state, [1] * columns), "clock")
            steps += 1
            if steps > 1:
                release(before)
        return LaneResult(state, [steps] * columns)
    shared = shared_csr(system)
    tagged = start.select("i", "p", "v", F.lit(0).alias("kind")).unionByName(forcing.select("i", "p", "v", F.lit(1).alias("kind")))

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        end = time.monotonic() + deadline_s
        matrix = shared.value
        ids, cols = matrix[0], sorted(pdf["p"].unique().tolist())
        x, f = _block_of(pdf[pdf["kind"] == 0], ids, cols), _block_of(pdf[pdf["kind"] == 1], ids, cols)
        t = 0
        while time.monotonic() < end:
            x = csr_apply(matrix, x) + f
            t += 1
        return pd.DataFrame({"i": np.repeat(ids, len(cols)), "p": np.tile(np.array(cols, np.int32), len(ids)), "v": x.ravel(), "steps": t})

    out = materialise(tagged.withColumn("g", F.floor(F.col("p") / 8)).groupBy("g").applyInPandas(work, "i long, p int, v double, steps int"), "clock")
    made = {r.p: r.steps for r in out.groupBy("p").agg(F.max("steps").alias("steps")).collect()}  # columns
    return LaneResult(out.select("i", "p", "v"), [made.get(c, 0) for c in range(columns)])
