"""One graph between odd and even nodes whose largest component is beyond a piece: columns are run by tasks, nodes scored by others.

A task reads all links, 4 bytes each, and runs a few columns on the whole graph. As in ``pieces.Sides`` only the deviation from what
all states tend to is iterated, until it is round-off. Between two step counts that plans use, deviations are summed; such a sum, a
level, goes to the tasks that score nodes in single precision, which is relative to each entry and so to each squared error. A
scoring task has all levels of all columns on a chunk of nodes, takes their products with each other in double precision, and has
the squared errors of any plan from those. Nodes are gone over in so many ranges that the levels of one stay below ``LEVEL_BYTES`` of
disk; levels of a range are deleted before those of the next are made.
"""

from __future__ import annotations

import gc

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.operators import engine
from softlanes.operators.pieces import LONG_ROW, SOME_ROWS, HashInputs, _prepared, _record, _unpack
from softlanes.sources.session import materialise, release

MOST_EDGES = 100_000_000  # entries whose links a task holds
LEVEL_BYTES = 2_600_000_000  # of levels that lie on disk at once
COLUMNS = 10  # that a task runs at a time
ROWS = 16_384  # nodes whose levels a task has at a time
SLICE = 2048
ONES = -1


class Half:
    """The links of one side's nodes, in order of falling degree, to the other's: the k-th neighbours of nodes that have so many
    are one gather, rows of very many neighbours are summed alone."""

    def __init__(self, n: int):
        self.n, self.long, self.levels = n, [], []

    def add(self, first: int, degree: np.ndarray, cols: np.ndarray) -> None:
        """Nodes from ``first`` on, with their links in the order of ``levelled``."""
        at = 0
        for a in range(0, len(degree), SOME_ROWS):
            own = degree[a : a + SOME_ROWS]
            long = int((own > LONG_ROW).sum())
            for i in range(long):
                self.long.append((first + a + i, cols[at : at + own[i]]))
                at += int(own[i])
            counts = _counts(own[long:])
            ends = at + np.cumsum(counts)
            self.levels.append((first + a + long, [cols[e - c : e] for c, e in zip(counts.tolist(), ends.tolist())]))
            at += int(counts.sum())

    def product(self, x: np.ndarray) -> np.ndarray:
        """Sums over the neighbours of ``x`` (the other side's nodes x columns)."""
        out, part = np.zeros((self.n, x.shape[1])), np.empty((min(SOME_ROWS, self.n), x.shape[1]))
        for i, own in self.long:
            out[i] = x[own].sum(axis=0)
        for a, levels in self.levels:
            for own in levels:
                terms = np.take(x, own, axis=0, out=part[: len(own)], mode="clip")
                rows = out[a : a + len(own)]
                np.add(rows, terms, out=rows)
        return out


def _counts(degree: np.ndarray) -> np.ndarray:
    """How many nodes have more than 0, 1, 2, ... neighbours; ``degree`` falls."""
    return np.searchsorted(-degree, -np.arange(int(degree.max(initial=0))), side="left")


def levelled(degree: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """Links by node in the order that ``Half.add`` takes them."""
    starts, out = np.append(0, np.cumsum(degree)), []
    for a in range(0, len(degree), SOME_ROWS):
        own = degree[a : a + SOME_ROWS]
        long = int((own > LONG_ROW).sum())
        out.append(cols[starts[a] : starts[a + long]])
        first = starts[a + long : a + len(own)]
        out += [cols[first[:count] + k] for k, count in enumerate(_counts(own[long:]).tolist())]
    return np.concatenate(out) if out else cols


class Halves:
    """What ``cut`` made: ``links(side, first, degree, cols)``; nodes are numbered within their side by falling degree."""

    def __init__(self, spark, links, ids, degree, keep, drive, inputs, totals, given):
        self.spark, self.links, self.keep, self.drive = spark, links, keep, drive
        self.high = [len(i) for i in ids]
        self.n_nodes, self.degree, self.inputs, self.totals, self.given = sum(self.high), degree, inputs, totals, given
        self.rest = [(d / d.sum())[:, None] for d in degree]
        self.shared = spark.sparkContext.broadcast((ids, degree, given))
        self.depth = None

    def _units(self, units: list[int]) -> DataFrame:
        """All links for each of ``units``, every one in one task: as many scans, and no shuffle."""
        out = None
        for unit in units:
            own = self.links.coalesce(1).withColumn("unit", F.lit(unit))
            out = own if out is None else out.unionByName(own)
        return out

    def _opened(self):
        """A function from a task's batches to (unit, halves, degrees, ids, forcing of some columns by side)."""
        shared, drive, recipe, totals, high = self.shared, self.drive, self.inputs, self.totals, self.high

        def opened(batches):
            ids, degree, given = shared.value
            halves, unit = [Half(n) for n in high], None
            for b in batches:
                for n in range(b.num_rows):
                    own, cols = (np.frombuffer(b.column(c)[n].as_buffer(), np.int32) for c in ("degree", "cols"))
                    halves[b.column("side")[n].as_py()].add(b.column("first")[n].as_py(), own, cols)
                    unit = b.column("unit")[n].as_py()

            def forcing(columns):
                if recipe is not None:
                    return [drive * recipe.values(recipe.raw(i, columns)) / totals[columns] for i in ids]
                out = [np.zeros((n, len(columns))) for n in high]
                for side, (place, problem, value) in enumerate(given):
                    for c, p in enumerate(columns):
                        own = problem == p
                        out[side][place[own], c] = drive * value[own]
                return out

            return unit, halves, degree, ids, forcing

        return opened

    def mass(self, columns: list[int]) -> np.ndarray:
        """Sums of the forcing on either side (sides x columns)."""
        if self.inputs is not None:
            return self.drive * self.given[:, columns] / self.totals[columns]
        size = max(columns) + 1
        return np.array([self.drive * np.bincount(p, weights=v, minlength=size)[columns] for _, p, v in self.given])

    def _levels(self, columns: list[int], starts: list[int], marks: list[int], ranges: int, r: int, converge: int) -> DataFrame:
        """``(chunk, level, first, data)`` of the nodes in range ``r``: for groups of ``columns`` the sums of deviations from each of
        ``starts`` on to the next; as group ``ONES`` what deviations of ones are after ``marks`` steps, with the same numbers."""
        opened, keep, rest, high = self._opened(), self.keep, self.spark.sparkContext.broadcast(self.rest), self.high
        chunks = _chunks(high)

        def work(batches):
            unit, halves, degree, _, forcing = opened(batches)
            if unit is None:
                return
            own = columns[unit : unit + COLUMNS]
            z = [np.ones((n, 1)) for n in high] if unit == ONES else forcing(own)
            mass, rests = np.array([v.sum(axis=0) for v in z]), [x.max(initial=0) for x in rest.value]
            state = {side: v for side, v in enumerate(z) if v.any()}
            del z
            for side, v in state.items():
                v -= rest.value[side] * mass[side]
            top = np.abs(mass).sum(axis=0)
            mine = [(side, c, a, b) for c, (side, a, b) in enumerate(chunks) if c % ranges == r]
            total = {}

            def rows(level):
                for side, c, a, b in mine:
                    if c in total and total[c].any():
                        yield _record(chunk=np.array([c // ranges], np.int32), at=np.array([c], np.int32), level=np.array([level], np.int32), first=np.array([unit], np.int32),
                                      data=pa.array([total[c].tobytes()], pa.binary()))
                total.clear()

            if unit == ONES:  # every chunk is scored, also where nothing deviates
                for _, c, _, _ in mine:
                    yield _record(chunk=np.array([c // ranges], np.int32), at=np.array([c], np.int32), level=np.array([-1], np.int32), first=np.array([ONES], np.int32),
                                  data=pa.array([b""], pa.binary()))
            level = 0
            for t in range(starts[-1] + converge + 1):
                if unit != ONES and level + 1 < len(starts) and t == starts[level + 1]:
                    yield from rows(level)
                    level += 1
                if unit != ONES or t in marks:
                    for began, v in state.items():
                        for side, c, a, b in mine:
                            if side == (began + t) % 2:
                                if c in total:
                                    total[c] += v[a:b]
                                else:
                                    total[c] = v[a:b].astype(np.float32)
                if unit == ONES and t in marks:
                    yield from rows(marks.index(t))
                if unit == ONES and t >= max(marks, default=0):
                    return
                if not any((np.maximum(v.max(axis=0), -v.min(axis=0)) > engine.ROUND_OFF / 4 * keep ** min(t, starts[-1]) * top * rests[(began + t) % 2]).any() for began, v in state.items()):
                    break
                new = {}
                for began in list(state):
                    side, v = (began + t) % 2, state.pop(began)
                    v *= (keep / degree[side])[:, None]
                    new[began] = halves[1 - side].product(v)
                    if t % 4 == 0:  # deviations sum to zero but for round-off, which would be all that is left of them
                        new[began] -= rest.value[1 - side] * new[began].sum(axis=0)
                    del v
                state = new
            else:
                raise engine.NotConverged(f"deviations are left after {converge} steps")
            yield from rows(level)

        units = [*([ONES] if marks else []), *range(0, len(columns), COLUMNS)]
        return self._units(units).mapInArrow(work, "chunk int, at int, level int, first int, data binary")

    def _passes(self, columns: int, starts: list[int]) -> int:
        """Ranges that keep the levels of one of them below ``LEVEL_BYTES``."""
        depth = self.depth or 40
        used = sum(s <= depth for s in starts)
        # a level of one step is on one side only
        each = sum(1 if a + 1 == b else 2 for a, b in zip(starts[:used], [*starts[1:], starts[-1] + 2][:used]))
        both = [] if self.inputs is None and not all(len(g[0]) for g in self.given) else [2 * used]
        return max(1, -(-4 * columns * max([each, *both]) * self.n_nodes // 2 // LEVEL_BYTES))

    def score(self, problems: int, most: int, plans: list, tol: float, converge: int) -> DataFrame:
        """``(plan, p, sse)``: squared error of every problem under every plan."""
        return self._score(list(range(problems)), most, plans, converge)

    def _score(self, columns, most, plans, converge) -> DataFrame:
        prepared = [_prepared(p, most) for p in plans]
        marks = sorted({m for p in prepared for m in p.marks})
        starts = sorted({0, *marks})
        mass, wide, high, chunks = self.mass(columns), len(columns), self.high, _chunks(self.high)
        steady = _steady(mass, starts, self.keep)  # (side, level, column)
        ones = _steady_at(np.array([[float(n)] for n in high]), marks, self.keep)  # (side, mark)
        shared, rest, s0 = self.spark.sparkContext.broadcast((prepared, steady, ones)), self.spark.sparkContext.broadcast(self.rest), 1.0 / max(1, self.n_nodes)

        def work(batches):
            by_chunk: dict[int, list] = {}
            for b in batches:
                for n in range(b.num_rows):
                    by_chunk.setdefault(b.column("at")[n].as_py(), []).append((b.column("level")[n].as_py(), b.column("first")[n].as_py(), b.column("data")[n].as_buffer()))
            plans, steady, ones = shared.value
            for c, own in by_chunk.items():
                side, a, b = chunks[c]
                blocks, at, ones_at, width = [], {}, {}, 1
                for level, first, data in sorted((x for x in own if x[0] >= 0), key=lambda x: x[:2]):
                    block = np.frombuffer(data, np.float32).reshape(b - a, -1)
                    blocks.append(block)
                    if first == ONES:
                        ones_at[level] = width
                    else:
                        at.setdefault(level, np.full(wide, -1))[first : first + block.shape[1]] = np.arange(width, width + block.shape[1])
                    width += block.shape[1]
                gram = np.zeros((width, width))
                for s in range(0, b - a, SLICE):
                    m = np.concatenate([rest.value[side][a + s : min(b, a + s + SLICE)], *(x[s : s + SLICE] for x in blocks)], axis=1, dtype=np.float64)
                    gram += m.T @ m
                deep = max([starts[level] for level in at], default=0)
                yield _record(plan=np.array([-1], np.int32), p=np.array([deep], np.int32), sse=np.zeros(1))
                for k, plan in enumerate(plans):
                    sse = _errors(gram, plan, starts, marks, at, ones_at, steady[side], ones[side], s0, wide)
                    yield _record(plan=np.full(len(sse), k, np.int32), p=np.arange(len(sse), dtype=np.int32), sse=sse)

        _clean(self.spark)
        schema, ranges = "plan int, p int, sse double", self._passes(wide, starts)
        found, depth, seen = {k: np.zeros(p.k) for k, p in enumerate(prepared)}, 0, set()
        for r in range(ranges):
            rows = self._levels(columns, starts, marks, ranges, r, converge)
            parts = -(-len(chunks) // ranges)
            scored = rows.repartitionById(parts, F.col("chunk")).drop("chunk").mapInArrow(work, schema)
            table = _apart(scored, DataFrame.toArrow)
            for plan, p, sse in zip(*(table[c].to_numpy() for c in ("plan", "p", "sse"))):
                if plan < 0:
                    depth = max(depth, int(p))
                else:
                    found[plan][p] += sse
            del rows, scored, table
            _clean(self.spark)
        self.depth = max(depth + 1, self.depth or 0)
        rows = [(k, p, float(v)) for k, own in found.items() for p, v in enumerate(own)]
        return self.spark.createDataFrame(rows, schema)

    def decoded(self, m: np.ndarray, r: np.ndarray, steps: list[int], make, schema: str) -> DataFrame:
        """Lanes of the real columns ``m`` (problems x columns) run for ``steps`` and decoded by ``r`` (columns x problems);
        ``make(ids, x)`` gives a record of the estimates (nodes x problems) of some nodes. Lanes go to where they are decoded as
        they are, in double precision."""
        opened, keep, high, chunks, s0 = self._opened(), self.keep, self.high, _chunks(self.high), 1.0 / max(1, self.n_nodes)
        budget, drive, sparse = np.array(steps), self.drive, self.inputs is None
        ranges = max(1, -(-8 * m.shape[1] * self.n_nodes // LEVEL_BYTES))

        def lanes_of(part):
            def work(batches):
                unit, halves, degree, ids, forcing = opened(batches)
                if unit is None:
                    return
                own, left, f = m[:, unit : unit + COLUMNS], budget[unit : unit + COLUMNS], []
                if sparse:
                    for n, (place, problem, value) in zip(high, shared.value[2]):
                        f.append(np.stack([np.bincount(place, weights=drive * value * c[problem], minlength=n) for c in own.T], axis=1) if len(place) else None)
                else:
                    f = [0.0, 0.0]
                    for a in range(0, len(own), COLUMNS):
                        few = range(a, min(a + COLUMNS, len(own)))
                        f = [have + new @ own[few] for have, new in zip(f, forcing(list(few)))]
                for began in (0, 1):  # what is on one side is on the other after a step
                    x = np.repeat(s0 * own.sum(axis=0)[None, :], high[began], axis=0)
                    for t in range(int(left.max()) + 1):
                        side = (began + t) % 2
                        if t:
                            x *= (keep / degree[1 - side])[:, None]
                            x = halves[side].product(x)
                            if f[side] is not None:
                                x += f[side]
                        done = np.flatnonzero(left == t)
                        for c, (of, a, b) in enumerate(chunks):
                            if len(done) and of == side and c % ranges == part:
                                yield _record(chunk=np.array([c // ranges], np.int32), at=np.array([c], np.int32), level=np.array([t], np.int32), first=np.array([unit], np.int32),
                                              data=pa.array([np.ascontiguousarray(x[a:b, done]).tobytes()], pa.binary()))

            return work

        def decode(batches):
            lanes: dict[int, np.ndarray] = {}
            for batch in batches:
                for n in range(batch.num_rows):
                    c, t, unit = (batch.column(name)[n].as_py() for name in ("at", "level", "first"))
                    _, a, b = chunks[c]
                    done = unit + np.flatnonzero(budget[unit : unit + COLUMNS] == t)
                    lanes.setdefault(c, np.empty((b - a, m.shape[1])))[:, done] = np.frombuffer(batch.column("data")[n].as_buffer()).reshape(b - a, -1)
            for c, y in lanes.items():
                side, a, b = chunks[c]
                yield make(shared.value[0][side][a:b], y @ r)

        shared, out = self.shared, None
        for part in range(ranges):
            _clean(self.spark)
            rows = self._units(list(range(0, m.shape[1], COLUMNS))).mapInArrow(lanes_of(part), "chunk int, at int, level int, first int, data binary")
            found = _apart(rows.repartitionById(-(-len(chunks) // ranges), F.col("chunk")).drop("chunk").mapInArrow(decode, schema), lambda df: materialise(df, "decoded"))
            out = found if out is None else out.unionByName(found)
        return out

    def tau(self, problems: list[int], most: int, tol: float, converge: int) -> np.ndarray:
        """Mean over ``problems`` of the squared norm of their residuals after 0..most steps: errors of stopping them all there."""
        from softlanes.operators.scoring import Plan

        one = np.eye(len(problems))
        got = self._score(problems, most, [Plan((), one, np.full(len(problems), m), one) for m in range(most + 1)], converge)
        out = np.zeros(most + 1)
        for row in got.groupBy("plan").agg(F.avg("sse").alias("sse")).collect():
            out[row.plan] = row.sse
        return out


def _chunks(high: list[int]) -> list[tuple[int, int, int]]:
    return [(side, a, min(n, a + ROWS)) for side, n in enumerate(high) for a in range(0, n, ROWS)]


def _sums(spark, recipe: HashInputs, ids: np.ndarray) -> np.ndarray:
    """Of every problem, the sum of the values that the recipe gives to ``ids``."""
    shared, parts = spark.sparkContext.broadcast(ids), -(-len(ids) // ROWS)

    def work(batches):
        for b in batches:
            for part in b.column("id").to_pylist():
                sums = recipe.values(recipe.raw(shared.value[part * ROWS : (part + 1) * ROWS])).sum(axis=0)
                yield _record(p=np.arange(recipe.k, dtype=np.int32), v=sums)

    out = np.zeros(recipe.k)
    for row in spark.range(0, parts, 1, min(parts, 2 * spark.sparkContext.defaultParallelism)).mapInArrow(work, "p int, v double").groupBy("p").agg(F.sum("v").alias("v")).collect():
        out[row.p] = row.v
    return out


def _apart(df: DataFrame, action):
    """What ``action`` makes of ``df``, every unit of its union in a task of its own: a union of single partitions is one else."""
    conf, name = df.sparkSession.conf, "spark.sql.unionOutputPartitioning"
    before = conf.get(name, "true")
    conf.set(name, "false")
    try:
        return action(df)
    finally:
        conf.set(name, before)


def _clean(spark) -> None:
    """Have the files of shuffles deleted that nothing will read."""
    gc.collect()
    spark._jvm.System.gc()


def _steady_at(mass: np.ndarray, marks: list[int], keep: float) -> np.ndarray:
    """What ``mass`` on either side has become after each of ``marks`` steps (sides x marks)."""
    return np.array([[keep**m * mass[(side - m) % 2][0] for m in marks] for side in (0, 1)])


def _steady(mass: np.ndarray, starts: list[int], keep: float) -> np.ndarray:
    """Multiples of ``rest`` in the sums from each of ``starts`` on to the next, the last without end (sides x starts x columns)."""
    out = np.zeros((2, len(starts), mass.shape[1]))
    for side in (0, 1):
        for n, (a, b) in enumerate(zip(starts, [*starts[1:], starts[-1] + 2])):
            for t in range(a, b):
                out[side, n] += keep**t * mass[(side - t) % 2]
        out[side, -1] /= 1 - keep**2
    return out


def _errors(gram, plan, starts, marks, at, ones_at, steady, ones, s0, wide) -> np.ndarray:
    """Squared errors of a plan's problems on nodes of one side, from the products of their columns: estimates are lanes stopped at
    their steps, so of what inputs give after t steps they have the lanes that went on beyond t, and truth has all."""
    plain = plan.diagonal is not None
    k, of = plan.k, len(plan.mixes[0][0])
    if plain:
        both = share = plan.diagonal
        one = np.ones(of)
    else:
        both, one = [left.astype(np.longdouble) @ right for left, right in plan.mixes], np.eye(of, k) if plan.mix is None else plan.mix
        share = [left.sum(axis=0) @ right for left, right in plan.mixes]  # of what is left of where they started
    after, left, weight = -one.astype(np.longdouble), list(zip(plan.marks, both)), []
    for s in starts[::-1]:
        while left and left[-1][0] > s:
            after = after + left.pop()[1]
        weight.insert(0, after.astype(float))
    rest = sum((s[:of] * w if plain else s[:of] @ w) for s, w in zip(steady, weight))
    rest = rest + s0 * sum(ones[marks.index(m)] * c for m, c in zip(plan.marks, share))
    coefs, places = [rest[None, :]], [np.zeros(1, np.intp)]
    for m, c in zip(plan.marks, share):
        if marks.index(m) in ones_at:
            coefs.append(s0 * c[None, :])
            places.append(np.array([ones_at[marks.index(m)]]))
    if plain:
        common, columns = np.concatenate(places), np.arange(of)
        levels = [(at[n], w) for n, w in enumerate(weight) if n in at]
        c = np.concatenate([*coefs, *(np.where(p[:of] >= 0, w, 0.0)[None, :] for p, w in levels)])
        spots = np.concatenate([np.repeat(common[:, None], of, axis=1), *(np.maximum(p[:of], 0)[None, :] for p, _ in levels)])
        return np.maximum(0.0, np.array([c[:, p] @ gram[np.ix_(spots[:, p], spots[:, p])] @ c[:, p] for p in columns]))
    for n, w in enumerate(weight):
        if n in at:
            known = at[n][:of] >= 0
            coefs.append(w[known])
            places.append(at[n][:of][known])
    c, spots = np.concatenate(coefs), np.concatenate(places)
    own = gram if len(spots) == len(gram) and (spots == np.arange(len(gram))).all() else gram[np.ix_(spots, spots)]
    return np.maximum(0.0, (c * (own @ c)).sum(axis=0))


def cut(edges: DataFrame, blocks: DataFrame, ids: np.ndarray, degree: np.ndarray, d: float, inputs) -> Halves | None:
    """The restart walk with ``d`` over the packed links ``blocks``; None where links do not only join odd nodes to even ones, or are
    too many for a task."""
    spark, total = edges.sparkSession, int(degree.sum())
    odd = ids % 2 == 1
    if total > MOST_EDGES or edges.where(F.pmod("src", F.lit(2)) == F.pmod("dst", F.lit(2))).limit(1).count():
        return None
    nodes = [np.flatnonzero(~odd), np.flatnonzero(odd)]
    nodes = [n[np.argsort(-degree[n], kind="stable")] for n in nodes]
    place = np.empty(len(ids), np.int32)
    for own in nodes:
        place[own] = np.arange(len(own), dtype=np.int32)
    where = spark.sparkContext.broadcast((odd, place))

    def split(batches):
        for b in batches:
            for m in range(b.num_rows):
                rows, own, cols = _unpack(b, m)
                side, local = where.value
                key = local[rows] // ROWS * 2 + side[rows]
                turn = np.argsort(key, kind="stable")
                starts, size = np.append(0, np.cumsum(own)), own[turn]
                begin = np.repeat(starts[:-1][turn] - np.append(0, np.cumsum(size)[:-1]), size)
                linked, ends = local[cols[begin + np.arange(len(cols))]], np.append(0, np.cumsum(size))
                for group in np.split(np.arange(len(turn)), np.flatnonzero(np.diff(key[turn])) + 1):
                    part = rows[turn[group]]
                    yield _record(key=pa.array([int(key[turn[group[0]]])], pa.int32()), **{c: pa.array([x.tobytes()], pa.binary()) for c, x in zip(
                        ("rows", "degree", "cols"), (local[part], size[group], linked[ends[group[0]] : ends[group[-1] + 1]]))})

    def joined(pdf: pd.DataFrame) -> pd.DataFrame:
        rows, own, cols = (np.concatenate([np.frombuffer(x, np.int32) for x in pdf[c]]) for c in ("rows", "degree", "cols"))
        turn = np.argsort(rows, kind="stable")
        starts, size = np.append(0, np.cumsum(own)), own[turn]
        begin = np.repeat(starts[:-1][turn] - np.append(0, np.cumsum(size)[:-1]), size)
        cols, key = cols[begin + np.arange(len(cols))], int(pdf["key"].iloc[0])
        return pd.DataFrame({"side": [key % 2], "first": [int(rows.min())], "degree": [size.tobytes()], "cols": [levelled(size, cols).tobytes()]})

    fragments = blocks.mapInArrow(split, "key int, rows binary, degree binary, cols binary")
    links = materialise(fragments.groupBy("key").applyInPandas(joined, "side int, first int, degree binary, cols binary"), "halves")
    release(blocks)
    recipe = inputs if isinstance(inputs, HashInputs) else None
    totals = given = None
    if recipe is not None:
        sums = [_sums(spark, recipe, ids[own]) for own in nodes]
        given, totals = np.array(sums), np.sum(sums, axis=0)
    else:
        t = inputs.groupBy("i", "p").agg(F.sum("v").alias("v")).toArrow()
        i, p, v = (t[c].to_numpy() for c in ("i", "p", "v"))
        near = np.minimum(np.searchsorted(ids, i), len(ids) - 1)
        known = ids[near] == i  # inputs at no node are left out
        near, p, v = near[known], p[known].astype(np.int32), v[known]
        given = [(place[near[own]], p[own], v[own]) for own in (~odd[near], odd[near])]
    return Halves(spark, links, [ids[own] for own in nodes], [degree[own].astype(np.float64) for own in nodes], 1 - d, d, recipe, totals, given)
