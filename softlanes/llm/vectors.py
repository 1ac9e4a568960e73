"""Embedding near-deduplication on a robust-pruned flat graph.

Distinct vectors are dealt to overlapping cluster shards (each to its ``overlap`` nearest centroids, fitted
on a bounded sample; shards that are overfull are clustered again). Every shard builds a flat proximity
graph, its adjacency lists robust-pruned so that long edges stay; the lists of a vector from all its shards
are united. Then every vector is searched for from its shard's medoid: greedily until the neighbourhood
is reached, then expanding every node in range until no node in range is left. The expansion follows the
united lists out of the shard: every node has one cell, its first shard, and a vector visits the cells of
the nodes found in range and of those they list, round by round, until no cell is new; a vector that
is found visits the cell of its finder too. A visit compares the vector with the whole cell in double precision,
so each pair counts once at either end, wherever it was found. The recall of links is audited against brute
force on sampled queries; where it is short, the build is repeated with one more overlap, and where three
builds are short, the whole table is compared exactly, block by block, which always ends with every link.

Exactly equal vectors are one node with a weight; pairs are counted at the node, never written out, and a
visited cell writes a spanning forest of its links.

Edge cases: null, empty and zero vectors and vectors with null or non-finite components have no links and
are their own component; vectors of another dimension than a shard's are never compared with it; repeated
rows of one id are separate vectors; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import connected_components, load, materialise

SHARD = 1200
MOST_SHARD = 6000
MOST_CENTROIDS = 4096
MOST_VISITS = 16384  # vectors that visit a cell, or are dealt to centroids, in one task
DEPTHS = 3  # rounds of clustering
SPREAD = 1 + MOST_CENTROIDS  # numbers kept free for a shard's own shards
BLOCK_NUMBERS = 4_000_000  # numbers of a block of vectors that goes to every task in the exact comparison
MARGIN = 1e-6  # single-precision slack of the search before the check in double precision


def unit(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 6) -> np.ndarray:
    """Spherical k-means centroids (float32, unit length)."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].astype(np.float32)
    for _ in range(rounds):
        at = np.concatenate([(x[i : i + 4096] @ c.T).argmax(axis=1) for i in range(0, len(x), 4096)])
        total = np.zeros_like(c)
        np.add.at(total, at, x.astype(np.float32))
        norm = np.sqrt((total * total).sum(axis=1, keepdims=True))
        c = np.where(norm > 0, total / np.maximum(norm, 1e-12), c).astype(np.float32)
    return c


def pruned_graph(x: np.ndarray, pool: int = 48, degree: int = 16, alpha: float = 1.2) -> np.ndarray:
    """Adjacency (n, degree), -1 where unused: of each node's nearest candidates, nearest first, those that no
    chosen neighbour is ``alpha`` times nearer to than the node is."""
    n = len(x)
    out = np.full((n, degree), -1, np.int64)
    pool = min(pool, n - 1)
    if pool < 1:
        return out
    for i in range(0, n, 256):
        own = x[i : i + 256]
        near = own @ x.T
        near[np.arange(len(own)), np.arange(i, i + len(own))] = -2
        cand = np.argpartition(-near, pool - 1, axis=1)[:, :pool]
        cos = np.take_along_axis(near, cand, 1)
        order = np.argsort(-cos, axis=1, kind="stable")
        cand, cos = np.take_along_axis(cand, order, 1), np.take_along_axis(cos, order, 1)
        among = np.matmul(x[cand], x[cand].transpose(0, 2, 1))
        far = np.sqrt(np.maximum(0, 2 - 2 * cos))
        between = np.sqrt(np.maximum(0, 2 - 2 * among))
        alive = np.ones(cand.shape, bool)
        rows = np.arange(len(own))
        for d in range(degree):
            first = alive.argmax(axis=1)
            some = alive[rows, first]
            if not some.any():
                break
            out[i : i + 256, d] = np.where(some, cand[rows, first], -1)
            alive &= ~(some[:, None] & (alpha * between[rows, first] <= far))
            alive[rows, first] = False
    return out


def range_search(x: np.ndarray, graph: np.ndarray, queries: np.ndarray, start: int, low: float, beam: int = 32) -> list[np.ndarray]:
    """For each query row of ``x``: nodes with cosine >= low that a greedy search from ``start`` reaches.

    Each step every query opens its best unopened nodes that are in range, or else in the best ``beam``.
    """
    n, out = len(x), []
    for i in range(0, len(queries), 128):
        q = queries[i : i + 128]
        cos = np.full((len(q), n), -2.0, np.float32)
        opened = np.zeros((len(q), n), bool)
        cos[:, start] = x[q] @ x[start]
        while True:
            waiting = (cos > -2) & ~opened
            floor = np.partition(cos, n - min(beam, n), axis=1)[:, n - min(beam, n)]
            waiting &= cos >= np.minimum(low, np.maximum(floor, -1.5))[:, None]
            who, node = np.nonzero(waiting)
            if not len(who):
                break
            score = cos[who, node]
            order = np.lexsort((-score, who))
            who, node, score = who[order], node[order], score[order]
            first = np.r_[True, who[1:] != who[:-1]]
            place = np.arange(len(who)) - np.maximum.accumulate(np.where(first, np.arange(len(who)), 0))
            go = (place < 4) | (score >= low)
            who, node = who[go], node[go]
            opened[who, node] = True
            to = graph[node]
            w = np.repeat(who, to.shape[1])
            t = to.ravel()
            ok = (t >= 0)
            ok[ok] = cos[w[ok], t[ok]] == -2
            code = np.unique(w[ok] * n + t[ok])
            w, t = code // n, code % n
            for a in range(0, len(w), 65536):
                ws, ts = w[a : a + 65536], t[a : a + 65536]
                cos[ws, ts] = np.maximum(-1, np.einsum("ij,ij->i", x[q[ws]], x[ts]))
        for r in range(len(q)):
            found = np.flatnonzero(cos[r] >= low)
            out.append(found[found != q[r]])
    return out


def _matrix(vectors: pd.Series) -> np.ndarray:
    return np.stack(vectors.to_numpy()) if len(vectors) else np.empty((0, 0))


def distinct_vectors(df: DataFrame, vec_id: str, embedding: str) -> tuple[DataFrame, DataFrame]:
    """(members(vec_id, v), nodes(node, v, n)): usable vectors as arrays of doubles, and each distinct one once.

    ``node`` is the smallest id of its copies; copies are counted map-side before the shuffle.
    """
    v = F.col(embedding).cast("array<double>")
    usable = F.coalesce(
        (F.size(v) > 0) & ~F.exists(v, lambda a: a.isNull() | F.isnan(a) | (F.abs(a) == float("inf"))) & F.exists(v, lambda a: a != 0), F.lit(False)
    )
    members = df.select(F.col(vec_id).alias("vec_id"), F.when(usable, v).alias("v"))
    nodes = members.where("v IS NOT NULL").groupBy("v").agg(F.min("vec_id").alias("first_id"), F.count("*").alias("n"))
    return members, nodes


def _fit_centroids(crowded: DataFrame, seed: int) -> DataFrame:
    """``(shard, count, centroids binary)`` of the shards of ``crowded(node, v, shard, count, k)``, each fitted in a task of
    its own on about ``40 k`` of its vectors."""

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        c = kmeans(unit(_matrix(pdf["v"])).astype(np.float32), int(pdf["k"].iloc[0]), seed)
        return pd.DataFrame({"shard": pdf["shard"].iloc[:1], "count": pdf["count"].iloc[:1], "centroids": [c.tobytes()]})

    coin = F.pmod(F.xxhash64("node", F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    return crowded.where(coin < 40.0 * F.col("k") / F.col("count")).groupBy("shard").applyInPandas(fit, "shard long, count long, centroids binary")


def _assign(crowded: DataFrame, centroids: DataFrame, overlap: int) -> DataFrame:
    """``crowded(node, v, n, shard)`` dealt to the ``overlap`` nearest centroids of its shard: new shards under the old one's
    number. A shard's rows meet its centroids in parts of about ``MOST_VISITS`` rows."""

    def deal(rows: pd.DataFrame, fitted: pd.DataFrame) -> pd.DataFrame:
        if not len(rows):
            return rows[["node", "v", "n", "shard"]]
        base = int(rows["shard"].iloc[0]) * SPREAD + 1
        if not len(fitted):  # no vector was picked: the shard is divided further down, or by hash
            return rows.assign(shard=base)[["node", "v", "n", "shard"]]
        x = unit(_matrix(rows["v"])).astype(np.float32)
        near = x @ np.frombuffer(fitted["centroids"].iloc[0], np.float32).reshape(-1, x.shape[1]).T
        k = min(overlap, near.shape[1])
        again = rows.loc[rows.index.repeat(k), ["node", "v", "n"]].copy()
        again["shard"] = base + np.argpartition(-near, k - 1, axis=1)[:, :k].ravel()
        return again

    parts = F.ceil(F.col("count") / MOST_VISITS).cast("int")
    placed = crowded.select("node", "v", "n", "shard", F.pmod(F.xxhash64("node", F.lit(3)), parts).cast("int").alias("part"))
    spread = centroids.select("shard", "centroids", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"))
    both = placed.groupBy("shard", "part").cogroup(spread.groupBy("shard", "part"))
    return both.applyInPandas(deal, "node long, v array<double>, n long, shard long")


def overlapping_shards(nodes: DataFrame, overlap: int, seed: int = 1) -> DataFrame:
    """``(node, v, n, shard)``: clusters of about ``SHARD`` nodes, each node in ``overlap`` of them; none over ``MOST_SHARD``.

    Shards that are crowded are clustered again, all of them in one job; what clustering cannot divide in
    ``DEPTHS`` rounds is divided by hash, and left to the search across shards.
    """
    rows = nodes.select("node", "v", "n", F.size("v").cast("long").alias("shard"))  # one shard per dimension
    for depth in range(DEPTHS + 1):
        most = MOST_SHARD if depth else SHARD
        sizes = materialise(rows.groupBy("shard").count().where(F.col("count") > most), "vector-crowded")
        if sizes.isEmpty():
            break
        crowded = rows.join(sizes, "shard")
        if depth < DEPTHS:
            share = overlap if depth == 0 else 1
            wanted = F.least(F.lit(MOST_CENTROIDS), F.greatest(F.lit(2), F.ceil(F.col("count") * share / SHARD).cast("int")))
            centroids = materialise(_fit_centroids(crowded.withColumn("k", wanted), seed + depth), "vector-centroids")
            dealt = _assign(crowded, centroids, overlap if depth == 0 else 2)
        else:
            piece = F.pmod(F.xxhash64("node", F.lit(seed)), F.least(F.lit(MOST_CENTROIDS), F.ceil(F.col("count") / SHARD)))
            dealt = crowded.select("node", "v", "n", (F.col("shard") * SPREAD + 1 + piece).cast("long").alias("shard"))
        calm = rows.join(sizes, "shard", "left_anti").select("node", "v", "n", (F.col("shard") * SPREAD).alias("shard"))
        rows = materialise(calm.unionByName(dealt), "vector-shards")
    return rows


def united_graph(shards: DataFrame, threshold: float) -> DataFrame:
    """``(node, cell, near array<long>, out array<long>)``: each node's first shard, its pruned lists from all its
    shards, and the cells of those listed that a vector in range of the node can have in range too."""
    wide = 2 * threshold * threshold - 1 - MARGIN if threshold > 0 else -2.0  # twice the angle
    cells = shards.groupBy("node").agg(F.min("shard").alias("cell"))

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, cell = pdf["node"].to_numpy(), pdf["cell"].to_numpy()
        x = unit(_matrix(pdf["v"])).astype(np.float32)
        graph = pruned_graph(x)
        lists = [g[g >= 0] for g in graph]
        out = [np.unique(cell[g[x[g] @ x[i] >= wide]]) for i, g in enumerate(lists)]
        return pd.DataFrame({"node": ids, "cell": cell, "near": pd.Series([ids[g] for g in lists], dtype=object), "out": pd.Series(out, dtype=object)})

    lists = shards.join(cells, "node").groupBy("shard").applyInPandas(build, "node long, cell long, near array<long>, out array<long>")
    united = [F.array_distinct(F.flatten(F.collect_list(c))).alias(c) for c in ("near", "out")]  # degree x shards at most
    return lists.groupBy("node").agg(F.min("cell").alias("cell"), *united)


def search_cells(shards: DataFrame, graph: DataFrame, threshold: float) -> DataFrame:
    """``(node, cells array<long>)`` per node and shard: the cells of the nodes found in range there and of those they list."""

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("node", ignore_index=True)
        ids = pdf["node"].to_numpy()
        x = unit(_matrix(pdf["v"])).astype(np.float32)
        n = len(ids)
        width = max(1, max(map(len, pdf["near"])))
        adjacency = np.full((n, 2 * width), -1, np.int64)
        for i, near in enumerate(pdf["near"]):
            at = np.minimum(np.searchsorted(ids, near), n - 1)
            at = at[ids[at] == near]
            adjacency[i, : len(at)] = at
        # some backward edges too, so that nodes nobody lists are reached
        fill = np.full(n, width)
        for d in range(min(width, 8)):
            source = np.flatnonzero(adjacency[:, d] >= 0)
            for s, t in zip(source.tolist(), adjacency[source, d].tolist()):
                if fill[t] < 2 * width:
                    adjacency[t, fill[t]] = s
                    fill[t] += 1
        start = int((x @ x.mean(axis=0)).argmax())
        found = range_search(x, adjacency, np.arange(n), start, threshold - MARGIN)
        targets, leads = _leads([np.append(o, c) for o, c in zip(pdf["out"], pdf["cell"])])
        some = [i for i, near in enumerate(found) if len(near)]
        return pd.DataFrame({"node": ids[some], "cells": pd.Series([targets[leads[found[i]].any(axis=0)] for i in some], dtype=object)})

    return shards.join(graph, "node").groupBy("shard").applyInPandas(search, "node long, cells array<long>")


def _leads(lists) -> tuple[np.ndarray, np.ndarray]:
    """(distinct values, boolean matrix of which list has which)."""
    lengths = [len(o) for o in lists]
    values, at = np.unique(np.concatenate([np.asarray(o, np.int64) for o in lists]), return_inverse=True)
    has = np.zeros((len(lengths), len(values)), bool)
    has[np.repeat(np.arange(len(lengths)), lengths), at] = True
    return values, has


def _merged(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """``root`` (smallest place of each tree) after the links a - b."""
    while True:
        ra, rb = root[a], root[b]
        apart = ra != rb
        if not apart.any():
            return root
        a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
        root = root.copy()
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while (root[root] != root).any():
            root = root[root]


def compared(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, weight: np.ndarray, threshold: float, each=None):
    """(links of each q, roots of x's rows then q's as ids): every row of ``q`` against every row of ``x``, both of unit
    length; ``each(first row of q, hits)`` is called by block."""
    links, root = np.zeros(len(q_ids), np.int64), np.arange(len(ids) + len(q_ids))
    step = max(1, min(512, 4_000_000 // max(1, len(ids))))
    for a in range(0, len(q_ids), step):
        hit = (q[a : a + step] @ x.T >= threshold) & (q_ids[a : a + step, None] != ids[None, :])
        links[a : a + step] = (hit * weight[None, :]).sum(axis=1)
        row, col = np.nonzero(hit)
        root = _merged(root, len(ids) + a + row, col)
        if each:
            each(a, hit)
    return links, np.r_[ids, q_ids][root]


def visit_cells(asked: DataFrame, placed: DataFrame, threshold: float) -> DataFrame:
    """``(node, links, root, cells)``: each of ``asked(node, cell)`` compared with all of ``placed(node, v, n, cell, out)``
    in the cell: weight linked to, its tree, and the cells that come up; members that are found tell the finders' cells."""
    parts = asked.groupBy("cell").agg(F.ceil(F.count("*") / MOST_VISITS).cast("int").alias("parts"))
    queries = asked.join(parts, "cell").select("node", "cell", F.pmod(F.xxhash64("node"), "parts").cast("int").alias("part")).join(
        placed.select("node", F.col("v").alias("q"), F.col("cell").alias("home")), "node")
    members = placed.join(parts, "cell").select(
        "node", F.col("v").alias("x"), "n", "out", "cell", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))

    def visit(queries: pd.DataFrame, members: pd.DataFrame) -> pd.DataFrame:
        if not len(queries) or not len(members):
            return pd.DataFrame({"node": [], "links": [], "root": [], "cells": pd.Series([], dtype=object)})
        q_ids, ids = queries["node"].to_numpy(), members["node"].to_numpy()
        targets, leads = _leads(members["out"])
        home, place = np.unique(queries["home"].to_numpy(), return_inverse=True)
        finders, cells = np.zeros((len(ids), len(home)), bool), []

        def each(a: int, hit: np.ndarray) -> None:
            row, col = np.nonzero(hit)
            finders[col, place[a + row]] = True
            cells.extend(targets[r] for r in hit.astype(np.float32) @ leads.astype(np.float32) > 0)

        links, root = compared(q_ids, unit(_matrix(queries["q"])), ids, unit(_matrix(members["x"])), members["n"].to_numpy(), threshold, each)
        met = np.flatnonzero(finders.any(axis=1))
        return pd.DataFrame({
            "node": np.r_[q_ids, ids[met]], "links": np.r_[links, np.zeros(len(met), np.int64)], "root": np.r_[root[len(ids) :], root[met]],
            "cells": pd.Series([*cells, *(home[finders[i]] for i in met)], dtype=object),
        })

    both = queries.groupBy("cell", "part").cogroup(members.groupBy("cell", "part"))
    return both.applyInPandas(visit, "node long, links long, root long, cells array<long>")


def follow_links(start: DataFrame, graph: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """``(node, links, root)`` per visit of a node to a cell, from the cells of ``start`` on until no visit is new."""
    placed = materialise(nodes.join(graph.select("node", "cell", "out"), "node"), "vector-cells")
    asked = materialise(start.select("node", F.explode("cells").alias("cell")).distinct(), "vector-visits")
    every, found = asked, nodes.sparkSession.createDataFrame([], "node long, links long, root long")
    while not asked.isEmpty():
        got = materialise(visit_cells(asked, placed, threshold), "vector-links")
        found = found.unionByName(got.select("node", "links", "root"))
        asked = materialise(got.select("node", F.explode("cells").alias("cell")).distinct().join(every, ["node", "cell"], "left_anti"), "vector-visits")
        every = every.unionByName(asked)
    return found


def audited_recall(nodes: DataFrame, counted: DataFrame, threshold: float, queries: int = 200) -> float:
    """Share of the links of ``queries`` sampled vectors (by hash, linked ones too) that ``counted(node, links)`` has."""
    total = max(1, nodes.count())
    pick = F.pmod(F.xxhash64("node", F.lit(23)), F.lit(1 << 30)) < int(min(1.0, queries / total) * (1 << 30))
    asked = nodes.where(pick).select("node", "v").union(
        counted.where("links > 0").orderBy(F.xxhash64("node", F.lit(29))).limit(queries).join(nodes, "node").select("node", "v")
    ).dropDuplicates(["node"]).toPandas()
    if not len(asked):
        return 1.0
    by_dim = {d: (g["node"].to_numpy(), unit(_matrix(g["v"]))) for d, g in asked.groupby(asked["v"].map(len))}

    def brute(batches):
        for pdf in batches:
            for d, own in pdf.groupby(pdf["v"].map(len)):
                if d in by_dim:
                    ids, q = by_dim[d]
                    hit = (q @ unit(_matrix(own["v"])).T >= threshold) & (ids[:, None] != own["node"].to_numpy()[None, :])
                    yield pd.DataFrame({"node": ids, "true": (hit * own["n"].to_numpy()[None, :]).sum(axis=1)})

    true = nodes.mapInPandas(brute, "node long, true long").groupBy("node").agg(F.sum("true").alias("true"))
    r = true.join(counted, "node", "left").agg(F.sum("true").alias("t"), F.sum(F.least(F.coalesce("links", F.lit(0)), "true")).alias("f")).first()
    return 1.0 if not r.t else r.f / r.t


def exact_links(nodes: DataFrame, threshold: float) -> DataFrame:
    """``(node, links, root)`` of all pairs: each block of vectors goes to every task and meets the whole table there,
    which is streamed; only counts and spanning forests are written."""
    found = nodes.sparkSession.createDataFrame([], "node long, links long, root long")
    sized = materialise(nodes.withColumn("d", F.size("v")), "vector-sizes")
    for r in sized.groupBy("d").count().collect():
        own = sized.where(F.col("d") == r.d).select("node", "v", "n")
        blocks = max(1, -(-r["count"] * r.d // BLOCK_NUMBERS))
        for b in range(blocks):
            picked = own.where(F.pmod(F.xxhash64("node"), F.lit(blocks)) == b).toPandas()
            if len(picked):
                shared = nodes.sparkSession.sparkContext.broadcast((picked["node"].to_numpy(), unit(_matrix(picked["v"])), picked["n"].to_numpy()))
                found = found.unionByName(materialise(own.mapInPandas(_against(shared, threshold), "node long, links long, root long"), "vector-exact"))
                shared.unpersist()
    return found


def _against(shared, threshold: float):
    def run(batches):
        ids, x, weight = shared.value
        for pdf in batches:
            if len(pdf):
                q_ids = pdf["node"].to_numpy()
                links, root = compared(q_ids, unit(_matrix(pdf["v"])), ids, x, weight, threshold)
                met = np.flatnonzero(root[: len(ids)] != ids)
                yield pd.DataFrame({"node": np.r_[q_ids, ids[met]], "links": np.r_[links, np.zeros(len(met), np.int64)], "root": np.r_[root[len(ids) :], root[met]]})

    return run


def near_duplicate_vectors(df: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", threshold: float = 0.9, overlap: int = 3, least_recall: float = 0.97) -> DataFrame:
    """``(vec_id, n_links, component_id, kept, audited_recall)``, one row per row of ``df``."""
    members, classes = distinct_vectors(df, vec_id, embedding)
    # a node needs a number of its own even where ids repeat or are null
    nodes = materialise(classes.withColumn("node", F.monotonically_increasing_id()), "vector-nodes")
    recall = 0.0
    for more in range(3):
        shards = overlapping_shards(nodes.select("node", "v", "n"), overlap + more)
        graph = materialise(united_graph(shards, threshold), "vector-graph")
        found = follow_links(search_cells(shards, graph, threshold), graph, nodes.select("node", "v", "n"), threshold)
        counted = found.groupBy("node").agg(F.sum("links").alias("links"))
        recall = audited_recall(nodes.select("node", "v", "n"), counted, threshold)
        if recall >= least_recall:
            break
    else:
        found = exact_links(nodes.select("node", "v", "n"), threshold)
        counted = found.groupBy("node").agg(F.sum("links").alias("links"))
        recall = audited_recall(nodes.select("node", "v", "n"), counted, threshold)
    parts = connected_components(found.select(F.col("node").alias("a"), F.col("root").alias("b")))
    per_node = (
        nodes.join(counted, "node", "left").join(parts, "node", "left")
        .select("node", "v", "n", "first_id", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("component", "node").alias("root"))
    )
    per_node = materialise(per_node, "vector-result")
    least = per_node.groupBy("root").agg(F.min("first_id").alias("component_id"))
    labelled = per_node.join(least, "root").select("v", (F.col("links") + F.col("n") - 1).alias("n_links"), "component_id")
    good = members.where("v IS NOT NULL").join(labelled, "v").select("vec_id", "n_links", "component_id")
    alone = members.where("v IS NULL").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return good.unionByName(alone).select(
        "vec_id", "n_links", "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept"), F.lit(float(recall)).alias("audited_recall")
    )


def op3_pruned_graph(spark, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(load(spark, sf_dir, "embeddings"))
