"""SimHash near-deduplication by covering locality-sensitive hashing.

Every text gets a 64-bit fingerprint: the majority bit of its word shingles' XXH64 hashes. Distinct
fingerprints are then sent to ``2**(radius+1) - 1`` tables, one per structured bit mask. Bit position i
owns a non-zero vector of ``radius+1`` bits, and mask v keeps the positions whose vector has an odd inner
product with v. At most ``radius`` differing positions cannot span the whole vector space, so some v is
orthogonal to all of them: in that table the two fingerprints agree, with certainty, not with high
probability. Colliding fingerprints are compared bit by bit.

Buckets larger than ``WIDE`` are keyed a second time, by a covering family over the bits their mask left
out, so every bucket is finished exactly and none is capped. A bucket writes a spanning forest of its
links where it is large, never all pairs.

Edge cases: null and empty texts have fingerprint zero, which links like any other; a text of fewer
words than a shingle is one shingle; repeated rows share their component; rows without an id get the
smallest id of their component, null if it has none; an empty table gives no rows; extra columns of any name
are kept by ``drop_near_duplicates``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import connected_components, load, located, materialise, smallest_row

WIDE = 2048
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_AT_ONCE = 1 << 16


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit majority fingerprint of one text."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) < shingle:
        hashes = [digest(b" ".join(words), seed)]
    else:
        hashes = [digest(b" ".join(s), seed) for s in zip(*(words[i:] for i in range(shingle)))]
    counts = np.zeros(64, np.int64)
    for i in range(0, len(hashes), _AT_ONCE):
        block = np.array(hashes[i : i + _AT_ONCE], dtype="<u8")
        counts += np.unpackbits(block.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = counts * 2 > len(hashes)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = 3) -> DataFrame:
    """``(doc_id long, at, fp long)``: each row's locator and its fingerprint as a signed long, one row per row of
    ``df``, which comes from ``located`` where the locator's column is called ``_at``; elsewhere it is null."""
    at = F.col("_at") if "_at" in df.columns else F.lit(None)
    place = "struct<file: string, row: bigint>"

    def run(batches):
        for batch in batches:
            fps = np.array([fingerprint(t.as_py(), shingle) for t in batch.column(2)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fps, pa.int64())], names=["doc_id", "at", "fp"])

    return df.select(F.col(doc_id).cast("long").alias("doc_id"), at.cast(place).alias("at"), F.col(text).alias("text")).mapInArrow(
        run, f"doc_id long, at {place}, fp long"
    )


def covering_masks(positions: list[int], radius: int) -> list[int]:
    """Unsigned masks over the given bit positions: any ``radius`` of them are all left out by some mask."""
    size = 1 << (radius + 1)
    own = {p: 1 + (i * 7) % (size - 1) for i, p in enumerate(positions)}
    return [sum(1 << p for p, m in own.items() if (m & v).bit_count() % 2) for v in range(1, size)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def forest(fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links (index pairs) that connect exactly what the links of at most ``radius`` bits connect."""
    n = len(fps)
    label = np.arange(n)
    froms, tos = [], []
    waiting = np.ones(n, bool)
    while waiting.any():  # breadth first from the first fingerprint that has no tree yet
        root = int(np.argmax(waiting))
        waiting[root] = False
        front = np.array([root])
        while len(front):
            rest = np.flatnonzero(waiting)
            reached = np.zeros(len(rest), bool)
            for i in range(0, len(front), 256):
                left = np.flatnonzero(~reached)
                if not len(left):
                    break
                near = np.bitwise_count(fps[front[i : i + 256], None] ^ fps[rest[left]][None, :]) <= radius
                reached[left] |= near.any(axis=0)
            front = rest[reached]
            waiting[front] = False
            froms.append(front)
            tos.append(np.full(len(front), root))
            label[front] = root
    return np.concatenate(froms), np.concatenate(tos)


def bucket_links(bucket: np.ndarray, fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal ``bucket``: all of them in short runs, a forest in long ones."""
    starts = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]])
    sizes = np.diff(np.r_[starts, len(bucket)])
    a, b = [], []
    short = np.repeat(sizes <= 32, sizes)
    run = np.repeat(np.arange(len(starts)), sizes)
    for d in range(1, int(min(32, sizes.max()))):
        hit = (run[d:] == run[:-d]) & short[d:]
        at = np.flatnonzero(hit)
        at = at[np.bitwise_count(fps[at] ^ fps[at + d]) <= radius]
        a.append(fps[at])
        b.append(fps[at + d])
    for s, k in zip(starts[sizes > 32], sizes[sizes > 32]):
        own = fps[s : s + k]
        x, y = forest(own, radius)
        a.append(own[x])
        b.append(own[y])
    none = np.empty(0, np.uint64)
    return np.concatenate([none, *a]), np.concatenate([none, *b])


def _links_of_buckets(keyed: DataFrame, keys: list[str], radius: int) -> DataFrame:
    """``(a, b)`` links between fingerprints that share all ``keys``; reads sorted partitions as a stream."""

    def run(batches):
        held_k, held_f = np.empty((0, len(keys)), np.int64), np.empty(0, np.uint64)

        def out(k, f):
            if len(f) < 2:
                return None
            edge = np.r_[True, (k[1:] != k[:-1]).any(axis=1)]
            a, b = bucket_links(np.cumsum(edge), f, radius)
            return pa.RecordBatch.from_arrays([pa.array(x.view(np.int64)) for x in (a, b)], names=["a", "b"]) if len(a) else None

        for batch in batches:
            k = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(len(keys))]).astype(np.int64)
            f = np.ascontiguousarray(batch.column(len(keys)).to_numpy(zero_copy_only=False)).astype(np.int64).view(np.uint64)
            k, f = np.vstack([held_k, k]), np.concatenate([held_f, f])
            if not len(f):
                continue
            last = int(np.argmax((k == k[-1]).all(axis=1)))  # the bucket that may go on in the next batch
            held_k, held_f = k[last:], f[last:]
            if (done := out(k[:last], f[:last])) is not None:
                yield done
        if (done := out(held_k, held_f)) is not None:
            yield done

    placed = keyed.select(*keys, "fp").repartition(*keys).sortWithinPartitions(*keys)
    return placed.mapInArrow(run, "a long, b long")


def near_links(distinct: DataFrame, radius: int = 3) -> DataFrame:
    """Links ``(a, b)`` that connect the same fingerprints as all pairs within ``radius`` bits do."""
    masks = covering_masks(list(range(64)), radius)
    tables = F.explode(F.array(*[
        F.struct(F.lit(i).cast("long").alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k")) for i, m in enumerate(masks)
    ])).alias("at")
    keyed = distinct.select("fp", tables).select("at.t", "at.k", "fp")
    sizes = keyed.groupBy("t", "k").count().where("count > 1")
    wide = materialise(sizes.where(F.col("count") > WIDE).select("t", "k"), "simhash-wide")
    if wide.isEmpty():
        return _links_of_buckets(keyed, ["t", "k"], radius)
    narrow = _links_of_buckets(keyed.join(wide, ["t", "k"], "left_anti"), ["t", "k"], radius)
    # in a wide bucket the masked bits agree: a second covering family over the others, table by table
    left_out = [[p for p in range(64) if not m >> p & 1] for m in masks]
    second = F.array(*[
        F.array(*[F.lit(_signed(m)) for m in covering_masks(left_out[t], radius)]) for t in range(len(masks))
    ])
    again = keyed.join(wide, ["t", "k"], "left_semi").select(
        "t", "k", "fp", F.posexplode(F.get(second, F.col("t").cast("int"))).alias("t2", "m2")
    ).select("t", "k", F.col("t2").cast("long").alias("t2"), F.expr("fp & m2").alias("k2"), "fp")
    return narrow.unionByName(_links_of_buckets(again, ["t", "k", "t2", "k2"], radius))


def components(prints: DataFrame, radius: int = 3) -> DataFrame:
    """``(fp, component_id, stays)`` for every distinct fingerprint of ``prints(doc_id, at, fp)``: the smallest id
    of its component and the locator of the row that stays, of the smallest id and then the smallest locator."""
    distinct = materialise(prints.groupBy("fp").agg(F.min(smallest_row("doc_id", "at")).alias("first")), "simhash-fp")
    links = connected_components(near_links(distinct.select("fp"), radius))
    rooted = distinct.join(links.withColumnRenamed("node", "fp"), "fp", "left").select(
        "fp", "first", F.coalesce("component", "fp").alias("root")
    )
    least = rooted.groupBy("root").agg(F.min("first").alias("least"))
    return rooted.join(least, "root").select("fp", F.col("least.doc_id").alias("component_id"), F.col("least.at").alias("stays"))


def near_dup_components(df: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = 3, radius: int = 3) -> DataFrame:
    """``(doc_id, fingerprint, component_id)``, one row per row of ``df``."""
    prints = materialise(fingerprints(df.select(doc_id, text), text, doc_id, shingle), "simhash")
    return prints.join(components(prints, radius), "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def drop_near_duplicates(df: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = 3, radius: int = 3) -> DataFrame:
    """``df`` with one row of each component, that of the smallest id; of repeated or missing ids the first row by its
    place. Columns stay as they are."""
    rows, at = located(df, "simhash-in")
    narrow = rows.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"), F.col(at).alias("_at"))
    prints = materialise(fingerprints(narrow, shingle=shingle), "simhash")
    gone = prints.join(components(prints, radius), "fp").where("at <> stays").select(F.col("at").alias(at))
    return rows.join(gone, at, "left_anti").select(*[F.col(f"`{c}`") for c in df.columns])


def op5_covering_simhash(spark, sf_dir: str) -> DataFrame:
    return near_dup_components(load(spark, sf_dir, "documents"))
