"""Sampled splitters: range-partition records into shards of near-equal bytes.

A size-weighted sample of keys gives quantile boundaries of many fine ranges; the exact bytes of each
range are then counted, ranges that are overfull are subdivided, and consecutive pieces are dealt to
shards by their exact cumulative bytes. A group of equal keys moves as a whole unless it alone exceeds
``whole_share`` of a shard; a larger one is cut into consecutive pieces. Balance: a shard's bytes differ from
the mean by no more than the largest piece, that is ``max(whole_share of a shard, two fine ranges, the
largest record)`` (``test_shards`` holds it to that). Everything is DataFrame functions; what reaches the driver
is one array of at most ``fine_ranges`` boundaries, one row per overfull range and one per key that fills more
than a fine range, of which there are no more than fine ranges.

Edge cases: null text has size 8; a null id or a null key sorts as its own value; repeated rows are
separate records; an empty table gives no rows; columns of the input named like results raise no clash,
because the result is built from positions under reserved names and replaces same-named inputs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from softlanes.llm.shared import load, located, materialise, text_crc32

MAX_RANGES = 1 << 14


def locate(key: Column, splits: list[int]) -> Column:
    """Index of the range of ``key``: how many splits are <= key. A binary search of array elements."""
    if not splits:
        return F.lit(0)
    steps = len(splits).bit_length()
    width = 1 << steps
    # padded to a power of two with the largest value; ranges past the real splits are never entered
    array = F.array(*[F.lit(s).cast("long") for s in splits]) if len(splits) < 64 else F.from_json(
        F.lit("[" + ",".join(map(str, splits)) + "]"), "array<bigint>"
    )
    halves = F.array(*[F.lit(width >> (i + 1)) for i in range(steps)])
    n = len(splits)
    return F.aggregate(
        halves,
        F.lit(0),
        lambda lo, h: F.when((lo + h <= n) & (F.get(array, lo + h - 1) <= key), lo + h).otherwise(lo),
    )


def plan_ranges(keyed: DataFrame, fine_ranges: int, per_range: int) -> tuple[DataFrame, list[int], int]:
    """Boundaries from a size-weighted sample of ``keyed(_k long, _s long, _t long)``, then exact bytes by range.

    Returns (ranges, splits, total): ``ranges(_r, _bytes)`` has a row per non-empty range.
    """
    total = keyed.agg(F.coalesce(F.sum("_s"), F.lit(0)).alias("t")).first().t
    if not total:
        return keyed.groupBy(F.lit(0).alias("_r")).agg(F.sum("_s").alias("_bytes")), [], 0
    wanted = fine_ranges * per_range
    coin = F.pmod(F.xxhash64(F.lit(17), "_k", "_t"), F.lit(1 << 40)) / float(1 << 40)
    # a record heavier than the sampling step counts as often as it spans steps
    copies = F.floor(F.col("_s") * F.lit(wanted / total) + coin).cast("int")
    sample = keyed.select(F.explode(F.array_repeat("_k", copies)).alias("_k"))
    points = [i / fine_ranges for i in range(1, fine_ranges)]
    got = sample.agg(F.expr(f"percentile_approx(_k, array({','.join(map(str, points))}), {20 * fine_ranges})").alias("q"))
    quantiles = got.first().q or []
    splits: list[int] = []
    for before, here in zip([None, *quantiles], quantiles):
        if here != before:
            splits.append(here)
        elif splits[-1] == here and here < (1 << 63) - 1:
            splits.append(here + 1)  # a key that spans several quantiles gets a range of its own
    ranges = keyed.groupBy(locate(F.col("_k"), splits).alias("_r")).agg(F.sum("_s").alias("_bytes"))
    return ranges, splits, total


def subdivided(keyed: DataFrame, ranges: DataFrame, splits: list[int], target: float, limit: float) -> DataFrame:
    """Add ``_r``, the range of each row, and ``_u``, its piece there: rows of a range that holds over two targets are
    dealt by their key's hash, keys over a target get pieces of their own, one up to ``limit`` bytes, more beyond."""
    where = keyed.withColumn("_r", locate(F.col("_k"), splits))
    over = {r._r: int(r._bytes) for r in ranges.where(F.col("_bytes") > 2 * target).collect()}
    if not over:
        return where.withColumn("_u", F.lit(0).cast("long"))
    spark, pieces = keyed.sparkSession, lambda n: max(1, -(-int(n) // int(target + 1)))
    hot = (
        where.where(F.col("_r").isin(*over)).groupBy("_r", "_k").agg(F.sum("_s").alias("_bytes")).where(F.col("_bytes") > target).collect()
    )
    rest = dict(over)
    for r in hot:
        rest[r._r] -= int(r._bytes)
    first, own = {r: pieces(n) for r, n in rest.items()}, []
    for r in sorted(hot, key=lambda r: (r._r, r._k)):
        parts = 1 if r._bytes <= limit else pieces(r._bytes)
        own.append((r._k, first[r._r], parts))
        first[r._r] += parts
    cuts = F.from_json(F.lit("[" + ",".join(str(pieces(rest[r])) if r in rest else "1" for r in range(len(splits) + 1)) + "]"), "array<int>")
    hot_keys = spark.createDataFrame(own, "_k long, _first long, _parts long")
    plain = F.pmod(F.xxhash64(F.lit(5), "_k"), F.coalesce(F.get(cuts, F.col("_r")), F.lit(1)).cast("long"))
    cut = F.col("_first") + F.pmod(F.xxhash64(F.lit(5), "_t", "_k"), F.col("_parts"))
    return where.join(F.broadcast(hot_keys), "_k", "left").withColumn("_u", F.coalesce(cut, plain)).drop("_first", "_parts")


def sampled_splitter_shards(
    df: DataFrame, n_shards: int, key: Column, size: Column, tie: Column, *, fine_per_shard: int = 192, per_range: int = 16, whole_share: float = 0.02
) -> DataFrame:
    """Add ``shard int``, ``slot long`` and ``range_id long`` to ``df``.

    ``key`` is the long to range-partition by, ``size`` its weight in bytes, ``tie`` a long that orders records
    of one key and cuts a key that is too large for one piece, so it should tell repeated rows apart.
    Slots are gapless from 0 in each shard, in order of (range, piece, key, tie).
    """
    fine = min(MAX_RANGES, max(2, n_shards * fine_per_shard))
    keyed = df.withColumns({"_k": F.coalesce(key, F.lit(0)), "_s": size.cast("long"), "_t": F.coalesce(tie, F.lit(0))})
    ranges, splits, total = plan_ranges(keyed.select("_k", "_s", "_t"), fine, per_range)
    target = max(1.0, total / fine)
    where = subdivided(keyed, ranges, splits, target, max(target, whole_share * total / n_shards))
    held = where.groupBy("_r", "_u").agg(F.sum("_s").alias("_bytes"), F.count("*").alias("_n"))
    # pieces: at most a few times the fine ranges, a parameter, so one task orders them
    line = Window.orderBy("_r", "_u")
    before = F.sum("_bytes").over(line) - F.col("_bytes")
    shard = F.least(F.lit(n_shards - 1), F.floor((before + F.col("_bytes") / 2) * n_shards / F.lit(max(1, total))).cast("int"))
    dealt = held.withColumn("shard", shard)
    order = Window.partitionBy("shard").orderBy("_r", "_u")
    dealt = dealt.withColumn("_first", F.sum("_n").over(order) - F.col("_n")).select("_r", "_u", "shard", "_first")
    inside = Window.partitionBy("_r", "_u").orderBy("_k", "_t")
    placed = where.drop("shard", "slot", "range_id").withColumn("_i", F.row_number().over(inside) - 1)
    return (
        placed.join(F.broadcast(dealt), ["_r", "_u"])
        .withColumn("slot", (F.col("_first") + F.col("_i")).cast("long"))
        .withColumn("range_id", F.col("_r").cast("long"))
        .drop("_k", "_s", "_t", "_r", "_u", "_i", "_first")
    )


def op1_sampled_splitters(spark, sf_dir: str) -> DataFrame:
    """All documents in 24 shards of near-equal bytes; equal texts share a key, so they stay together
    unless they alone fill over a fiftieth of a shard."""
    text = F.coalesce(F.col("text"), F.lit(""))
    narrow = load(spark, sf_dir, "documents").select(
        "doc_id",
        (F.octet_length(text) + 8).cast("long").alias("size"),
        text_crc32(F.col("text")).alias("text_crc32"),
        F.xxhash64(text).alias("text_key"),
    )
    narrow, at = located(materialise(narrow, "shard-keys"), "shard-keys")
    done = sampled_splitter_shards(narrow, 24, F.col("text_key"), F.col("size"), F.xxhash64("doc_id", at))
    return done.select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )
