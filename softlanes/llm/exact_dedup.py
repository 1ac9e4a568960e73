"""Stateful streaming exact deduplication, on DataFrame and SQL functions only.

Digests of normalised texts flow through a Structured Streaming aggregation whose keyed state lives in
RocksDB on disk and never expires: per digest it retains the stable identifier (smallest doc_id), the
content locator (file and row) of that row, and the number of rows seen. Hits, digests seen more than once,
are then checked over their full bytes: the smallest and the largest text of a digest must be the same
string, found with map-side aggregation, so a group that holds a third of all rows is reduced before it is
shuffled. Should a digest hold different texts, its rows are grouped again by whole text.

With a ``state_folder`` later runs continue the state: their rows are judged by all rows seen so far, and the
folder keeps each distinct text once, so that bytes are compared across runs. What earlier runs returned is
not revised: a later row with a smaller id is kept too.

Edge cases: null text counts as empty; null doc_id sorts last and null is its keep_id only where no row
has an id; ties of doc_id (repeated rows) are broken by the locator, so one row stays; an empty table
gives no rows; extra columns of any name are ignored by ``dedup_decisions`` and kept by ``drop_duplicates``.
Rows that do not come straight from Parquet files are written once to have locators.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import load, located, materialise, shared_folder, smallest_row

#: Up to so many digests of hits (16 bytes each) go to every task, and only texts of hits are shuffled; beyond, texts are.
BROADCAST_HITS = 2_000_000
KEYED = "doc_id long, digest string, text_sha256 string, at struct<file: string, row: bigint>"
KEEP = "struct<no_id: boolean, doc_id: bigint, at: struct<file: string, row: bigint>>"
#: Keyed state on disk. Changelogs are written instead of whole snapshots, and files are not allocated ahead, which
#: for many small partitions of state would take megabytes each.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
    "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
}


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")


def stateful_groups(keyed_folder: str, spark, state_folder: str) -> DataFrame:
    """Stream the new files in ``keyed_folder`` through the keyed state; returns ``(digest, keep, group_size)``.

    The sink writes each trigger's updates as Parquet; the last update of a digest is its state.
    """
    out = f"{state_folder}/updates"
    before = {k: spark.conf.get(k, None) for k in STATE}
    for k, v in STATE.items():
        spark.conf.set(k, v)
    try:
        grouped = (
            spark.readStream.schema(KEYED).parquet(keyed_folder)
            .groupBy("digest").agg(F.min(smallest_row("doc_id", "at")).alias("keep"), F.count("*").alias("group_size"))
        )

        def sink(batch: DataFrame, number: int) -> None:
            batch.withColumn("trigger", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{out}/trigger={number}")

        query = (
            grouped.writeStream.outputMode("update").foreachBatch(sink)
            .option("checkpointLocation", f"{state_folder}/state").trigger(availableNow=True).start()
        )
        query.awaitTermination()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    updates = spark.read.schema(f"digest string, keep {KEEP}, group_size long, trigger int").parquet(out)
    triggers = [r.trigger for r in updates.select("trigger").distinct().collect()]
    if len(triggers) > 1:
        updates = updates.groupBy("digest").agg(
            F.max_by("keep", "trigger").alias("keep"), F.max_by("group_size", "trigger").alias("group_size")
        )
    return updates.select("digest", "keep", "group_size")


def _texts_of(texts: DataFrame, hits: DataFrame) -> DataFrame:
    """Rows of ``texts`` whose digest is among ``hits(digest)``; a few others may come with them."""
    if hits.count() > BROADCAST_HITS:
        return texts.join(hits, "digest", "left_semi")
    short = hits.select(F.xxhash64("digest").alias("short"))
    return texts.join(F.broadcast(short), F.xxhash64(texts["digest"]) == short["short"], "left_semi")


def _decisions(rows: DataFrame, at: str, text: str, doc_id: str, digest, state_folder: str | None) -> DataFrame:
    spark = rows.sparkSession
    texts = rows.select(F.col(doc_id).cast("long").alias("doc_id"), normalised(F.col(text)).alias("norm"), F.col(at).alias("at"))
    texts = texts.withColumn("digest", digest(F.col("norm")).cast("string"))
    sha = F.sha2(F.col("norm").cast("binary"), 256)
    folder, run = state_folder or f"{shared_folder(spark)}/dedup-{uuid.uuid4().hex}", uuid.uuid4().hex
    texts.select("doc_id", "digest", sha.alias("text_sha256"), "at").write.parquet(f"{folder}/keyed/{run}")
    keyed = spark.read.schema(KEYED).parquet(f"{folder}/keyed/{run}")
    if keyed.isEmpty():
        return keyed.select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(0).cast("long").alias("group_size"), F.lit(True).alias("kept"), "text_sha256", "at")
    groups = stateful_groups(f"{folder}/keyed/*", spark, folder)
    seen = texts.select("digest", "norm", smallest_row("doc_id", "at").alias("keep"), F.lit(1).cast("long").alias("n"))
    hits = groups.where("group_size > 1").select("digest")
    if state_folder:  # what later runs compare their hits with: each distinct text once a run
        each = seen.groupBy("digest", "norm").agg(F.min("keep").alias("keep"), F.sum("n").alias("n"))
        each.write.parquet(f"{folder}/texts/{run}")
        seen = spark.read.schema(each.schema).parquet(f"{folder}/texts/*")
        hits = hits.join(keyed.select("digest"), "digest", "left_semi")
    hits = materialise(hits, "dedup-hits")
    compared = _texts_of(seen, hits).groupBy("digest").agg(F.min("norm").alias("low"), F.max("norm").alias("high"))
    clashes = materialise(compared.where("low <> high").select("digest"), "dedup-clash")
    plain = keyed.join(groups, "digest").select(
        "doc_id", F.col("keep.doc_id").alias("keep_id"), "group_size", (F.col("at") == F.col("keep.at")).alias("kept"), "text_sha256", "at", "digest",
    )
    if clashes.isEmpty():
        return plain.drop("digest")
    whole = seen.join(clashes, "digest", "left_semi").groupBy("digest", "norm").agg(F.min("keep").alias("keep"), F.sum("n").alias("group_size"))
    split = texts.join(clashes, "digest", "left_semi").join(whole, ["digest", "norm"]).select(
        "doc_id", F.col("keep.doc_id").alias("keep_id"), "group_size", (F.col("at") == F.col("keep.at")).alias("kept"), sha.alias("text_sha256"), "at",
    )
    return plain.join(clashes, "digest", "left_anti").drop("digest").unionByName(split)


def sha256(norm: Column) -> Column:
    return F.sha2(norm.cast("binary"), 256)


def dedup_decisions(df: DataFrame, text: str = "text", doc_id: str = "doc_id", digest=sha256, state_folder: str | None = None) -> DataFrame:
    """One row per row of ``df``: doc_id, keep_id, group_size, kept, text_sha256, and the locator ``at(file, row)``."""
    rows, at = located(df.select(doc_id, text), "dedup-in")
    return _decisions(rows, at, text, doc_id, digest, state_folder)


def drop_duplicates(df: DataFrame, text: str = "text", doc_id: str = "doc_id", digest=sha256, state_folder: str | None = None) -> DataFrame:
    """``df`` without the rows whose normalised text a smaller doc_id has; all columns stay as they are."""
    rows, at = located(df, "dedup-in")
    gone = _decisions(rows, at, text, doc_id, digest, state_folder).where("NOT kept").select(F.col("at").alias(at))
    return rows.join(gone, at, "left_anti").select(*[F.col(f"`{c}`") for c in df.columns])


def op7_streaming_exact_dedup(spark, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return dedup_decisions(docs).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


ORACLE_OP7 = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       row_number() OVER (PARTITION BY norm ORDER BY doc_id) = 1 AS kept, sha256(norm) AS text_sha256
FROM t WINDOW w AS (PARTITION BY norm)"""
