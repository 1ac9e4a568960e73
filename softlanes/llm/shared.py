"""Helpers every operator of this subpackage uses: tables, shared storage, components."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softlanes.sources.session import materialise, release, shared_folder, ship_package

__all__ = ["connected_components", "held_out_fold", "load", "located", "materialise", "shared_folder", "smallest_row", "text_crc32"]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _plain_scan(df: DataFrame) -> bool:
    """Whether every row of ``df`` is one row of a Parquet file: nothing but selections over one scan."""
    plan = df._jdf.queryExecution().analyzed()
    while plan.nodeName() in ("Project", "Filter", "SubqueryAlias"):
        plan = plan.children().head()
    if plan.nodeName() != "LogicalRelation" or plan.relation().getClass().getSimpleName() != "HadoopFsRelation":
        return False
    return plan.relation().fileFormat().getClass().getSimpleName() == "ParquetFileFormat"


def located(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """``df`` with a column ``struct(file, row)`` that says where each row's content lies, and that column's name,
    which ``df`` has not. Rows that are no rows of files yet are written first: a locator must not change when
    the plan runs again."""
    taken, name = {c.lower() for c in df.columns}, "_at"
    while name in taken:
        name += "_"
    if not _plain_scan(df):
        df = materialise(df, label)
    place = df.metadataColumn("_metadata")
    return df.withColumn(name, F.struct(place["file_path"].alias("file"), place["row_index"].alias("row"))), name


def smallest_row(doc_id: str, at: str) -> F.Column:
    """Orders rows by id, nulls last, then by where they lie: the smallest of a group stays."""
    return F.struct(F.col(doc_id).isNull().alias("no_id"), F.col(doc_id).alias("doc_id"), F.col(at).alias("at"))


def held_out_fold(doc_id) -> F.Column:
    """True for the fold never learnt from: crc32 of the id as text, remainder 0 by 5 (null id: held out)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def text_crc32(text) -> F.Column:
    return F.crc32(F.coalesce(text, F.lit("")).cast("binary"))


def connected_components(edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """Smallest reachable node of every node that has an edge: ``(node, component)``.

    ``edges(a long, b long)`` is undirected; loops and repeats are allowed. Alternating star
    contraction: each round hangs larger neighbours on the smallest one, so the number of rounds is
    logarithmic in practice. Each round is two groupings with map-side minimum and two equi-joins,
    which adaptive execution splits where a node is hot; the rows never exceed the edges plus the nodes.
    """
    spark = edges.sparkSession
    cur = materialise(
        edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "cc"
    )

    def digest(df):
        r = df.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        return (r.n, r.h)

    seen = digest(cur)
    for _ in range(max_rounds):
        if seen[0] == 0:
            break
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low2 = large.groupBy("u").agg(F.min("v").alias("m"))
        hung = large.join(low2, "u")
        small = (
            hung.where("v <> m")
            .select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(low2.select("u", F.col("m").alias("v")))
            .distinct()
        )
        before, cur = cur, materialise(small, "cc")
        release(before)
        now = digest(cur)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    stars = cur.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return stars.unionByName(stars.select(F.col("component").alias("node"), "component").distinct())
