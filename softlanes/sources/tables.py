"""Reading and writing: Parquet tables, edge lists in text formats, bucketed edge stores, generators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softlanes import schemas
from softlanes.sources.session import ship_package


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, pruned to ``columns`` where given (the scan reads no others)."""
    ship_package(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edges_csv(spark: SparkSession, path: str, header: bool = True) -> DataFrame:
    """Edge list with an explicit schema: src, dst and weight (1 where missing)."""
    raw = spark.read.schema(schemas.EDGE).csv(path, header=header)
    return raw.withColumn("weight", F.coalesce("weight", F.lit(1.0)))


def read_edges_json(spark: SparkSession, path: str) -> DataFrame:
    raw = spark.read.schema(schemas.EDGE).json(path)
    return raw.withColumn("weight", F.coalesce("weight", F.lit(1.0)))


def save_edges(df: DataFrame, table: str, buckets: int) -> DataFrame:
    """Edge store bucketed and sorted on the source node, so that joins with a state bucketed alike never
    shuffle it again."""
    df.write.mode("overwrite").bucketBy(buckets, "j" if "j" in df.columns else "src").sortBy("j" if "j" in df.columns else "src").saveAsTable(table)
    return df.sparkSession.table(table)


def write_partitioned(df: DataFrame, path: str, *by: str) -> None:
    """Parquet sink with partition folders, each written by few tasks."""
    (df.repartition(*by) if by else df).write.mode("overwrite").partitionBy(*by).parquet(path)


def values(spark: SparkSession, schema: str, rows: list[tuple]) -> DataFrame:
    """In-memory relation of literal rows."""
    return spark.createDataFrame(rows, schema)


def node_range(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("i"))


def read_heartbeats(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """Streaming file source with an explicit schema."""
    ship_package(spark)
    return spark.readStream.schema(schema).parquet(path)
