"""The corpus pipeline: quality, language, exact copies, near copies, packing.

Each stage takes (spark, docs, sf_dir), works on all documents that the one before kept, and returns a
DataFrame that the caller writes as Parquet and reads again. All but the last return the columns of
``documents``; the last returns the packed pieces. Nulls in any column, empty and very long texts, repeated
rows and empty tables are handled as the stages' operators document.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from softlanes.llm import exact_dedup, language, packing, quality, simhash
from softlanes.llm.shared import load, materialise


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    labels = load(spark, sf_dir, "labels").select("doc_id", F.col("quality").alias("y"))
    return quality.keep_good(docs, labels)


def keep_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.keep_recognised(docs)


def keep_one_copy(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_duplicates(docs)


def keep_one_near_copy(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.drop_near_duplicates(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("quality_classifier", keep_quality),
    ("language_id", keep_language),
    ("exact_dedup", keep_one_copy),
    ("simhash_near_dedup", keep_one_near_copy),
    ("best_fit_packing", pack_sequences),
]

#: Learnt models, keyed state and tokenisation are not SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's output is written to the shared folder and read again."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
