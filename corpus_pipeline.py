"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again.

Counted as part of the llm subpackage: it needs it and goes with it.

Defined results, of every stage: each row is judged by its own doc_id and text, so that rows
without an id, or with one that repeats, lose nothing to another row's fate; a null text is an
empty one; texts of any length are read whole; extra columns come through, whatever their
names (packing returns its own); of rows that repeat id and text the dedup stages keep one;
an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from motifspark.llm import decontaminate, exact_dedup, jaccard_join, packing, toxicity
from motifspark.llm.common import Scratch, relieve, scratch_scope


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model rejects go."""
    relieve(spark)
    return toxicity.survivors(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the smallest doc_id stays."""
    relieve(spark)
    return exact_dedup.survivors(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that similarity links connect the smallest doc_id stays."""
    relieve(spark)
    return jaccard_join.survivors(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    relieve(spark)
    return decontaminate.survivors(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What is left, tokenised and packed into sequences."""
    relieve(spark)
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact dedup", drop_copies),
    ("n-gram Jaccard join", drop_near_copies),
    ("benchmark decontamination", drop_leaks),
    ("packing", pack),
]

#: SQL can't express the learned and the packing stage; the tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), Scratch(spark, "pipeline"), []
    for name, stage in STAGES:
        at: list[str] = []
        with scratch_scope(spark):  # what a stage's operator wrote goes when the stage is written
            docs = scratch.table(stage(spark, docs, sf_dir), name.replace(" ", "-"), at)
        scratch.drop(*before)
        before = at
    return docs
