"""From raw documents to packed token sequences, in stages that are each written as Parquet and read again.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept; all but the last return the columns of
documents. An empty table passes through every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from passagekit.llm import importance, jaccard_join, mixing, packing, surrogates
from passagekit.llm.common import materialise, table
from passagekit.session import ship


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that importance resampling keeps."""
    ship(spark)
    return importance.keep(docs, importance.target_labels(spark, sf_dir))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document (the smallest id) of each class of five-word shingle sets at Jaccard similarity 0.8."""
    ship(spark)
    return jaccard_join.one_of_each(docs, k=5, percent=80)


def private_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Surrogates for personal data and secrets."""
    ship(spark)
    return surrogates.replace(docs, spans=False).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document at least once, small sources up to twice."""
    return mixing.mix(docs, max_repeats=2.0, keep=docs.columns).select("_row.*")


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their ids and their places in sequences of 2048 tokens."""
    ship(spark)
    return packing.pack(docs, with_ids=True)


STAGES = [("quality classifier", quality), ("n-gram jaccard join", near_duplicates), ("pii surrogates", private_data), ("mixing sources", mixture), ("best-fit packing", packed)]

#: The stages hash, sample and tokenize, which SQL cannot state; tests/llm/test_brute_force.py holds run() to its stages by hand.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over documents."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir))
    return docs
