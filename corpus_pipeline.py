"""The corpus pipeline: quality rules, near-duplicates, pseudonyms, the mix, and token ids.

Each stage takes ``(spark, docs, sf_dir)`` and returns a frame that is written as Parquet and read again for the next.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardweave.llm import mixing, nearcopies, pieces, pseudonyms, rules
from shardweave.llm.registry import KEY, MODEL
from shardweave.staging import stage

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return rules.judge(docs).where("kept").select(*COLUMNS)


def apart(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies: five-word shingles, similarity 0.8 or more."""
    return nearcopies.keep_one(docs).select(*COLUMNS)


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Private values replaced; ``n_chars`` follows the text."""
    out = pseudonyms.pseudonymise(docs, KEY(spark))
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of the sources; a document comes as often as the mix takes it."""
    return mixing.rows_of(mixing.mix(docs)).select(*COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every row."""
    return pieces.encode(docs, pieces.load(MODEL())).withColumnRenamed("id", "doc_id")


STAGES = [("quality_rules", good), ("simhash", apart), ("pseudonyms", private), ("mixing", mixed), ("pieces", encoded)]

#: SQL can't say the fingerprints, the pseudonyms and the lattice; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for at, (name, step) in enumerate(STAGES):
        docs = step(spark, docs, sf_dir)
        if at < len(STAGES) - 1:
            docs = stage(docs, name)
    return docs
