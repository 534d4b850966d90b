"""The queries of the operators on the given tables, and their SQL where SQL can say the same."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardweave.llm import balltree, crf, jump, kneser_ney, mixing, pieces, pseudonyms, rules, simhash, warc
from shardweave.llm.sql import BALLTREE_SQL, JUMP_SQL, MIXING_SQL, RULES_SQL, WARC_SQL
from shardweave.llm.textcols import table

SHARDS = 40


def MODEL() -> str:  # noqa: N802
    """The piece model's path: ``SHARDWEAVE_PIECES``, else the installed public one."""
    return os.environ.get("SHARDWEAVE_PIECES", "/opt/tokenizers/piece_bpe_32k.model")


def KEY(spark: SparkSession) -> str:  # noqa: N802
    """The pseudonyms' key: ``spark.shardweave.pseudonyms.key`` of the session, else ``SHARDWEAVE_PSEUDONYMS_KEY``; for the
    given synthetic tables, which hold nobody's data, a public one."""
    return spark.conf.get("spark.shardweave.pseudonyms.key", None) or os.environ.get("SHARDWEAVE_PSEUDONYMS_KEY") or "synthetic tables only"


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return mixing.shares(docs).select("doc_id", "size", "source_size", "target", "taken")


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.classes(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select(F.col("id").alias("doc_id"), simhash.hexadecimal().alias("fingerprint"), "component_id")


def op3_balltree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return balltree.top_k(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), F.col("vec_id") % 50 == 0)


def op4_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels")
    out = kneser_ney.score(docs, labels, ~kneser_ney.held_out("doc_id", 3, 1))
    return _judged(out, 3, 1, 0.7)


def _judged(scored: DataFrame, parts: int, part: int, least: float) -> DataFrame:
    named = scored.withColumnRenamed("id", "doc_id")
    return named.select("doc_id", kneser_ney.held_out("doc_id", parts, part).alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.digest(warc.round_trip(table(spark, sf_dir, "pages")))


def op6_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = rules.judge(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op7_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels")
    return _judged(crf.score(docs, labels, ~kneser_ney.held_out("doc_id", 5, 0)), 5, 0, 0.3)


def op8_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return pieces.encode(docs, pieces.load(MODEL())).withColumnRenamed("id", "doc_id")


def op9_jump(spark: SparkSession, sf_dir: str) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    docs = table(spark, sf_dir, "documents").select(
        "doc_id", (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.lit("key").alias("law")
    )
    out = jump.assign(docs, "doc_id", ["size", "text_crc32"], SHARDS)
    return out.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")


def op10_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonyms.pseudonymise(table(spark, sf_dir, "documents").select("doc_id", "text"), KEY(spark))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mixing": op1_mixing,
    "op2_simhash": op2_simhash,
    "op3_balltree": op3_balltree,
    "op4_kneser_ney": op4_kneser_ney,
    "op5_warc": op5_warc,
    "op6_rules": op6_rules,
    "op7_crf": op7_crf,
    "op8_pieces": op8_pieces,
    "op9_jump": op9_jump,
    "op10_pseudonyms": op10_pseudonyms,
}

ORACLES: dict[str, str] = {"op1_mixing": MIXING_SQL, "op3_balltree": BALLTREE_SQL, "op5_warc": WARC_SQL, "op6_rules": RULES_SQL, "op9_jump": JUMP_SQL}
