"""The queries of this subpackage: each applies one operator to its whole table and derives the columns asked for.

Rows with nulls, empty and long texts, repeated rows, empty tables and tables with more columns are handled as each operator
states; a query returns a row per row of its table, without rows for an empty one.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from flowmatch.llm import bpe, embedding_dedup, language_id, lm_scoring, minhash, mixing, quality_classifier, quality_rules, quotation, sharding
from flowmatch.llm.common import fold, table


def tokenizer(name: str = "byte_bpe_50k.tiktoken") -> tuple[str, str]:
    """Path of a public vocabulary, and its split pattern."""
    import public_tokenizers

    return public_tokenizers.path(name), public_tokenizers.PATTERN


def op1_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(table(spark, sf_dir, "documents"), *tokenizer())


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return judged.select("doc_id", *quality_rules.COUNTS, "base_failed", "kept", "anomaly")


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = quality_classifier.fit(docs, labels.where(fold(F.col("doc_id"), 4) != 2))
    scored = quality_classifier.score(docs, model)
    return scored.select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "score", (F.col("score") >= quality_classifier.ACCEPT).cast("int").alias("predicted"))


def op5_quotation_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotation.conversations(table(spark, sf_dir, "conversations"))


def op6_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.classes(table(spark, sf_dir, "documents"), weights="count")


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(mixing.drawn(table(spark, sf_dir, "documents")))


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = lm_scoring.scored(table(spark, sf_dir, "documents"), fold(F.col("doc_id"), 5) != 1)
    return scored.select("doc_id", (fold(F.col("doc_id"), 5) == 1).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language_id.fit(docs.where(fold(F.col("doc_id"), 4) != 2))
    return language_id.predict(docs, model).select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", "score")


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.place(table(spark, sf_dir, "documents"), weights=[1.0] * sharding.SHARDS)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def rule_counts_op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The counts and hard rules of op3 alone, which SQL can state."""
    return op3_quality_rules(spark, sf_dir).select("doc_id", *quality_rules.COUNTS, "base_failed")


def base_score_op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The exact part of op8, which SQL can state; the base score to three places."""
    return op8_lm_scoring(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 3).alias("base_score"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    every = (op1_embedding_dedup, op2_byte_bpe, op3_quality_rules, op4_quality_classifier, op5_quotation_linking, op6_minhash, op7_mixing, op8_lm_scoring, op9_language_id, op10_sharding, pipeline, rule_counts_op3, base_score_op8)
    return {f.__name__: f for f in every}


def oracle_sql() -> dict[str, str]:
    return {"op5_quotation_linking": quotation.oracle(), "op7_mixing": mixing.oracle(), "op10_sharding": sharding.oracle(), "rule_counts_op3": quality_rules.oracle(), "base_score_op8": lm_scoring.oracle()}
