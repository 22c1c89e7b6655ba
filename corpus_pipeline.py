"""A training-data pipeline over ``documents``: each stage calls one operator on all that its predecessor kept.

Language ID drops what is in no learnt language, the quality classifier what scores low, near-duplicate removal all but
one of each group; mixing repeats and samples what is left to its sources' targets; the last stage encodes and decodes
it.  All but the last return the columns of ``documents``, extra ones included.  SQL cannot express the first stages, so
tests hold each stage against a brute-force version on a small table.

Empty tables pass through every stage.  Null and empty texts have no language and go at the first stage; rows that repeat
are duplicates of each other; a null id is no duplicate of another.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from flowmatch.llm import bpe, language_id, minhash, mixing, quality_classifier
from flowmatch.llm.common import dropped, fold, scratch, table, written
from flowmatch.llm.queries import tokenizer


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The rows in a language that the labelled ones outside the held-out fold have; without any such language, none."""
    return language_id.identified(docs, language_id.fit(docs.where(fold(F.col("doc_id"), 4) != 2)))


def classify_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The rows that score at least the bar; all of them if there are not labels of both kinds to learn from."""
    labels = table(spark, sf_dir, "labels").where(fold(F.col("doc_id"), 4) != 2)
    return quality_classifier.accepted(docs, quality_classifier.fit(docs, labels))


def remove_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class of near-duplicates; rows with a null id all stay."""
    return minhash.deduplicated(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row as often as the mix takes it, at most three times; a null source is a source."""
    return mixing.repeated(docs)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Per row its id, number of tokens and digests of ids and of the decoded text; a null text is the empty one."""
    return bpe.round_trip(docs, *tokenizer())


STAGES = [
    ("language ID", identify_language),
    ("quality classifier", classify_quality),
    ("MinHash near-dedup", remove_near_duplicates),
    ("mixing sources to target weights", mix_sources),
    ("byte-level BPE encoding and decoding", encode_tokens),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order, each written before the next; a stage's own tables are deleted when it is through, and its input with them."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES[:-1]):
        with scratch() as keep:
            kept = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
            keep.append(kept)
        if k:
            dropped(docs)
        docs = kept
    return STAGES[-1][1](spark, docs, sf_dir)
