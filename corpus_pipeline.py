"""A training-data pipeline: five stages over documents, each written and read again by its caller."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semigraph.llm import byte_bpe, language_id, mixing, near_duplicates, personal_data
from semigraph.llm.common import kept_table, table


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is known; texts without letters, or of hardly more than single letters, go."""
    return language_id.keep_identified(docs, language_id.learn(docs))


def deduplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near duplicates."""
    return near_duplicates.keep_first(docs)


def mask(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced by its kind."""
    weights, _ = personal_data.train(docs)
    return personal_data.mask_personal_data(docs, weights)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it: none, once or twice."""
    return mixing.take(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every remaining row, checked by decoding."""
    import public_tokenizers

    return byte_bpe.encode_documents(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=True)


STAGES = [("language", language), ("near_duplicates", deduplicate), ("personal_data", mask), ("mixing", mix), ("byte_bpe", encode)]

#: Training, rounding and byte-pair coding have no SQL form; tests/llm/test_cases.py takes the stages again on lists.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = kept_table(spark, stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
