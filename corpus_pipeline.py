"""A training-corpus pipeline of five stages over ``documents``.

Language ID drops texts whose language can't be told; near-duplicate classes
keep one document each; secrets are masked; sources are mixed to their target
weights; texts are encoded. Each stage is written as Parquet in the shared
folder and read again as the next one's input, so a lost executor costs at most
a stage's tasks.

Each stage takes any table with doc_id, text, lang, source and n_chars and keeps
further columns whatever their names. An empty table gives an empty table. What
a stage does with nulls, empty texts, ties and repeated rows stands at it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from annspark.llm import language_id, mixing, secrets, sentencepiece_codec, simhash
from annspark.plans.session import stage
from annspark.sources.tables import table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the documents whose language is determined.

    Null and empty texts and texts without letters go; rows with null ids,
    languages or sources stay; repeated rows share one decision.
    """
    return language_id.keep_identified(docs, language_id.fit(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each near-duplicate class.

    The smallest doc_id stays. Of rows that repeat it, and of a class without
    any id, one row stays; null and empty texts are one class; rows that repeat
    an id with unrelated texts all stay.
    """
    return simhash.keep_representatives(docs)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace secrets in texts by a mark; every document stays.

    Null texts stay null; n_chars is renewed where a text changes; repeated rows
    change alike.
    """
    return secrets.redact(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeat or thin out each source to its target.

    Null and empty texts are never taken; a null source is a source; rows that
    repeat in all columns count each; n_chars is renewed.
    """
    return mixing.mix_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with digests of ids, decoded text and byte spans.

    A null text is empty and has the begin and end ids alone; repeated rows give
    equal rows; ids may be null or repeat.
    """
    return sentencepiece_codec.encode_digests(docs, with_ids=True)


STAGES = [
    ("language_id", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("secrets", mask_secrets),
    ("mixing", mix_sources),
    ("sentencepiece", encode),
]

#: SQL has neither the language model nor the encoder; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``."""
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
