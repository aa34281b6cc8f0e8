"""The corpus pipeline: documents of a known language, one of each near-duplicate group, without secrets, mixed to target weights, as token ids.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from commlens.llm import bpe, langid, mixing, secret_scan, simhash
from commlens.llm.common import Scratch, documents


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised with a score of a half or more (operator 8)."""
    return langid.keep_recognised(docs, langid.fit(docs))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of least doc_id of each group of near-duplicates (operator 3)."""
    return simhash.keep_one_of_each(docs)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets masked (operator 7)."""
    return secret_scan.redact(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents by target weights, each as often as it is taken (operator 10)."""
    return mixing.draw(docs)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, and digests of the ids and of the text decoded from them (operator 1)."""
    return bpe.encode_with_digests(docs)


STAGES = [
    ("language_id", known_language),
    ("near_duplicates", one_of_each),
    ("secret_scan", without_secrets),
    ("mixing", mixed),
    ("bpe", encoded),
]

#: Several stages are learned models or hash links that SQL cannot express; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch, docs = Scratch(spark), documents(spark, sf_dir)
    for _, stage in STAGES[:-1]:
        docs = scratch.table(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
