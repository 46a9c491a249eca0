"""Corpus pipeline over `documents`: toxic documents go, one document of each near-duplicate group stays, repeated
passages go, personal data is replaced, and what is left is packed into training sequences.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents. Between
stages the rows are written as Parquet and read again.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from saferoads.llm import jaccard_join, packing, suffix_dedup, surrogates, toxicity
from saferoads.llm.queries import SURROGATE_KEY, byte_bpe
from saferoads.plans.runtime import durable, read_table


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the classifier, fitted on the labelled rows of the tables, scores below the threshold."""
    trained = toxicity.train(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    return toxicity.drop_toxic(docs, trained)


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five-word shingles, similarity 0.8: the least doc_id of each component stays."""
    return jaccard_join.keep_one(docs, words=5, percent=80)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words covered by windows of 50 words that start anywhere else in the rows are cut out; every row stays."""
    return suffix_dedup.remove_repeats(docs, replace_text=True, unit=suffix_dedup.word_unit())


def replace_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return surrogates.replace_entities(docs, SURROGATE_KEY, keep_columns=True)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, byte_bpe())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", reject_toxic),
    ("jaccard_join", keep_one_of_each_group),
    ("suffix_dedup", cut_repeated_passages),
    ("pii", replace_personal_data),
    ("packing", pack_sequences),
]

#: Classifier, components and tokens have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
