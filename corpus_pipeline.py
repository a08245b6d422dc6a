"""The training-data pipeline: language ID, exact dedup, SimHash near-dedup, mixing, best-fit packing.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame, which ``run`` writes as
Parquet into the shared folder and rereads as the next one's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seqstat.llm import exact_dedup, language_id, mixing, packing, simhash
from seqstat.llm.shared import documents, stage


def known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in a known language; null texts, texts without letters and texts of no language go."""
    return language_id.keep_known(docs)


def distinct_texts(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per text, the one with the smallest id."""
    return exact_dedup.keep_first(docs)


def distinct_prints(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates: five-word shingles, Jaccard similarity 0.8 or more."""
    return simhash.keep_one(docs)


def target_mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in training order, each as often as its source's target takes it."""
    return mixing.mixture(docs)


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their sequences and offsets."""
    return packing.pack(docs)


STAGES = [
    ("language ID", known_languages),
    ("exact dedup", distinct_texts),
    ("SimHash near-dedup", distinct_prints),
    ("mixing", target_mixture),
    ("best-fit packing", packed_sequences),
]

#: Language models, fingerprints and tokenizers have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, function in STAGES:
        docs = stage(function(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
