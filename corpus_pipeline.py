"""Training corpus from raw documents: quality, near-dedup, personal data, mixing, packing.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame, which :func:`run` writes as Parquet
and reads again for the next one. All but the last return the columns of ``documents``. Nulls, empty and
very long texts, repeated rows and empty tables are handled as the operators' docstrings say; columns
that ``documents`` does not have are kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from meshspan.llm import mixing, packing, quality, simhash, surrogates
from meshspan.llm.common import stored, table
from meshspan.llm.queries import surrogate_key, tokenizer_path


def select_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, learned from the labels, does not reject."""
    return quality.kept(docs, table(spark, sf_dir, "labels"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-copies: the one with the smallest doc_id."""
    return simhash.deduplicated(docs)


def replace_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced by surrogates."""
    return surrogates.with_surrogates(docs, surrogate_key(spark))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; the one in which a budget ends gives its first words."""
    return mixing.mixture(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the tokenised documents in sequences of up to 4,096 tokens."""
    return packing.packed(docs, tokenizer_path(spark))


STAGES = [
    ("quality", select_quality),
    ("near_copies", drop_near_copies),
    ("personal_data", replace_personal_data),
    ("mix", mix_sources),
    ("packing", pack_sequences),
]

#: The first three stages and the packing have no SQL form, so the rows of run() have none; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), name)
    return docs
