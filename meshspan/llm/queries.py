"""Queries of the training-data operators, as the entry module registers them."""

from __future__ import annotations

import secrets
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshspan.llm import chat, context_tree, hashed_search, html_text, mixing, packing, pruned_graph, quality, simhash, surrogates
from meshspan.llm.common import table

def tokenizer_path(spark: SparkSession) -> str:
    """The tokenizer file of packing: ``meshspan.tokenizer.path`` of the session, else the public one."""
    own = spark.conf.get("meshspan.tokenizer.path", None)
    if own:
        return own
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def surrogate_key(spark: SparkSession) -> str:
    """The secret key of surrogates: ``meshspan.surrogates.key`` of the session. Without one, a key is drawn for this
    session, so that its surrogates agree with each other and with nobody else's."""
    key = spark.conf.get("meshspan.surrogates.key", None)
    if not key:
        key = secrets.token_hex(32)
        spark.conf.set("meshspan.surrogates.key", key)
    return key


def op1_context_tree_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return context_tree.score_documents(table(spark, sf_dir, "documents"))


def op2_embedding_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pruned_graph.near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mix = mixing.mixed(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return mix.select("doc_id", "size", "source_size", "target", "taken")


def op4_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extracted(table(spark, sf_dir, "pages"))


def op5_quality_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.scored(docs, quality.fit(docs, table(spark, sf_dir, "labels")))


def op6_chat_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    probe = "</s>[INST] ok [/INST]"
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.createDataFrame([(-7, 0, "user", probe), (-7, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    return chat.digests(chat.formatted_conversations(rows.union(extra)))


def op7_packed_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"), tokenizer_path(spark))


def op8_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicate_groups(table(spark, sf_dir, "documents"))


def op9_hashed_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return hashed_search.nearest(vectors, vectors.where(F.col("vec_id") % 100 == 0))


def op10_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return surrogates.with_surrogates(docs, surrogate_key(spark), counts=True)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    """The ten operators have no SQL form: their tests compare them with brute force."""
    return {}
