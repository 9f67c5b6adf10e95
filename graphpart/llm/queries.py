"""The training-data queries of the driver contract, and the SQL that expresses some of them."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from graphpart.llm.common import load

Query = Callable[[SparkSession, str], DataFrame]


def tokenizer_path(name: str) -> str:
    """Where a public vocabulary file lies; GRAPHPART_TOKENIZERS overrides the installed folder."""
    folder = os.environ.get("GRAPHPART_TOKENIZERS")
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.media import media_features

    return media_features(load(spark, sf_dir, "documents")).drop("tile_npy")


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.quality import fit_quality, score_quality

    docs = load(spark, sf_dir, "documents")
    return score_quality(docs, fit_quality(docs, load(spark, sf_dir, "labels")))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.jaccard import jaccard_classes

    return jaccard_classes(load(spark, sf_dir, "documents"))


def op4_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.ann import nearest_neighbours

    return nearest_neighbours(load(spark, sf_dir, "embeddings"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.langid import fit_langid, identify_languages

    docs = load(spark, sf_dir, "documents")
    return identify_languages(docs, fit_langid(docs))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.tokens import token_counts

    return token_counts(load(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


def op7_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.pii import find_personal_data

    return find_personal_data(load(spark, sf_dir, "documents"))


def op8_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.bpe import encode_documents

    return encode_documents(load(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.secrets import find_secrets

    return find_secrets(load(spark, sf_dir, "documents"))


def op10_retrieval_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphpart.llm.packing import pack_documents

    return pack_documents(load(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        op1_media_columns, op2_quality_classifier, op3_jaccard_join, op4_nearest_neighbours, op5_language_id,
        op6_token_counts, op7_personal_data, op8_bpe_round_trip, op9_secret_scan, op10_retrieval_packing,
    )
}
ORACLE_SQL: dict[str, str] = {}
