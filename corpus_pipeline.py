"""The training-corpus pipeline: quality, language, near duplicates, personal data, packing.

STAGES lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame. Every stage but the
last returns the columns of documents for the rows it keeps; the last returns the pieces of the packed sequences.
The models are trained on the documents that come in (bounded samples of labelled rows). Null texts, empty texts, repeated
rows, extra columns and empty tables are handled as the operators' docstrings say.
"""

from __future__ import annotations

import os
import uuid

from pyspark.sql import DataFrame, SparkSession

from graphpart.llm.common import load
from graphpart.llm.jaccard import keep_one_of_each
from graphpart.llm.langid import fit_langid, keep_identified
from graphpart.llm.packing import pack_documents
from graphpart.llm.pii import redact_personal_data
from graphpart.llm.quality import fit_quality, keep_quality
from graphpart.llm.queries import tokenizer_path
from graphpart.session import shared_folder


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents whose quality score is under 0.3."""
    return keep_quality(docs, fit_quality(docs, load(spark, sf_dir, "labels"), train_only=False))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents that have no letter, or no language of a posterior of 0.5."""
    return keep_identified(docs, fit_langid(docs, train_only=False))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the smallest id, of each class of near duplicates."""
    return keep_one_of_each(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in the texts replaced by its kind."""
    return redact_personal_data(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the packed sequences."""
    return pack_documents(docs, tokenizer_path("word_bpe_49k.json"))


STAGES = [("quality", quality), ("language", language), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("packing", packing)]

#: No stage's model or token ids can be said in SQL; tests/llm/test_pipeline.py has a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet to the shared folder and read again."""
    folder = os.path.join(shared_folder(spark), f"pipeline-{uuid.uuid4().hex}")
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = f"{folder}/{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs

