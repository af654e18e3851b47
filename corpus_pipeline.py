"""Corpus pipeline: stages over documents, each written as Parquet and reread as the next one's input."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from privgrove.llm import jaccard, langid, mixing, packing
from privgrove.llm.textio import shared_dir

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]

#: A text is rejected when it has no letter, or when no language holds this share of its expected words.
LEAST_SCORE = 0.3


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in a language that the model knows; it learns from their own labels. Each row is decided by its own text."""
    return langid.kept(docs, langid.trained(docs), LEAST_SCORE)


def deduplicated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates: five-word n-grams, Jaccard similarity of 0.8 or more. Texts without words stay."""
    return jaccard.first_of_each(docs, words=5, percent=80).select(*docs.columns)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A sample whose tokens are raked to smoothed source, language and topic shares."""
    return mixing.sampled(docs).select(*docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents kept, placed in sequences of 2048 tokens."""
    return packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"), 2048, 0)


STAGES: list[tuple[str, Stage]] = [
    ("language_id", identified),
    ("ngram_jaccard_join", deduplicated),
    ("mixing_to_target_weights", mixed),
    ("best_fit_packing", packed),
]

#: Language models and tokenisation are not SQL; tests hold the stages against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply the stages to documents."""
    docs, at = spark.read.parquet(f"{sf_dir}/documents.parquet"), shared_dir(spark)
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        out.write.mode("overwrite").parquet(f"{at}/{k}_{name}")
        docs = spark.read.parquet(f"{at}/{k}_{name}")
    return docs
