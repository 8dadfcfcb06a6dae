"""Corpus preparation in five stages; each reads what its predecessor wrote and returns documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from memojoin.llm import bpe, jaccard_join, kn_quality, langid, mixing
from memojoin.llm.common import materialise, read, small_batches

#: Near duplicates: shingles of five words, similarity of 0.8 or more.
NEAR_WORDS, NEAR_PERCENT = 5, 80
LEAST_LANGUAGE_SCORE = 0.4


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose language is told with at least LEAST_LANGUAGE_SCORE."""
    small_batches(spark)
    return langid.keep_identified(docs, langid.train(docs), LEAST_LANGUAGE_SCORE)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents within their language's perplexity threshold."""
    return kn_quality.keep_good(docs, read(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document, that of the smallest id, of each group of near copies."""
    return jaccard_join.keep_first(docs, NEAR_WORDS, NEAR_PERCENT)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Emits each document as often as its source's rate says."""
    return mixing.mix(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of every document that is left."""
    small_batches(spark)
    return bpe.digests(docs, bpe.VOCABULARY)


STAGES = [("language_id", language), ("quality_classifier", quality), ("ngram_jaccard", near_duplicates), ("mixing", mix), ("bpe", encode)]
#: Trained stages have no SQL form; tests compare what each stage keeps or returns with plain Python (the trained network
#: of the first with its own scores).
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialise(docs, f"pipeline-{name}")
    return docs
