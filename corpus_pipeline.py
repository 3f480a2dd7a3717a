"""Corpus pipeline: quality classifier, near-duplicate join, substring dedup, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from repeatfold.llm import mixing, ngram_join, packing, quality, substring_dedup
from repeatfold.llm.common import cut, table
from repeatfold.llm.queries import tokenizer_path

ORACLE_SQL = None
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def classify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go.

    Null and empty texts get the prior's score; repeated rows are judged alike; without labels every document stays; an empty table gives none.
    """
    scores = quality.score_rows(docs, quality.train(docs, table(spark, sf_dir, "labels")))
    return scores.where("keep").select(*COLUMNS)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the document with the smallest id stays.

    One without an id stays only if no other of its group has one. Texts that are null or have no words are in no group and stay; of rows repeated
    with id and text one stays; an empty table gives none.
    """
    return ngram_join.representatives(docs).select(*COLUMNS)


def strip_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 35 words or more that stand elsewhere too are cut out of the texts; every document stays, with what is left of it.

    A null text becomes an empty one, and what is left has one space between words; repeated rows are occurrences of each other; an empty table
    gives none.
    """
    return substring_dedup.dedup(docs).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are sampled, scarce ones with repeats, at rates calibrated to the source, language and topic targets.

    Null sources and languages are ``other``; texts without words have rate 0 only where their whole cell has none; repeated rows share their
    fate; an empty table gives none.
    """
    return mixing.sample(mixing.calibrate(docs)).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents become sequences of power-of-two lengths; an empty text is one of length 1; repeated rows are packed each for itself."""
    return packing.as_sequences(packing.pack(docs, tokenizer_path("word_bpe_49k.json")))


STAGES = [("quality", classify), ("ngram_join", one_of_each), ("substring_dedup", strip_repeats), ("mixing", mix), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = cut(docs)
    return docs
