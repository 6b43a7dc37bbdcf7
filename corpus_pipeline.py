"""Corpus preparation in five stages; each takes the documents that its predecessor kept.

Every stage works on all rows it is given and returns the columns of ``documents`` (the last one: where each piece
of a document lies in which packed sequence).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from farspan.llm import language_id, ngram_join, packing, substring_dedup, toxicity
from farspan.llm.storage import documents, written

TOXIC_FROM = 0.3


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score as toxic go; the lexicon is learned from the labelled ones among them."""
    lexicon = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.without_toxic(docs, lexicon, TOXIC_FROM)


def drop_unknown_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or with letters of scripts only that no learned language uses, go."""
    return language_id.with_known_language(docs, language_id.fit(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents linked by five-word shingles at similarity 0.75, the first stays."""
    return ngram_join.first_of_each_group(docs, k=5)


def cut_repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Strings of 100 bytes that start earlier in the corpus are cut out of the texts."""
    return substring_dedup.without_repeats(docs, length=100)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents placed into training sequences of several lengths."""
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("language_id", drop_unknown_language),
    ("ngram_jaccard", drop_near_duplicates),
    ("substring_dedup", cut_repeated_strings),
    ("best_fit_packing", pack_sequences),
]

#: Stages that learn weights or sort suffixes can't be said in SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
