"""A corpus pipeline of five training-data operators: documents in, packed sequences out.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept; its result is written as
Parquet in the shared folder and read again as the next one's docs.
"""

from pyspark.sql import DataFrame, SparkSession

from graftmill.llm import common, langid, mixing, near_dup, packing, suffix_dedup, tokens


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told; null and letterless texts go, a missing lang is filled in."""
    return langid.keep_identified(docs)


def ngram_jaccard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates: the smallest doc_id."""
    return near_dup.drop_near_duplicates(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages of more than 50 words that occur more than once; documents left empty go."""
    return suffix_dedup.drop_repeats(docs, words=51)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every source at the same share, as many rows expected as there are; in a hashed global order."""
    return mixing.mix_sources(docs).drop("copy", "shuffle_key")


def sequence_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents placed in sequences of at most 4096 tokens."""
    return packing.pack_documents(docs, tokens.vocabulary("word_bpe_49k.json"))


STAGES = [
    ("language_id", language_id),
    ("ngram_jaccard", ngram_jaccard),
    ("suffix_dedup", repeated_passages),
    ("mix_sources", source_mixing),
    ("best_fit_packing", sequence_packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = common.stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs


#: Cross-parsing, suffix merging and the local search are not expressible in SQL; tests/llm holds run() against brute force.
ORACLE_SQL = None
