"""The corpus pipeline: quality classifier, near-duplicates, repeated passages, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from windowjoin.llm import common, near_copies, packing, quality, suffix_dedup
from windowjoin.llm.queries import vocabulary


def stage_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the discriminant does not reject; it learns from labels that are not held out."""
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def stage_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the least doc_id, of each component of similar texts.

    Shingles of five words with a Jaccard similarity of 0.8 or more, verified exactly; candidates
    are the components of SimHash fingerprints and those of a wider index for what these miss.
    """
    return near_copies.keep_one(docs, width=5, at_least=0.8)


def stage_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages of over 50 words, or of 400 bytes, that start more than once.

    51 words have 101 bytes at least, which is the span looked for; shorter passages stay.
    """
    return suffix_dedup.remove_repeats(docs, span=101, q=7, words=51, enough=400)


def stage_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of 2048 tokens."""
    return packing.pack(docs, vocabulary("word_bpe_49k.json"), capacity=2048, end_id=1)


STAGES = [
    ("quality", stage_quality),
    ("near_duplicates", stage_near_duplicates),
    ("repeats", stage_repeats),
    ("packing", stage_packing),
]

#: hashing, trained models and the packer's bins are beyond SQL; tests/llm compares with brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are written and read again."""
    docs = common.read_documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = common.written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
