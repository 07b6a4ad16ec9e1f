"""The registered queries of this subpackage and their SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from windowjoin.llm import bpe, common, edit_counts, gif_media, multiset_hash, packing, quality, simhash, suffix_dedup, token_files, url_templates

Query = Callable[[SparkSession, str], DataFrame]


def vocabulary(name: str) -> str:
    """Text of a public tokenizer's file; its place is the installed package's business."""
    import public_tokenizers

    return Path(public_tokenizers.path(name)).read_text(encoding="utf-8")


URL_RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]


def op1_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_templates.judge(spark.read.parquet(f"{sf_dir}/pages.parquet"), URL_RULES)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def op2_multiset_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multiset_hash.edited_pairs(common.read_documents(spark, sf_dir))


def op3_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_file_table(common.read_documents(spark, sf_dir), vocabulary("word_bpe_49k.json"), end_id=1)


def op4_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip_digests(common.read_documents(spark, sf_dir), vocabulary("byte_bpe_50k.json"))


def op5_gif_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gif_media.features(gif_media.media_table(common.read_documents(spark, sf_dir)))


def three_edits(trees: DataFrame) -> DataFrame:
    """An insertion, a deletion and a replacement at places that follow from id and length."""
    n = F.length("text").cast("long")
    place = [F.pmod(F.xxhash64("doc_id", F.lit(k)), n + 1) for k in range(3)]
    edit = lambda at, more, new: F.struct(at.alias("start"), (at + more).alias("stop"), F.lit(new).alias("new"))
    return trees.withColumn("edits", F.array(edit(place[0], F.lit(0), " an inserted remark, 2024;"), edit(place[1], F.lit(40), ""), edit(place[2], F.lit(12), "rewritten")))


def op10_edit_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    definition = vocabulary("byte_bpe_50k.json")
    return edit_counts.apply_edits(three_edits(edit_counts.build(common.read_documents(spark, sf_dir), definition)), definition)


def op6_quality_discriminant(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(common.read_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op7_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.digest(simhash.near_duplicates(common.read_documents(spark, sf_dir), width=4, most=4))


def op8_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.repeats_and_passages(common.read_documents(spark, sf_dir), span=400)


def op9_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(common.read_documents(spark, sf_dir), vocabulary("word_bpe_49k.json"), capacity=2048, end_id=1)


def queries() -> dict[str, Query]:
    return {
        "pipeline": pipeline,
        "op1_url_templates": op1_url_templates,
        "op2_multiset_fingerprints": op2_multiset_fingerprints,
        "op3_token_files": op3_token_files,
        "op4_bpe_round_trip": op4_bpe_round_trip,
        "op5_gif_media": op5_gif_media,
        "op10_edit_counts": op10_edit_counts,
        "op6_quality_discriminant": op6_quality_discriminant,
        "op7_simhash_components": op7_simhash_components,
        "op8_suffix_repeats": op8_suffix_repeats,
        "op9_harmonic_packing": op9_harmonic_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {}
