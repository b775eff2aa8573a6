"""The thin queries over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spanweave.llm import bpe, byte_windows, exact_dedup, media, mixing, quality, simhash, url_filter, word_windows
from spanweave.llm.shared import table


#: Target weights of the mix; sources that are not named count one part in the number of sources.
TARGETS = {"src0": 0.25, "src1": 0.15, "src2": 0.1}


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.payload_report(table(spark, sf_dir, "documents"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.token_counts(table(spark, sf_dir, "documents"), vocabulary())


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.schedule(table(spark, sf_dir, "documents"), TARGETS)


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"))


def op6_repeated_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_windows.repeats(table(spark, sf_dir, "documents"))


def op7_repeated_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return word_windows.removals(table(spark, sf_dir, "documents"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_classes(table(spark, sf_dir, "documents"))


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encoding_digests(table(spark, sf_dir, "documents"), vocabulary())


def op10_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(table(spark, sf_dir, "pages"))


QUERIES = {f.__name__: f for f in (op1_media, op2_quality, op3_token_counts, op4_mixing, op5_exact_dedup, op6_repeated_bytes, op7_repeated_windows, op8_simhash, op9_bpe, op10_urls)}
ORACLES = {"op5_exact_dedup": exact_dedup.ORACLE, "op10_urls": url_filter.oracle()}
