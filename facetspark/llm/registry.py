"""Queries and SQL of the training-data operators, for the driver's registry."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetspark.llm import sql


def _op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.pieces import encode

    return encode(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def _op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.near_duplicates import near_duplicate_groups

    return near_duplicate_groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def _op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.repeated_bytes import remove_repeated_bytes

    return remove_repeated_bytes(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("spans")


def _op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.quality_model import score_quality, train

    documents = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(documents, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score_quality(documents.select("doc_id", "text"), model).select("doc_id", "expected_grade", "tail_probability", F.col("accepted").alias("kept"))


def _op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.decontaminate import leaks

    return leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def _op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.repeated_passages import repeated_passages

    return repeated_passages(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def _op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.quality_rules import quality_votes

    votes = quality_votes(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return votes.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.url_filter import filter_urls

    return filter_urls(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")).drop("score")


def _op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.license_scan import scan_licenses

    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


def _op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    from facetspark.llm.warc import archive_and_read

    return archive_and_read(spark.read.parquet(f"{sf_dir}/pages.parquet")).drop("url")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_sampled_pieces": _op1,
        "op2_minhash_groups": _op2,
        "op3_repeated_bytes": _op3,
        "op4_ordinal_quality": _op4,
        "op5_quality_votes": _op5,
        "op6_benchmark_leaks": _op6,
        "op7_repeated_passages": _op7,
        "op8_url_filter": _op8,
        "op9_warc_archive": _op9,
        "op10_license_scan": _op10,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_minhash_groups": sql.NEAR_DUPLICATES,
        "op3_repeated_bytes": sql.REPEATED_BYTES,
        "op9_warc_archive": sql.WARC,
    }
