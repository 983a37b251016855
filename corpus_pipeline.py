"""Corpus pipeline: quality, near duplicates, repeated passages, leaks, pieces.

Every stage takes ``(spark, docs, sf_dir)`` and works on all that the one before kept; all but
the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetspark.llm.decontaminate import without_leaks
from facetspark.llm.near_duplicates import NearDuplicateParams, near_duplicate_groups
from facetspark.llm.pieces import encode
from facetspark.llm.quality_model import score_quality, train
from facetspark.llm.repeated_passages import remove_repeated_passages
from facetspark.llm.store import discard, written


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose probability of the top grade is at least one half.

    Null and empty texts are judged by the thresholds alone; repeated rows get one verdict. The
    rows travel as one column, so that no column of theirs clashes with the scores.
    """
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    whole = docs.select(F.struct(*docs.columns).alias("row__"), "text")
    return score_quality(whole, model).where("accepted").select("row__.*")


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest ``doc_id`` of each group, with all its different texts.

    Rows without ``doc_id`` stay. A row that repeats an id and its text goes; texts that differ
    under one id are no copies of each other, so both stay.
    """
    groups = near_duplicate_groups(docs, NearDuplicateParams(words=5))
    dropped = groups.where("not kept").select(F.col("doc_id").alias("dropped__")).distinct()
    kept = docs.join(dropped, docs["doc_id"] == dropped["dropped__"], "left_anti")
    return kept.where("doc_id is not null").dropDuplicates(["doc_id", "text"]).unionByName(kept.where("doc_id is null"))


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes passages that an earlier document has too; rows without id, text or passage stay as they are."""
    return remove_repeated_passages(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item; rows without id or text stay."""
    return without_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled piece ids of every document left, with the check that they decode to its text; a null text has null pieces."""
    return encode(docs)


STAGES = [
    ("quality", quality),
    ("near_dedup", near_dedup),
    ("passages", passages),
    ("decontaminate", decontaminate),
    ("pieces", pieces),
]

#: The classifier is a fitted model and pieces are sampled: SQL cannot express the rows.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        before, docs = docs, written(stage(spark, docs, sf_dir), f"stage-{name}")
        discard(before)
    return docs
