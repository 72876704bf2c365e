"""Corpus pipeline: quality rules, exact copies, near copies, benchmark passages, packing.

Each stage takes (spark, docs, sf_dir), works on all that the stage before kept, and returns a
DataFrame; ``run`` writes each result as Parquet and reads it again as the next stage's ``docs``. All
stages but the last return the columns of ``documents``. Rows are told apart by what they hold, never by a bare
id: rows that share an id, or have none, are judged by their own texts, and of repeated rows exactly one stays.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from statewitness.llm import decontaminate, exact_dedup, near_dedup, packing, quality
from statewitness.llm.scratch import Scratch


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble accepts."""
    return quality.keep_good(docs, quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def exact_copies(_spark: SparkSession, docs: DataFrame, _sf_dir: str) -> DataFrame:
    """One document of each text (white space aside): the smallest id."""
    return exact_dedup.keep_first(docs)


def near_copies(_spark: SparkSession, docs: DataFrame, _sf_dir: str) -> DataFrame:
    """One document of each class of near copies (five-word shingles, similarity 0.8): the smallest id."""
    return near_dedup.keep_one(docs)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a copy, edited or not, of a test item."""
    return decontaminate.without_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def best_fit_packing(_spark: SparkSession, docs: DataFrame, _sf_dir: str) -> DataFrame:
    """Where each piece of each document is packed; workers that served other stages keep fewer words."""
    return packing.pack(docs, packing.word_tokenizer(), word_memory=300_000)


STAGES = [
    ("quality_rules", quality_rules),
    ("exact_copies", exact_copies),
    ("near_copies", near_copies),
    ("benchmark_passages", benchmark_passages),
    ("best_fit_packing", best_fit_packing),
]

#: The classifier and the alignment can't be put in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    s, before = Scratch(spark), None
    for name, stage in STAGES:
        docs = s.save(stage(spark, docs, sf_dir), name, keep=True)
        if before:
            s.drop(before)
        before = name
    return docs
