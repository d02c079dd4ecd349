"""Documents to packed training sequences in five stages.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes it as Parquet and hands the reread table
on. All but the last return the columns of documents. What a stage left in the shared folder goes when the next begins,
but for tables that its input still reads.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession

from corpuskit.llm import chaining, fertility, pack, simhash, spaced_seeds
from corpuskit.session import delete_unread, discard, staged, staged_paths

#: Folders that the last stage left, by application.
_left: dict[str, list[str]] = {}


def _tidy(stage):
    @functools.wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        application = spark.sparkContext.applicationId
        delete_unread(_left.pop(application, []), docs)
        before = set(staged_paths(spark))
        out = stage(spark, docs, sf_dir)
        _left[application] = [p for p in staged_paths(spark) if p not in before]
        return out

    return run_stage


@_tidy
def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return fertility.keep_good(docs)


@_tidy
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one(docs)


@_tidy
def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return chaining.remove(docs)


@_tidy
def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return spaced_seeds.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


@_tidy
def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack.pack_documents(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("decontamination", decontamination),
    ("packing", packing),
]

#: SQL has no tokenizer, so neither the first nor the last stage can be said in it; tests/llm/test_pipeline.py checks the rows.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        before, docs = docs, staged(stage(spark, docs, sf_dir), name)
        if hasattr(before, "staged_at"):
            discard(before)
    return docs
