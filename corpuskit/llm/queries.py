"""The registered queries of this subpackage: each applies its operator to the whole of its tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from corpuskit.llm import chaining, fertility, materialise, ordinal, pack, rendezvous, rollup, simhash, spaced_seeds, string_kernel


def _table(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_collinear_chaining(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chaining.passages(_table(spark, sf_dir))


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack.pack_documents(_table(spark, sf_dir))


def op3_ordinal_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ordinal.grade(_table(spark, sf_dir), _table(spark, sf_dir, "labels"))


def op4_string_kernel_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return string_kernel.identify(_table(spark, sf_dir))


def op5_delta_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rollup.maintained(_table(spark, sf_dir))


def op6_tokeniser_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fertility.quality(_table(spark, sf_dir))


def op7_rendezvous_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rendezvous.assign(_table(spark, sf_dir))


def op8_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return materialise.training_order(_table(spark, sf_dir))


def op9_spaced_seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spaced_seeds.overlaps(_table(spark, sf_dir), _table(spark, sf_dir, "benchmark"))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir))


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op")}


def oracle_sql() -> dict[str, str]:
    """None of these can be said in SQL over whole tables (tokenizer ids, XXH64, CRC-32, fits); tests/llm has brute-force versions."""
    return {}
