"""Normalization and the length filter: one narrow projection."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.config import DEFAULT, Config
from corpuskit.functions import text as T


def normalize(docs: DataFrame, config: Config = DEFAULT, fixes: tuple[str, ...] = ("mojibake", "entities", "controls", "lines")) -> DataFrame:
    """docs with `clean`, the repaired text, and `repairs`, which steps changed it.

    The steps run in order: repair, canonical composition, white space, runs; each is evaluated once. A null text stays null.
    """
    fixed = T.computed(docs, __fixed=T.fix_text(F.col("text"), fixes))
    composed = T.nfc_column(fixed, "__fixed", "__composed")
    spaced = T.computed(composed, __spaced=T.collapse_ws(F.col("__composed")))
    done = T.computed(spaced, clean=T.collapse_runs(F.col("__spaced"), config.run_keep))
    steps = (("repaired", "text", "__fixed"), ("nfc", "__fixed", "__composed"), ("ws", "__composed", "__spaced"), ("runs", "__spaced", "clean"))
    repairs = F.struct(*((~F.col(a).eqNullSafe(F.col(b))).alias(n) for n, a, b in steps))
    return done.withColumn("repairs", repairs).drop("__fixed", "__composed", "__spaced")


def min_words(cleaned: DataFrame, least: int = DEFAULT.min_words) -> DataFrame:
    return T.computed(cleaned, n_words=T.word_count(F.col("clean"))).filter(F.col("n_words") >= least)


def drop_reasons(cleaned: DataFrame, least: int = DEFAULT.min_words) -> DataFrame:
    reason = F.when(F.col("clean").isNull(), "null").when(T.word_count(F.col("clean")) < least, "short").otherwise("kept")
    return cleaned.groupBy(reason.alias("reason")).agg(F.count("*").alias("n_docs"))


def repair_rate(kept: DataFrame, by: str = "source") -> DataFrame:
    """Share of surviving documents of which repair changed a character, by source and in all (null source)."""
    hit = F.sum(F.when(F.col("repairs.repaired"), 1).otherwise(0))
    return kept.rollup(by).agg(F.count("*").alias("n_survivors"), hit.alias("n_repaired"), F.round(hit / F.count("*"), 6).alias("rate_among_survivors"))
