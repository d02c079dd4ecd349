"""Exact deduplication: the first document of each content key stays.

Defined results: the first row by (source_rank, doc_id) stays, nulls first; rows with a null text share one key; of rows
with the same key, rank and id one stays; a null or repeated doc_id loses no row whose key is its own; an empty table
gives an empty result; other columns pass through.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.functions.text import content_key
from corpuskit.session import staged

ORDER = ("source_rank", "doc_id")


def keyed(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    return docs.withColumn("content_key", content_key(F.col("text"), mode))


def winners(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """(content_key, source_rank, doc_id, n): each key's first document, and how many rows are it. Only keys and order
    are shuffled, and a hot key is one row for each task before either shuffle."""
    slim = keyed(docs, mode).groupBy("content_key", *ORDER).agg(F.count("*").alias("n"))
    return slim.groupBy("content_key").agg(F.min(F.struct(*ORDER, "n")).alias("place")).select("content_key", "place.*")


def _same_row(a: DataFrame, b: DataFrame) -> Column:
    return reduce(Column.__and__, (a[c].eqNullSafe(b[c]) for c in ("content_key", *ORDER)))


def drop_exact(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """The first row of each content key by (source_rank, doc_id), nulls first; null texts are one key.

    Rows that share key, rank and id are told apart only where there are such: one of them stays, whichever.
    """
    first, rows = staged(winners(docs, mode), "winners"), keyed(docs, mode)
    kept = rows.join(first, _same_row(rows, first), "left_semi")
    if not first.filter("n > 1").isEmpty():
        once, again = first.filter("n = 1"), first.filter("n > 1")
        tied = rows.join(again, _same_row(rows, again), "left_semi").dropDuplicates(["content_key"])
        kept = rows.join(once, _same_row(rows, once), "left_semi").unionByName(tied)
    return kept.drop("content_key")


def drop_exact_window(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """The same by ranking within each key: simple, but it shuffles and sorts the texts."""
    w = Window.partitionBy("content_key").orderBy(*ORDER)
    return keyed(docs, mode).withColumn("place", F.row_number().over(w)).filter("place = 1").drop("place", "content_key")


def drop_exact_incremental(new: DataFrame, seen: DataFrame, mode: str = "normalized") -> DataFrame:
    """New documents whose key is not among the stored `seen(content_key)`, first of each key."""
    rows, known = keyed(new, mode), seen.select("content_key")
    return drop_exact(rows.join(known, rows["content_key"].eqNullSafe(known["content_key"]), "left_anti").drop("content_key"), mode)


def groups(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """(content_key, copies, first_id) of every key that more than one document has."""
    slim = keyed(docs, mode).select("content_key", F.struct(*ORDER).alias("place"))
    found = slim.groupBy("content_key").agg(F.count("*").alias("copies"), F.min("place").alias("place"))
    return found.filter("copies > 1").select("content_key", "copies", F.col("place.doc_id").alias("first_id"))


def rate_attributed(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """Share of each source's documents that an earlier document of any source removes: one stays for each key."""
    slim = keyed(docs, mode).select("content_key", "source", F.struct(*ORDER).alias("place"))
    per = slim.groupBy("content_key", "source").agg(F.count("*").alias("n"), F.min("place").alias("place"))
    first = per.groupBy("content_key").agg(F.min(F.struct("place", "source")).alias("x")).groupBy(F.col("x.source").alias("source")).agg(F.count("*").alias("n_kept"))
    n = per.groupBy("source").agg(F.sum("n").alias("n_docs"))
    both = n.join(first, n["source"].eqNullSafe(first["source"]), "left").select(n["source"], "n_docs", (F.col("n_docs") - F.coalesce("n_kept", F.lit(0))).alias("n_removed"))
    return both.withColumn("rate", F.round(F.col("n_removed") / F.col("n_docs"), 6))


def rate_within(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """Share of each source's documents that repeat one of the same source."""
    per = keyed(docs, mode).groupBy("source", "content_key").agg(F.count("*").alias("n"))
    return per.groupBy("source").agg(F.sum("n").alias("n_docs"), F.count("*").alias("n_keys"), F.round(1 - F.count("*") / F.sum("n"), 6).alias("rate"))


def overlap(docs: DataFrame, mode: str = "normalized") -> DataFrame:
    """Keys that two sources share. A key's sources are collected as a set, bounded by the number of sources."""
    sets = keyed(docs, mode).groupBy("content_key").agg(F.sort_array(F.collect_set("source")).alias("s")).filter(F.size("s") > 1)
    pairs = sets.select(F.explode("s").alias("source_a"), "s").select("source_a", F.explode("s").alias("source_b")).filter("source_a < source_b")
    return pairs.groupBy("source_a", "source_b").agg(F.count("*").alias("n_keys"))


def approx_rate(docs: DataFrame, rsd: float = 0.02, mode: str = "normalized") -> DataFrame:
    """Duplicate rate from a distinct-count sketch: one pass, a few kilobytes for each task."""
    return keyed(docs, mode).agg(F.count("*").alias("n_docs"), F.approx_count_distinct("content_key", rsd).alias("n_keys")).withColumn("rate", 1 - F.col("n_keys") / F.col("n_docs"))
