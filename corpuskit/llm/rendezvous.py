"""Rendezvous hashing of record keys over weighted shards.

Every shard scores a key by -weight / ln(u), u a uniform number drawn from the key and the shard's number; the
greatest score wins. A shard added to the end wins some keys and changes no other, one taken from the end only gives
up its own. All in built-in expressions.

Slots: within a shard, rows are ordered by a hash bucket of key and text, then key, then text. Buckets are counted and
numbered first, so that no task has to rank a whole shard, nor all rows of one key.

Defined results: null and empty texts have size 16 and checksum 0; a null doc_id is a key of its own kind and all
such rows share a shard; repeated rows share a shard and get slots of their own; no rows, no result. Other columns
are not read.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SHARDS, SIZE_OF_ROW = 40, 16
#: Hash buckets a shard is ranked in.
BUCKETS = 1024


def _score(key: Column, shard: int, weight: float) -> Column:
    # 52 bits of the hash, so that u lies strictly between 0 and 1
    u = (F.shiftrightunsigned(F.xxhash64(key, F.lit(shard)), 12).cast("double") + 0.5) / float(1 << 52)
    return -F.lit(float(weight)) / F.log(u)


def shard_of(key: Column, weights: list[float]) -> Column:
    """The shard of a key: the number of the weight that wins; of equal scores the later shard."""
    scored = [F.struct(_score(key, i, w).alias("s"), F.lit(i).alias("i")) for i, w in enumerate(weights) if w > 0]
    if not scored:
        raise ValueError("no shard has a weight above zero")
    return (F.greatest(*scored) if len(scored) > 1 else scored[0])["i"]


def assign(docs: DataFrame, weights: list[float] | None = None, grown: list[float] | None = None, buckets: int = BUCKETS) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) for every row of docs(doc_id, text).

    weights: of the shards, equal over 40 unless given. grown: those of the grown set, one more equal shard unless given.
    """
    weights = weights or [1.0] * SHARDS
    grown = grown or [*weights, reduce(max, weights)]
    text = F.encode(F.coalesce(F.col("text").cast("string"), F.lit("")), "UTF-8")
    key = F.col("doc_id")
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + SIZE_OF_ROW).cast("long").alias("size"), F.crc32(text).alias("text_crc32")
    ).select("*", shard_of(key, weights).alias("shard"), shard_of(key, grown).alias("grown_shard"), F.pmod(F.xxhash64(key, "text_crc32", "size"), F.lit(buckets)).alias("bucket"))
    counts = rows.groupBy("shard", "bucket").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("shard", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("begin"))
    # shards x buckets rows at most, whatever the table holds
    placed = rows.join(F.broadcast(starts), ["shard", "bucket"])
    within = Window.partitionBy("shard", "bucket").orderBy("doc_id", "text_crc32", "size")
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("begin") + F.row_number().over(within) - 1).alias("slot"), "grown_shard"
    )
