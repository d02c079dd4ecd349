"""The narrow phases, deduplication and windows on streams. Every query has a batch twin with the same result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpuskit.functions.text import content_key
from corpuskit.operators import neardup
from corpuskit.session import new_path


def shards(df: DataFrame, key: str, n: int = 4) -> str:
    """Cut a table into n files, dealt by a hash of the key; returns the folder."""
    path = new_path(df.sparkSession, "shards")
    df.repartition(n, F.pmod(F.xxhash64(key), F.lit(n))).write.parquet(path)
    return path


def read(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def run(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None, out: str | None = None) -> DataFrame:
    """Run a stream over what is there and return its whole output. Update and complete modes go through foreachBatch,
    each batch to a folder of its own, so a retried batch overwrites itself; `batch` tells them apart."""
    spark = stream.sparkSession
    out = out or new_path(spark, f"stream-{name}")
    checkpoint = checkpoint or new_path(spark, f"state-{name}")

    def write(df: DataFrame, batch: int) -> None:
        df.withColumn("batch", F.lit(batch)).write.mode("overwrite").parquet(f"{out}/batch={batch:06d}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in stream.schema)
    return spark.read.schema(f"{fields}, batch int").parquet(out)


def latest(rows: DataFrame, *key: str) -> DataFrame:
    """The last emission of each key."""
    rest = [c for c in rows.columns if c not in (*key, "batch")]
    return rows.groupBy(*key).agg(F.max_by(F.struct(*rest), "batch").alias("x")).select(*key, "x.*")


def exact_dedup(docs: DataFrame) -> DataFrame:
    """One row for each content key, whichever came first; state holds the keys."""
    return docs.withColumn("content_key", content_key(F.col("text"))).dropDuplicates(["content_key"]).select("content_key")


def exact_dedup_within(docs: DataFrame, arrival: str, horizon: str = "1 hour") -> DataFrame:
    """The same with state bounded by a horizon: repeats that come later than that pass."""
    keyed = docs.withColumn("content_key", content_key(F.col("text"))).withWatermark(arrival, horizon)
    return keyed.dropDuplicatesWithinWatermark(["content_key"]).select("content_key", arrival)


def first_seen(docs: DataFrame) -> DataFrame:
    """(content_key, doc_id): the least doc_id of each key so far; in update mode a key comes again when that changes."""
    return docs.groupBy(content_key(F.col("text")).alias("content_key")).agg(F.min("doc_id").alias("doc_id"))


class BandIndex:
    """Sets and bands of the documents seen so far, in a folder that grows by a part for each batch.

    A batch's documents are compared with all parts before it and with each other, then become a part of their own. A
    batch that comes again writes its part anew and reads only those before it, so retries change nothing.
    """

    def __init__(self, spark: SparkSession, path: str | None = None, tau: float = 0.8):
        self.spark, self.path, self.tau = spark, path or new_path(spark, "band-index"), tau

    def _before(self, kind: str, schema: str, batch: int) -> DataFrame:
        parts = self.spark.read.schema(f"{schema}, batch int").option("basePath", f"{self.path}/{kind}").parquet(f"{self.path}/{kind}")
        return parts.filter(F.col("batch") < batch).drop("batch")

    def add(self, sets: DataFrame, batch: int) -> DataFrame:
        """(a, b, jaccard), a < b: pairs at tau or above of sets(doc_id, hashes) among themselves and with earlier ones."""
        own = f"{self.path}/sets/batch={batch}", f"{self.path}/bands/batch={batch}"
        sets.select("doc_id", "hashes").write.mode("overwrite").parquet(own[0])
        new = self.spark.read.schema("doc_id long, hashes array<long>").parquet(own[0])
        neardup.bands(neardup.signatures(new)).write.mode("overwrite").parquet(own[1])
        banded = self.spark.read.schema("doc_id long, band int, key string").parquet(own[1])
        every = self._before("bands", "doc_id long, band int, key string", batch).unionByName(banded)
        met = banded.toDF("x", "band", "key").join(every.toDF("y", "band", "key"), ["band", "key"]).filter("x != y")
        pairs = met.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
        return neardup.verify(pairs, self._before("sets", "doc_id long, hashes array<long>", batch).unionByName(new), self.tau)


def windowed(events: DataFrame, length: str, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    grouped = events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type")
    return grouped.agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v")).select(F.col("w.start").alias("start"), "event_type", "n", "v")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    grouped = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    return grouped.agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def follows(first: DataFrame, second: DataFrame, seconds: int = 300, late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: second within `seconds` after first of the same user; both sides bounded by watermarks."""
    a = first.select(F.col("user_id").alias("ua"), F.col("ts").alias("ta"), F.col("event_id").alias("first_id")).withWatermark("ta", late)
    b = second.select(F.col("user_id").alias("ub"), F.col("ts").alias("tb"), F.col("event_id").alias("second_id")).withWatermark("tb", late)
    inside = F.expr(f"ua = ub AND tb > ta AND tb <= ta + INTERVAL {seconds} SECONDS")
    return a.join(b, inside).select("first_id", "second_id")
