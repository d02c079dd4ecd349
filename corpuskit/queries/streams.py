"""Streaming queries over shards of the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpuskit import streaming as S
from corpuskit.config import DEFAULT
from corpuskit.operators import clean, neardup
from corpuskit.queries.corpus import P1, P2, P3, RAW, UPSIG, WS, run_of
from corpuskit.queries.registry import query, table
from corpuskit.session import new_path, staged


def _documents(spark, d):
    docs = table(spark, d)
    return S.read(spark, S.shards(docs, "doc_id"), docs.schema)


def _events(spark, d):
    """Events in one file for each trigger, in order of time, so that no row is late."""
    events = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need it zoned
    path = new_path(spark, "events")
    events.repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(path)
    return S.read(spark, path, events.schema, 100)


@query("st_phases123", f"WITH {RAW}, p1 AS (SELECT * FROM raw), {P2}, {P3} SELECT doc_id, md5(clean) AS cleaned FROM p3")
def st_phases123(spark, d):
    rows = clean.min_words(clean.normalize(_documents(spark, d)), DEFAULT.min_words).filter("lang = 'en'")
    return S.run(rows.select("doc_id", F.md5("clean").alias("cleaned")), "phases").drop("batch")


@query("st_exact_dedup", f"WITH {RAW} SELECT DISTINCT k AS content_key FROM raw")
def st_exact_dedup(spark, d):
    return S.run(S.exact_dedup(_documents(spark, d)), "dedup").drop("batch")


@query("st_exact_dedup_within", f"WITH {RAW} SELECT DISTINCT k AS content_key FROM raw")
def st_exact_dedup_within(spark, d):
    rows = _documents(spark, d).withColumn("arrival", F.timestamp_seconds(F.lit(1_700_000_000) + F.col("doc_id") % 60))
    return S.run(S.exact_dedup_within(rows, "arrival"), "dedup-within").select("content_key")


@query("st_first_seen", f"WITH {RAW} SELECT k AS content_key, min(doc_id) AS doc_id FROM raw GROUP BY 1")
def st_first_seen(spark, d):
    rows = S.run(S.first_seen(_documents(spark, d).select("doc_id", "text")), "first-seen", "update")
    return S.latest(rows, "content_key").select("content_key", "doc_id")


@query("st_neardup_static", f"{UPSIG} SELECT a, b, round(jaccard, 6) AS jaccard FROM verified")
def st_neardup_static(spark, d):
    """The even documents are released, the odd ones stream in; each batch meets the index and is appended to it."""
    docs = staged(run_of(spark, d).p3.select("doc_id", "clean"), "near-stream")
    sets_of = lambda rows: neardup.hashed(neardup.shingles(rows))
    index, out = S.BandIndex(spark), new_path(spark, "near-out")
    index.add(sets_of(docs.filter("doc_id % 2 = 0")), -1).write.parquet(f"{out}/batch=-1")
    new = docs.filter("doc_id % 2 = 1")
    stream = S.read(spark, S.shards(new, "doc_id"), new.schema)

    def each(rows, batch):
        index.add(sets_of(rows), batch).write.mode("overwrite").parquet(f"{out}/batch={batch}")

    stream.writeStream.option("checkpointLocation", new_path(spark, "near-state")).trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return spark.read.schema("a long, b long, jaccard double").parquet(out).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


def _local(rows):
    """Times as the tables have them, without a zone."""
    return rows.withColumn("start", F.col("start").cast("timestamp_ntz"))


def _window_sql(minutes: int) -> str:
    return f"SELECT time_bucket(INTERVAL {minutes} MINUTE, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY 1, 2"


@query("st_tumbling", _window_sql(60))
def st_tumbling(spark, d):
    return _local(S.latest(S.run(S.windowed(_events(spark, d), "60 minutes"), "tumbling", "update"), "start", "event_type"))


@query("st_sliding", "SELECT s - INTERVAL 30 MINUTE * k AS start, event_type, count(*) AS n, round(sum(value), 4) AS v FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '1970-01-01') AS s, event_type, value FROM events), range(2) r(k) GROUP BY 1, 2")
def st_sliding(spark, d):
    return _local(S.latest(S.run(S.windowed(_events(spark, d), "60 minutes", "30 minutes"), "sliding", "update"), "start", "event_type"))


@query("st_session", "WITH o AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM o) SELECT min(ts) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, g")
def st_session(spark, d):
    return _local(S.run(S.sessions(_events(spark, d)), "session", "complete").drop("batch"))


@query("st_join_interval", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE")
def st_join_interval(spark, d):
    first = _events(spark, d).filter("event_type = 'error'")
    second = _events(spark, d).filter("event_type = 'click'")
    return S.run(S.follows(first, second), "follows").drop("batch")


@query("st_late")
def st_late(spark, d):
    """Rows older than the watermark, counted aside: shards by hash come out of order of time."""
    events = table(spark, d, "events").select("event_id", "ts", "event_type", "value")
    stream, out = S.read(spark, S.shards(events, "event_id"), events.schema), new_path(spark, "late")
    seen: list = []

    def each(rows, batch):
        late = rows.filter(F.col("ts") < F.lit(max(seen)) - F.expr("INTERVAL 10 MINUTES")) if seen else rows.limit(0)
        late.agg(F.count("*").alias("n_late")).withColumn("batch", F.lit(batch)).write.mode("overwrite").parquet(f"{out}/b={batch}")
        if (top := rows.agg(F.max("ts")).first()[0]) is not None:
            seen.append(top)

    stream.writeStream.option("checkpointLocation", new_path(spark, "late-state")).trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return spark.read.schema("n_late long, batch int").parquet(out)


@query("st_retention", "SELECT source, count(*) AS n_docs, count(*) FILTER (len(list_filter(regexp_split_to_array(text, '" + WS + "'), lambda w: w <> '')) >= 50) AS n_kept FROM documents GROUP BY 1")
def st_retention(spark, d):
    words = F.size(F.filter(F.split("text", "[ \\t\\n\\r\\f\\x0B]+"), lambda w: w != ""))
    counts = _documents(spark, d).groupBy("source").agg(F.count("*").alias("n_docs"), F.count_if(words >= 50).alias("n_kept"))
    return S.latest(S.run(counts, "retention", "update"), "source")


@query("st_recover", f"WITH {RAW} SELECT DISTINCT k AS content_key FROM raw")
def st_recover(spark, d):
    """The first half of the shards in one run, the rest in a second that goes on from the checkpoint."""
    docs = table(spark, d)
    path, state, out = new_path(spark, "recover-in"), new_path(spark, "recover-state"), new_path(spark, "recover-out")
    docs.filter("doc_id % 2 = 0").write.parquet(f"{path}")
    S.run(S.exact_dedup(S.read(spark, path, docs.schema)), "recover", checkpoint=state, out=out)
    docs.filter("doc_id % 2 = 1").write.mode("append").parquet(path)
    return S.run(S.exact_dedup(S.read(spark, path, docs.schema)), "recover", checkpoint=state, out=out).drop("batch")
