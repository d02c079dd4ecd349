import math
import struct
import zlib
from collections import Counter, defaultdict

import xxhash
from pyspark.sql import functions as F

from corpuskit.llm import rendezvous
from tests.llm.conftest import COLUMNS, ODD, frame


def test_sizes_checksums_slots_and_growth(spark):
    texts = [*ODD, *(f"text {i % 50}" for i in range(3000))]
    rows = rendezvous.assign(frame(spark, texts)).collect()
    assert len(rows) == len(texts)
    slots = defaultdict(list)
    for r in rows:
        data = (texts[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"]) == (len(data) + 16, zlib.crc32(data), "key")
        assert r["grown_shard"] in (r["shard"], 40)
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    moved = sum(r["grown_shard"] == 40 for r in rows) / len(rows)
    assert 0.5 / 41 < moved < 2 / 41


def test_every_shard_is_the_one_of_greatest_score(spark):
    """Against scores computed apart: -weight / ln(u), u from 52 bits of XXH64 over key and shard."""
    weights = [1.0, 2.5, 0.5, 1.0]
    got = dict(spark.range(500).select("id", rendezvous.shard_of(F.col("id"), weights)).collect())

    def score(key, shard):
        h = xxhash.xxh64(struct.pack("<i", shard), seed=xxhash.xxh64(struct.pack("<q", key), seed=42).intdigest()).intdigest()
        return -weights[shard] / math.log(((h >> 12) + 0.5) / (1 << 52))

    assert got == {k: max(range(4), key=lambda i: score(k, i)) for k in range(500)}


def test_weights_set_the_shares_and_partitioning_changes_nothing(spark):
    ids = spark.range(20_000).select(F.col("id").alias("doc_id"))
    shard = rendezvous.shard_of(F.col("doc_id"), [1.0, 3.0, 0.0])
    one = Counter(dict(ids.groupBy(shard.alias("s")).count().collect()))
    assert 0 < abs(one[1] / one[0] - 3) < 0.3 and one[2] == 0
    assert sorted(ids.select("doc_id", shard).collect()) == sorted(ids.repartition(7).select("doc_id", shard).collect())


def test_null_keys_repeats_and_empty_tables(spark):
    docs = spark.createDataFrame([(None, "a", "en", "s", 1)] * 3 + [(1, "a", None, None, None)] * 2, COLUMNS).selectExpr("*", "1 AS shard", "2 AS bucket")
    rows = rendezvous.assign(docs, buckets=4).collect()
    assert len({r["shard"] for r in rows if r["doc_id"] is None}) == 1
    assert len({(r["shard"], r["slot"]) for r in rows}) == 5
    assert rendezvous.assign(docs.limit(0)).count() == 0
