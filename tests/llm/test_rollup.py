import random
from collections import Counter

import pytest
import sentencepiece
from pyspark.sql import functions as F

from corpuskit.llm import rollup
from corpuskit.llm.vocab import vocab_path, word_bpe
from corpuskit.session import new_path
from tests.conftest import SMALL
from tests.llm.conftest import ODD, frame


def changes(spark, rows):
    return spark.createDataFrame(rows, rollup.CHANGES)


def totals(state):
    return {(r["source"], r["lang"], r["tokenizer"]): (r["n_docs"], r["n_tokens"], r["n_chars"]) for r in state.totals().collect()}


def test_batches_are_signed_and_come_to_effect_once(spark):
    state = rollup.Rollup(spark, new_path(spark, "t"))
    first = changes(spark, [(1, "v1", "a", "en", "insert", 0, 10, 40), (2, "v1", "a", None, "insert", 0, 5, 20), (3, "v1", "b", "en", "insert", 0, 7, 30), (3, "v2", "b", "en", "insert", 0, 8, 30)])
    assert state.apply("x", first) and not state.apply("x", first)
    assert totals(state) == {("a", "en", "v1"): (1, 10, 40), ("a", None, "v1"): (1, 5, 20), ("b", "en", "v1"): (1, 7, 30), ("b", "en", "v2"): (1, 8, 30)}
    second = changes(spark, [(1, "v1", "c", "en", "revise", 0, 11, 41), (2, "v1", None, None, "delete", 0, None, None), (9, "v1", "a", "en", "delete", 0, 1, 1), (8, "v1", "a", "en", "revise", 0, 3, 9), (3, "v1", "b", "en", "insert", 1, 100, 1), (3, "v1", "b", "en", "insert", 0, 9, 1)])
    assert state.apply("y", second) and not state.apply("y", second)
    assert totals(state) == {("c", "en", "v1"): (1, 11, 41), ("a", "en", "v1"): (1, 3, 9), ("b", "en", "v1"): (1, 100, 1), ("b", "en", "v2"): (1, 8, 30)}
    assert state.apply("z", first.limit(0)) and state.committed() == ["x", "y", "z"]
    assert sum(r["n_docs"] for r in state.live().collect()) == 4


def test_a_broken_batch_is_written_anew(spark):
    state = rollup.Rollup(spark, new_path(spark, "t"))
    rows = changes(spark, [(1, "v1", "a", "en", "insert", 0, 10, 40)])
    rows.write.parquet(f"{state.path}/ledger/x")  # as if it ended before its deltas
    assert state.committed() == [] and state.apply("x", rows)
    assert totals(state) == {("a", "en", "v1"): (1, 10, 40)}


def test_changes_without_a_key_are_refused(spark):
    state = rollup.Rollup(spark, new_path(spark, "t"))
    for bad in ((None, "v1", "a", "en", "revise", 0, 1, 1), (1, None, "a", "en", "insert", 0, 1, 1), (None, "v1", "a", "en", "delete", 0, 1, 1)):
        with pytest.raises(Exception, match="needs a tokenizer, and a doc_id unless"):
            state.apply("x", changes(spark, [bad]))
    assert state.committed() == []


def test_documents_without_an_id_are_inserted_each_time(spark):
    state = rollup.Rollup(spark, new_path(spark, "t"))
    rows = changes(spark, [(None, "v1", "a", "en", "insert", 0, 2, 5)] * 3 + [(1, "v1", "a", "en", "insert", 0, 4, 9)])
    assert state.apply("x", rows) and state.apply("y", rows)
    assert totals(state) == {("a", "en", "v1"): (7, 16, 39)}


def test_snapshots_change_nothing_and_replace_the_history(spark):
    draw = random.Random(4)
    often, never = (rollup.Rollup(spark, new_path(spark, "t"), buckets=4, compact_after=n) for n in (2, 10**6))
    live = {}
    for turn in range(5):
        rows = [(i, "v", draw.choice("ab"), "en", draw.choice(["insert", "revise", "delete"]), 0, draw.randrange(50), 1) for i in draw.sample(range(12), 6)]
        for state in (often, never):
            assert state.apply(f"b{turn}", changes(spark, rows))
        for i, _, source, _, op, _, n, _ in rows:
            live.pop(i, None)
            if op != "delete":
                live[i] = (source, n)
    want = {(s, "en", "v"): (sum(x == s for x, _ in live.values()), sum(n for x, n in live.values() if x == s), sum(x == s for x, _ in live.values())) for s in {x for x, _ in live.values()}}
    assert totals(often) == totals(never) == want
    assert often._snapshot()[0] == "00000001" and never._snapshot()[0] is None
    gone = often._read("ledger", rollup.LEDGER).inputFiles()
    assert not any("/ledger/b0/" in f or "/ledger/b3/" in f for f in gone)


def test_a_batch_reads_its_own_buckets(spark):
    state = rollup.Rollup(spark, new_path(spark, "t"), buckets=8)
    state.apply("x", changes(spark, [(i, "v", "a", "en", "insert", 0, 1, 1) for i in range(100)]))
    plan = state.live().filter(F.col("bucket").isin([3]))._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(bucket" in plan


def test_maintained_totals_equal_a_count_of_what_is_live(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "source", "lang", "text")
    rows = docs.collect()
    model = word_bpe(vocab_path("word_bpe_49k.json"))
    first = {}
    for r in sorted(rows):
        first.setdefault(r["text"], r["doc_id"])
    want = Counter()
    for r, ids in zip(rows, model.ids([r["text"] for r in rows]), strict=True):
        if first[r["text"]] == r["doc_id"]:
            want[r["source"], r["lang"]] += len(ids) // 4 + 1
    got = rollup.maintained(docs).filter("level = 0").collect()
    assert {(r["source"], r["lang"]): r["n_tokens"] for r in got if r["tokenizer"] == "word_bpe_49k"} == dict(want)
    pieces = sentencepiece.SentencePieceProcessor(model_file=vocab_path("piece_bpe_32k.model"))
    second = Counter()
    for r in rows:
        second[r["source"], r["lang"]] += sum(len(pieces.encode(w)) for w in r["text"].split())
    assert {(r["source"], r["lang"]): r["n_tokens"] for r in got if r["tokenizer"] == "piece_bpe_32k"} == dict(second)


def test_odd_texts(spark):
    rows = rollup.count(frame(spark, ODD).withColumn("copy", F.lit(1)))
    assert rows.count() == 2 * len(ODD)
    assert {r["n_tokens"] for r in rows.filter("doc_id IN (0, 1, 2)").collect()} == {0}
    assert rollup.maintained(frame(spark, ODD).limit(0)).count() == 0
