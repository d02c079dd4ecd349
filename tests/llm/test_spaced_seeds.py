import pytest

from corpuskit.llm import spaced_seeds as S
from tests.conftest import MEDIUM
from tests.llm.conftest import ODD, frame


def bench(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")


def found(spark, texts, items):
    return {(r["doc_id"], r["item_id"]): r for r in S.overlaps(frame(spark, texts), bench(spark, items)).collect()}


def test_exact_cased_and_substituted_passages(spark, prose):
    item = prose(30, 1)
    words = item.split()
    swapped = " ".join("other" if i % 7 == 3 else w for i, w in enumerate(words))
    half = " ".join(words[10:25])
    few = " ".join(words[:10])
    texts = [f"{prose(40, 2)} {x} {prose(40, 3)}" for x in (item, item.upper().replace(" ", ", "), swapped, half, few)] + [prose(200, 9), *ODD]
    got = found(spark, texts, [item, prose(25, 50), None, "", " ,. "])
    assert set(got) == {(0, 0), (1, 0), (2, 0), (3, 0)}
    assert (got[0, 0]["doc_word"], got[0, 0]["item_word"], got[0, 0]["length"], got[0, 0]["matches"]) == (40, 0, 30, 30)
    assert got[2, 0]["matches"] == sum(i % 7 != 3 for i in range(30) if i < 30)
    assert got[3, 0]["length"] == 15


@pytest.mark.parametrize("n", [1, 4, 9, 11, 12])
def test_short_items_are_found_whole(spark, prose, n):
    item = prose(n, 70 + n)
    got = found(spark, [f"{prose(20, 1)} {item} {prose(20, 2)}", prose(60, 3)], [item])
    assert set(got) == {(0, 0)}


def test_equal_items_are_one_and_blocks_change_nothing(spark, prose, monkeypatch):
    items = [prose(20, i) for i in range(6)] + [prose(20, 0)]
    texts = [f"{prose(15, 99)} {x}" for x in items]
    want = {(i, i) for i in range(6)} | {(6, 0)}
    assert set(found(spark, texts, items)) == want
    monkeypatch.setattr(S, "BLOCK_BYTES", 200)
    assert {d for d, _ in found(spark, texts, items)} == set(range(7))
    kept = S.drop_contaminated(frame(spark, [*texts, "clean"]).selectExpr("*", "1 AS item_id"), bench(spark, items))
    assert [r["doc_id"] for r in kept.collect()] == [7]


def test_every_planted_passage_of_the_tables(spark):
    docs, items = (spark.read.parquet(f"{MEDIUM}/{t}.parquet") for t in ("documents", "benchmark"))
    listed = [r["text"] for r in items.collect()]
    holds = {r["doc_id"] for r in docs.collect() if any(x in r["text"] for x in listed)}
    assert holds and holds <= {r["doc_id"] for r in S.overlaps(docs, items).collect()}


def test_empty_tables(spark):
    assert S.overlaps(frame(spark, ["x"]).limit(0), bench(spark, ["a b"])).count() == 0
    assert S.overlaps(frame(spark, ["x"]), bench(spark, ["a b"]).limit(0)).count() == 0
