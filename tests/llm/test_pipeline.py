import corpus_pipeline
from corpuskit.llm import fertility, spaced_seeds
from corpuskit.session import staged
from tests.conftest import SMALL
from tests.llm.conftest import ODD, frame
from tests.llm.test_pack import check


def test_stages_on_the_small_tables(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    columns, tables = docs.columns, [docs]
    for name, stage in corpus_pipeline.STAGES:
        tables.append(staged(stage(spark, tables[-1], SMALL), name))
    assert all(t.columns == columns for t in tables[:-1])
    ids = [{r["doc_id"] for r in t.select("doc_id").collect()} for t in tables]
    assert all(b <= a for a, b in zip(ids, ids[1:], strict=False))
    assert ids[1] == {r["doc_id"] for r in fertility.quality(docs).filter("kept").collect()}
    assert ids[2] <= ids[1]
    before = {r["doc_id"]: r["text"] for r in tables[2].collect()}
    after = {r["doc_id"]: r["text"] for r in tables[3].collect()}
    assert all(len(after[i]) <= len(before[i]) for i in after) and set(after) == set(before) - (set(before) - set(after))
    leaks = {r["doc_id"] for r in spaced_seeds.overlaps(tables[3], spark.read.parquet(f"{SMALL}/benchmark.parquet")).collect()}
    assert ids[4] == ids[3] - leaks and ids[5] == ids[4]
    kept = sorted(tables[4].collect(), key=lambda r: r["doc_id"])
    number = {r["doc_id"]: i for i, r in enumerate(kept)}
    rows = [r.asDict() | {"doc_id": number[r["doc_id"]]} for r in tables[5].collect()]
    check(rows, [r["text"] for r in kept], 4096)
    assert corpus_pipeline.run(spark, SMALL).count() == len(rows)


def test_odd_rows_clashing_names_and_empty_tables(spark, prose):
    """Nulls in every column, empty and very long texts, repeated rows, names that operators use themselves."""
    texts = [*ODD, prose(400, 1), prose(400, 1), prose(6000, 2), prose(300, 3), *(prose(120, s) for s in range(4, 40))]
    docs = frame(spark, texts)
    docs = docs.unionByName(docs.filter("doc_id IN (10, 12)"))
    docs = docs.unionByName(docs.filter("doc_id = 13").selectExpr("CAST(NULL AS long) AS doc_id", "text", "CAST(NULL AS string) AS lang", "CAST(NULL AS string) AS source", "CAST(NULL AS int) AS n_chars"))
    names = ["node", "list", "slot", "seed", "words", "cuts", "cut_id", "kept", "entropy_low", "in_0", "item_id", "marks", "part", "place", "__id", "Band", "root", "component_id", "n"]
    docs = docs.selectExpr("*", *(f"{i} AS `{c}`" for i, c in enumerate(names)))
    for table in (docs, docs.limit(0)):
        now = table
        for name, stage in corpus_pipeline.STAGES[:-1]:
            now = staged(stage(spark, now, SMALL), name)
            assert now.columns == docs.columns
        rows = now.collect()
        packed = staged(corpus_pipeline.STAGES[-1][1](spark, now, SMALL), "packed").collect()
        assert {r["doc_id"] for r in rows} == {r["doc_id"] for r in packed}
        assert all(r[c] == i for r in rows for i, c in enumerate(names))
        if table is docs:
            ids = [r["doc_id"] for r in rows]
            assert 10 in ids and 11 not in ids and ids.count(12) == 2 and None in ids and set(range(14, 50)) <= set(ids)
