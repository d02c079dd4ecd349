"""Plans that hold at scale."""

import pytest

from corpuskit import sqlfuncs
from corpuskit.operators import clean, exact, neardup, release, tokenizer
from corpuskit.queries import QUERIES
from corpuskit.sources import with_roles
from tests.conftest import SMALL


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_no_text_crosses_the_network_to_find_first_copies(spark):
    docs = with_roles(spark.read.parquet(f"{SMALL}/documents.parquet"))
    text = plan(exact.winners(docs))
    exchange = [x for x in text.splitlines() if "Exchange" in x]
    assert exchange and not any("text" in x for x in exchange)


def test_scans_read_only_what_is_asked(spark):
    text = plan(QUERIES["scan_parquet_pruned"](spark, SMALL))
    assert "PushedFilters: [IsNotNull(source), EqualTo(source,src3)]" in text and "text" not in text.split("ReadSchema")[1]


@pytest.mark.parametrize("name", ["p1_exact_dedup", "p4_candidates", "p4_verified", "p5_coverage", "join_asof", "join_interval", "join_range", "decontam"])
def test_no_cartesian_product(spark, name):
    text = plan(QUERIES[name](spark, SMALL))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_each_step_of_cleaning_is_evaluated_once(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    text = clean.min_words(clean.normalize(docs))._jdf.queryExecution().optimizedPlan().toString()
    # two passes of repair, a guard each; one guard for composition, one for suspicion in each pass
    assert text.count("RLIKE(") <= 6 and text.count("regexp_replace(") <= 5 and text.count("translate(") <= 2 and text.count("split(") == 1
    assert len(text) < 5000


def test_places_need_no_single_task(spark):
    text = plan(release.places(spark.read.parquet(f"{SMALL}/documents.parquet")))
    assert "hashpartitioning(p" in text


def test_hashes_are_made_once_for_all_minima(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").withColumnRenamed("text", "clean")
    sets = neardup.hashed(neardup.shingles(docs))
    text = neardup.signatures_native(sets)._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("md5(") <= 2


def test_sql_functions(spark):
    model = tokenizer.train_from_counts([("low", 5), ("lower", 2)], 300)
    sqlfuncs.register(spark, tokenizer=model)
    spark.read.parquet(f"{SMALL}/documents.parquet").createOrReplaceTempView("ck_docs")
    row = spark.sql("SELECT ck_content_key(' A  b') AS k, ck_clean('x  aaaaa') AS c, size(ck_shingles('a b c d')) AS s, ck_jaccard(array('a','b'), array('b','c')) AS j, size(ck_char_grams('abcdef')) AS g, ck_token_count('low lower') AS t").first()
    assert (row["c"], row["s"], round(row["j"], 4), row["g"]) == ("x aaa", 2, 0.3333, 2) and row["t"] == len(model.encode("low lower"))
    assert spark.sql("SELECT * FROM ck_shingle_rows('a b c d', 3)").count() == 2
    assert spark.sql("SELECT * FROM ck_tokens('low')").count() == len(model.encode("low"))
    minima = spark.sql("SELECT ck_signature(array(5L, 7L, 5L)) AS s").first()["s"]
    assert minima == [min((x * a + c) % neardup.PRIME for x in (5, 7)) for a, c in neardup.hash_family()]
    assert spark.sql("SELECT count(DISTINCT ck_content_key(text)) FROM ck_docs").first()[0] == exact.winners(with_roles(spark.table("ck_docs"))).count()
