import math
import re
from collections import Counter

from pyspark.sql import functions as F

from corpuskit.llm import fertility
from tests.conftest import SMALL
from tests.llm.conftest import ODD, frame


def brute(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    seen, cover = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7)), set()
    for i in range(len(words) - 7):
        if seen[tuple(words[i : i + 8])] > 1:
            cover.update(range(i, i + 8))
    lines, dup, before = text.split("\n"), 0, set()
    for x in lines:
        if re.search(r"[^\x20\x09-\x0D]", x):
            dup += x in before
            before.add(x)
    return [len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(cover)]


def texts_of(spark):
    given = [r["text"] for r in spark.read.parquet(f"{SMALL}/documents.parquet").select("text").collect()]
    return [*ODD, "a b c d e f g h a b c d e f g h", "x\nx\n \nx\r\ny", "one two three four five six seven eight nine " * 5, "#*$%&|<>", *given]


def test_counts_and_entropy_equal_brute_force(spark):
    texts = texts_of(spark)
    tokens = fertility.token_lists(texts)
    got = {r["doc_id"]: r for r in fertility.quality(frame(spark, texts)).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        r, want = got[i], brute(t)
        assert [r[c] for c in fertility.COUNTS[:5]] == want, t
        assert r["base_failed"] == (want[0] < 20 or 100 * want[4] > 30 * want[0])
        assert not (r["kept"] and r["base_failed"])
        n, c = len(tokens[i]), Counter(tokens[i])
        assert r["n_tokens"] == n
        h = -sum(v / n * math.log2(v / n) for v in c.values()) if n else 0
        assert abs(r["entropy"] - h) < 1e-5


def test_bands_reject_outliers_of_their_language(spark, prose):
    clean = [prose(80 + i, i) for i in range(80)]
    odd = " ".join("漢字仮名\U0001f600" + chr(0x4E00 + i) for i in range(80))
    docs = frame(spark, [*clean, odd])
    kept = {r["doc_id"]: r["kept"] for r in fertility.quality(docs).collect()}
    assert kept[80] is False and all(kept[i] for i in range(80))
    mixed = docs.withColumn("lang", F.when(F.col("doc_id") == 80, "zz").otherwise(F.col("lang")))
    assert {r["doc_id"]: r["kept"] for r in fertility.quality(mixed).collect()}[80] is False  # the bands of all documents
    few = {r["doc_id"]: r["kept"] for r in fertility.quality(docs.filter("doc_id >= 70")).collect()}
    assert few[80] is True  # too few documents for a band


def test_filter_keeps_columns_with_clashing_names_and_nulls(spark, prose):
    docs = frame(spark, [prose(60, 1), "short", None]).selectExpr("*", "5 AS n_words", "true AS kept", "false AS in_kept", "'x' AS band", "1 AS entropy_low", "2 AS in_0", "named_struct('a b', 3) AS `odd name`", "4 AS every")
    out = fertility.keep_good(docs)
    assert out.columns == docs.columns and out.schema.simpleString() == docs.schema.simpleString()
    assert [(r["doc_id"], r["n_words"], r["band"]) for r in out.collect()] == [(0, 5, "x")]
    assert fertility.quality(docs.limit(0)).count() == 0
