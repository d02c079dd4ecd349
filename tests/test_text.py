import unicodedata

import pytest
from pyspark.sql import functions as F

from corpuskit.functions import text as T


def apply(spark, f, values):
    df = spark.createDataFrame(list(enumerate(values)), "i int, t string")
    return [r[0] for r in df.orderBy("i").select(f(F.col("t"))).collect()]


@pytest.mark.parametrize("sign", ["a", "7", "!", "é", "\U0001f600"])
def test_runs_shrink_to_three(spark, sign):
    assert apply(spark, T.collapse_runs, [sign * n for n in range(1, 9)]) == [sign * min(n, 3) for n in range(1, 9)]


def test_white_space_is_the_ascii_class(spark):
    got = apply(spark, T.collapse_ws, ["  a\t\n\x0b b\r\n", "a b​c", "", None])
    assert got == ["a b", "a b​c", "", None]


def test_mojibake_of_either_charset_once_and_twice(spark):
    texts = ["café “naïve” – déjà", "Übergrößenträger", "plain", "€ 5 – ‘ok’"]
    latin = [t.encode().decode("latin-1") for t in texts]
    twice = [t.encode().decode("latin-1") for t in latin]
    wide = ["".join(bytes([b]).decode("cp1252", "ignore") or chr(b) for b in t.encode()) for t in texts]
    for damaged in (texts, latin, twice, wide):
        assert apply(spark, T.repair_mojibake, damaged) == texts


def test_sound_text_is_left_alone_and_mixed_damage_mended(spark):
    sound = ["Ãltere Â§ 5", "naïve Ã", "日本語 café", "\U0001f600 é", "", None]
    assert apply(spark, T.repair_mojibake, sound) == sound
    half = "ünverletzt – " + "café “x”".encode().decode("latin-1")
    docs = spark.createDataFrame([(0, half), (1, "日 " + "é".encode().decode("latin-1")), (2, None)], "i int, t string")
    assert [r["u"] for r in T.repair_mixed(docs, "t", "u").orderBy("i").collect()] == ["ünverletzt – café “x”", "日 é", None]


def test_nfc_equals_the_standard(spark):
    texts = ["é", "é", "a" * 20, "각", "ñ\U0001f600", None, ""]
    assert apply(spark, T.nfc, texts) == [t and unicodedata.normalize("NFC", t) for t in texts]


def test_other_fixes(spark):
    assert apply(spark, T.decode_entities, ["a &amp;lt; &lt;b&gt; &copy;&nbsp;&#39;"]) == ["a &lt; <b> ©\xa0'"]
    assert apply(spark, T.drop_controls, ["a\x00b\x1b[31mc\x1b[0m﻿\td"]) == ["abc\td"]
    assert apply(spark, T.unify_lines, ["a\r\nb\rc d\x85e"]) == ["a\nb\nc\nd\ne"]
    assert apply(spark, T.straighten_quotes, ["‘a’ “b”"]) == ["'a' \"b\""]
    assert apply(spark, T.split_ligatures, ["ﬁt oﬃce"]) == ["fit office"]
    assert apply(spark, T.narrow_width, ["ＡＢ！　ｚ"]) == ["AB! z"]


def test_pages_lose_markup(spark):
    html = "<html><style>x{}</style><script type='a'>if(a<b){}</script><p>Tom &amp; <b>Ann</b></p><!-- no --></html>"
    assert apply(spark, T.page_text, [html, "plain", ""]) == ["Tom & Ann", "plain", ""]


def test_keys_fold_case_and_space_only_when_asked(spark):
    a, b = "A  b\n", "a b"
    assert len(set(apply(spark, T.content_key, [a, b]))) == 1
    assert len(set(apply(spark, lambda c: T.content_key(c, "raw"), [a, b]))) == 2
    with pytest.raises(ValueError):
        T.content_key(F.col("t"), "other")


def test_grams(spark):
    assert apply(spark, lambda c: T.char_grams(c, 5), ["abcd", "abcde", "aaaaaaa", "ab cd\U0001f600"]) == [[], ["abcde"], ["aaaaa"], ["ab cd", "b cd\U0001f600"]]
    assert apply(spark, lambda c: T.word_grams(c, 3), ["", "a b", "a b c", "a b c a b c"]) == [[], [], ["a b c"], ["a b c", "b c a", "c a b"]]
    assert apply(spark, T.word_count, ["", "a", "a b"]) == [0, 1, 2]
