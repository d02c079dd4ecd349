import zlib

import numpy as np

from corpuskit.llm import string_kernel as K
from tests.conftest import MEDIUM, SMALL
from tests.llm.conftest import COLUMNS, frame


def plain_grams(text):
    letters = []
    for c in text:
        c = c if c.isalpha() else " "
        if c != " " or letters[-1:] != [" "]:
            letters.append(c)
    s = "".join(letters)
    return {s[i : i + n] for n in (1, 2, 3) for i in range(len(s) - n + 1)} - {" "}


def test_grams_and_kernel_equal_brute_force():
    texts = ["hello, world!", "", "12 34", "aaa", "überall  straße", "漢字 と", "x y"]
    codes, first, lettered = K.grams(texts)
    sets = [plain_grams(t) for t in texts]
    assert [first[i + 1] - first[i] for i in range(len(texts))] == [len(s) for s in sets]
    assert lettered.tolist() == [any(c.isalpha() for c in t) for t in texts]
    model = K.Model([t for t in texts if t], ["a", "b", "a", "b", "a", "b"], landmarks=8)
    kept = [t for t in texts if t]
    used = [t for lang in () for t in lang] or kept
    kernel = model._kernel(codes, first)
    marks = [s for s in (plain_grams(t) for t in used) if s]
    for i, s in enumerate(sets):
        want = [len(s & m) / max(1, (len(s) * len(m)) ** 0.5) for m in marks]
        assert np.allclose(kernel[i], want, atol=1e-6) or not s


def test_predictions_equal_a_plain_kernel_ridge_regression(spark):
    """The same landmarks, kernels from Python sets, the normal equations of the Nystroem features solved densely."""
    rows = spark.read.parquet(f"{SMALL}/documents.parquet").orderBy("doc_id").collect()
    texts, langs = [r["text"][:300].lower() for r in rows], [r["lang"] for r in rows]
    teach, ask = slice(0, 60), slice(60, 140)
    model = K.Model(texts[teach], langs[teach], landmarks=5, ridge=1e-3)
    names, seen, marks = sorted(set(langs[teach])), {}, []
    for t, lang in zip(texts[teach], langs[teach], strict=True):
        seen[lang] = seen.get(lang, 0) + 1
        if seen[lang] <= 5:
            marks.append(plain_grams(t))
    kernel = lambda ts: np.array([[len(g & m) / (len(g) * len(m)) ** 0.5 for m in marks] for g in map(plain_grams, ts)])
    k, among = kernel(texts[teach]), np.array([[len(a & b) / (len(a) * len(b)) ** 0.5 for b in marks] for a in marks])
    aims = np.array([[1.0 if x == n else -1.0 for n in names] for x in langs[teach]])
    weights = np.linalg.solve(k.T @ k / 60 + 1e-3 * among + 1e-9 * np.eye(len(marks)), k.T @ aims / 60)
    values = K.STEEP * kernel(texts[ask]) @ weights
    odds = np.exp(values - values.max(axis=1, keepdims=True))
    got, score = model.predict(texts[ask])
    assert got == [names[i] for i in values.argmax(axis=1)]
    assert np.allclose(score, 1 / odds.sum(axis=1), atol=1e-6)


def test_letters_beyond_the_basic_plane_and_letterless_teachers(spark):
    codes, first, lettered = K.grams(["\U00020000", "\U00020000 \U00020001", "\U0001f600", "a\ue000b"])
    assert lettered.tolist() == [True, True, False, True] and np.diff(first).tolist() == [1, 5, 0, 5]
    assert K.Model(["12", "!!"], ["a", "b"]).predict(["abc", "3"]) [0] == ["und", "und"]
    half = K.Model(["12", "le chat", "the cat"], ["zz", "fr", "en"])
    assert half.langs == ["en", "fr"] and half.predict(["le chat", "the cat", "1"])[0] == ["fr", "en", "und"]
    docs = spark.createDataFrame([(1, "abc", "en", "s", 3), (2, "123", "fr", "s", 3), (3, "\U00020000", None, None, None)], COLUMNS)
    assert {r["doc_id"]: r["lang_pred"] for r in K.identify(docs, K.Model(["abc"], ["en"])).collect()} == {1: "en", 2: "und", 3: "en"}
    assert {r["lang_pred"] for r in K.identify(docs.filter("doc_id = 2")).collect()} == {"und"}


def test_any_number_of_texts_at_once():
    texts = ["ab", "", "c d", "eé"] * 5
    whole = K.grams(texts, 1000)
    for at_once in (1, 3, 7):
        assert all(np.array_equal(a, b) for a, b in zip(whole, K.grams(texts, at_once), strict=True))
    assert K.grams([])[1].tolist() == [0]


def test_the_sample_is_bounded_and_the_least_hashes(spark, monkeypatch):
    docs = spark.range(4000).selectExpr("id AS doc_id", "concat('w', id) AS text", "concat('l', id % 4) AS lang")
    rows = K.sample(docs, per_language=20).collect()
    assert len(rows) == 80
    every = docs.filter(~K.held_out(docs["doc_id"])).selectExpr("lang", "xxhash64(doc_id) AS h").collect()
    for lang in {r["lang"] for r in rows}:
        assert sorted(r["turn"] for r in rows if r["lang"] == lang) == sorted(r["h"] for r in every if r["lang"] == lang)[:20]
    monkeypatch.setattr(K, "MOST_SAMPLE", 20)
    assert len(K.sample(docs, per_language=20).collect()) == 20


def test_held_out_accuracy_and_split(spark):
    docs = spark.read.parquet(f"{MEDIUM}/documents.parquet")
    gold = {r["doc_id"]: r["lang"] for r in docs.select("doc_id", "lang").collect()}
    rows = K.identify(docs).collect()
    assert len(rows) == len(gold)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in rows)
    assert all(0 <= r["score"] <= 1 for r in rows)
    held = [r for r in rows if r["held_out"]]
    assert sum(r["lang_pred"] == gold[r["doc_id"]] for r in held) / len(held) > 0.97


def test_und_nulls_and_nothing_to_learn(spark):
    docs = spark.read.parquet(f"{MEDIUM}/documents.parquet")
    model = K.fit(docs, 50, 8)
    odd = frame(spark, [None, "", "12 34 !!", "le chat et la souris dans la maison"]).selectExpr("*", "1 AS score", "2 AS held_out_x")
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in K.identify(odd, model).collect()}
    assert [got[i] for i in range(3)] == [("und", 0.0)] * 3 and got[3][0] in ("de", "en", "es", "fr")
    unlabelled = spark.createDataFrame([(1, "abc", None, None, None), (None, "abc", "en", None, None)], COLUMNS)
    assert {r["lang_pred"] for r in K.identify(unlabelled).collect()} == {"und"}
    assert K.identify(docs.limit(0), model).count() == 0
