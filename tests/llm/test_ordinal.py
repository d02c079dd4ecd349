import math
import re

import numpy as np
import pyarrow as pa

from corpuskit.llm import ordinal
from tests.conftest import MEDIUM, SMALL
from tests.llm.conftest import ODD, frame


def test_slope_equals_numeric_differences():
    draw = np.random.default_rng(0)
    inverse, doc = draw.integers(0, 5, 40), np.sort(draw.integers(0, 12, 40))
    own, grades, level = np.arange(5), draw.integers(0, 3, 12), draw.uniform(0.5, 2, 12)
    pars = draw.normal(size=7)

    def loss(p):
        cuts = np.r_[-np.inf, np.cumsum(np.r_[p[5], np.exp(p[6:])]), np.inf]
        s = np.bincount(doc, p[:5][inverse], 12)
        inner = ordinal._logistic(cuts[grades + 1] - s) - ordinal._logistic(cuts[grades] - s)
        return -(level * np.log(inner)).sum() / 12 + ordinal.PENALTY * (p[:5] ** 2).sum() / 2

    slope = ordinal.Ordinal._slope(pars, own, inverse, doc, grades, level, 12)
    for i in range(7):
        e = np.eye(7)[i] * 1e-6
        assert abs(slope[i] - (loss(pars + e) - loss(pars - e)) / 2e-6) < 1e-5


def test_grades_equal_a_plain_count(spark):
    """Word features from Python strings: those of the shape come from features() of a text without words."""
    docs, labels = (spark.read.parquet(f"{SMALL}/{t}.parquet") for t in ("documents", "labels"))
    model = ordinal.fit(docs, labels)
    got = {r["doc_id"]: r for r in ordinal.grade(docs, labels, model).collect()}
    for r in docs.collect():
        numbers, _ = ordinal.features(pa.array([r["text"]]))
        words = {w: ordinal.features(pa.array([w]))[0] for w in set(re.findall(r"[a-z0-9\x80-\U0010ffff]+", r["text"].lower()))}
        alone = [set(x.tolist()) for x in words.values()]
        assert all(a & set(numbers.tolist()) for a in alone)  # each word's feature is there
        score = sum(model.weights[i] for i in numbers.tolist())
        above = [1 / (1 + math.exp(t - score)) for t in model.thresholds]
        assert abs(got[r["doc_id"]]["expected_grade"] - sum(above)) < 1e-5
        assert abs(got[r["doc_id"]]["tail_probability"] - above[-1]) < 1e-5
        assert got[r["doc_id"]]["kept"] == (round(above[-1], 6) >= 0.5)


def test_thresholds_are_ordered_and_toxic_and_poor_texts_go(spark):
    docs, labels = (spark.read.parquet(f"{MEDIUM}/{t}.parquet") for t in ("documents", "labels"))
    model = ordinal.fit(docs, labels)
    assert model.thresholds[0] < model.thresholds[1]
    rows = ordinal.grade(docs, labels, model).join(labels, "doc_id").collect()
    assert docs.count() == ordinal.grade(docs, labels, model).count()
    clean = [r["kept"] for r in rows if r["quality"] == 1 and r["toxic"] == 0]
    toxic = [r["kept"] for r in rows if r["toxic"] == 1]
    assert sum(clean) / len(clean) > 0.97 and sum(toxic) / len(toxic) < 0.05
    assert all(0 <= r["expected_grade"] <= 2 and 0 <= r["tail_probability"] <= 1 for r in rows)


def test_features_are_those_of_each_text_alone():
    texts = ["the cat sat", "", "A B a !!! ###", "é ü", "the cat sat"]
    numbers, first = ordinal.features(pa.array([*texts, None]))
    for i, t in enumerate([*texts, ""]):
        alone, _ = ordinal.features(pa.array([t]))
        assert numbers[first[i] : first[i + 1]].tolist() == alone.tolist()


def test_odd_texts_and_no_ratings(spark):
    docs = frame(spark, ODD).selectExpr("*", "1 AS grade", "2 AS kept")
    none = spark.createDataFrame([(1, None, 0), (None, 1, 1)], "doc_id long, quality int, toxic int")
    rows = ordinal.grade(docs, none).collect()
    assert len(rows) == len(ODD) and all(r["kept"] and r["expected_grade"] is None for r in rows)
    some = spark.createDataFrame([(3, 1, 0), (4, 0, 0), (5, 1, 1)], "doc_id long, quality int, toxic int")
    assert ordinal.grade(docs, some).count() == len(ODD)
    assert ordinal.grade(docs.limit(0), some).count() == 0
