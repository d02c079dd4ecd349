"""Phase 3 and the language-identification benchmark."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.functions import metrics
from corpuskit.operators import exact, lid
from corpuskit.plans import corpus as C
from corpuskit.queries.corpus import BAG, IDENTIFIED, P1, P2, P3, P3_MODEL, RAW, SCORE, TRAIN, WS, run_of
from corpuskit.queries.registry import query, table, version
from corpuskit.session import staged
from corpuskit.sources import with_roles

LABELS = ["de", "en", "es", "fr"]
WORDS = 2
TEST = f"""test AS (SELECT doc_id, lang AS gold, text FROM p1 WHERE doc_id % 2 = 1 QUALIFY row_number() OVER (PARTITION BY lang ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id) <= 40),
snip AS (SELECT doc_id, gold, array_to_string(string_split(trim(regexp_replace(text, '{WS}', ' ', 'g')), ' ')[1:{WORDS}], ' ') AS text FROM test),
asked AS (SELECT doc_id, ' ' || trim(regexp_replace(lower(text), '{WS}', ' ', 'g')) || ' ' AS t FROM snip),
{BAG}"""
PRED = f"WITH {RAW}, {P1}, {TRAIN}, {TEST}, {SCORE}, res AS (SELECT p.doc_id, snip.gold, p.label AS predicted, p.prob FROM pred p JOIN snip USING (doc_id) WHERE place = 1)"
_made: dict[tuple, DataFrame] = {}


def _once(spark, d, name, make):
    key = (*version(spark, d), name)
    if key not in _made:
        _made[key] = staged(make(), name)
    return _made[key]


def _unique(spark, d) -> DataFrame:
    return _once(spark, d, "lid-unique", lambda: exact.drop_exact(with_roles(table(spark, d))))


def _profile(spark, d) -> DataFrame:
    return _once(spark, d, "lid-profile", lambda: lid.train_profile(_unique(spark, d).filter("doc_id % 2 = 0")))


def snippets(spark, d, words: int = WORDS, unique: DataFrame | None = None) -> DataFrame:
    rows = lid.test_set(unique or _unique(spark, d))
    return rows.select("doc_id", F.col("lang").alias("gold"), (lid.snippet(F.col("text"), words) if words else F.col("text")).alias("text"))


def _with_gold(test: DataFrame, predicted: DataFrame) -> DataFrame:
    return test.select("doc_id", "gold").join(predicted, "doc_id").withColumnRenamed("label", "predicted")


def benchmark_rows(spark, d, words: int = WORDS) -> DataFrame:
    """Answers of the profile model over test snippets, drawn from the documents anew for each query; only the model is kept."""
    test = snippets(spark, d, words, exact.drop_exact(with_roles(table(spark, d))))
    return _with_gold(test, lid.predict_profile(test, lid.Profile.of(_profile(spark, d))))


@query("lid_profile", f"WITH {RAW}, {P1}, {TRAIN} SELECT label, CAST(n AS INTEGER) AS n, gram, round(logp, 6) AS logp, round(unk, 6) AS unknown FROM prof")
def lid_profile(spark, d):
    return _profile(spark, d).withColumns({"logp": F.round("logp", 6), "unknown": F.round("unknown", 6)})


@query("lid_profile_pred", f"{PRED} SELECT doc_id, gold, predicted, round(prob, 4) AS prob FROM res")
def lid_profile_pred(spark, d):
    return benchmark_rows(spark, d).withColumn("prob", F.round("prob", 4))


@query("lid_profile_pred_joined", f"{PRED} SELECT doc_id, predicted AS label, round(prob, 4) AS prob FROM res")
def lid_profile_pred_joined(spark, d):
    return lid.predict_profile_joined(snippets(spark, d), _profile(spark, d)).withColumn("prob", F.round("prob", 4))


@query("lid_sampled")
def lid_sampled(spark, d):
    test = snippets(spark, d, 10)
    return _with_gold(test, lid.predict_profile(test, lid.Profile.of(_profile(spark, d)), draws=lid.Draws()))


@query("lid_tempered")
def lid_tempered(spark, d):
    test = snippets(spark, d, 10)
    return _with_gold(test, lid.predict_profile(test, lid.Profile.of(_profile(spark, d)), temper=10.0))


@query("p3_lid_filter", f"{PRED} SELECT doc_id FROM res WHERE predicted = 'en' AND prob >= 0.5")
def p3_lid_filter(spark, d):
    return lid.verify(lid.predict_profile(snippets(spark, d), lid.Profile.of(_profile(spark, d))), "en").select("doc_id")


#: The second pass: the target and the language most like it, told apart by a model trained on these two alone.
SISTER = "de"
_SECOND = f"""{TRAIN.replace("WHERE doc_id % 2 = 0", f"WHERE doc_id % 2 = 0 AND lang IN ('en', '{SISTER}')")}, asked AS (SELECT doc_id, ' ' || trim(regexp_replace(lower(clean), '{WS}', ' ', 'g')) || ' ' AS t FROM p3), {BAG}, {SCORE}"""
_TAGGED = f"WITH {RAW}, {P1}, {P2}, {P3}, {_SECOND}, t AS (SELECT doc_id, label AS variety FROM pred WHERE place = 1)"


def _second_pass(spark, d):
    """The variety model, trained on the target and its sister variety."""
    taught = _unique(spark, d).filter(F.col("lang").isin("en", SISTER) & (F.col("doc_id") % 2 == 0))
    return lid.identifier(_once(spark, d, "lid-second", lambda: lid.train_profile(taught)))


@query("p3_filter_model", f"WITH {RAW}, {P1}, {P2}, {P3_MODEL} SELECT doc_id, lang FROM p3")
def p3_filter_model(spark, d):
    """Phase 3 by the profile model over whole documents, with the label they came with."""
    return run_of(spark, d, None).p3.select("doc_id", "lang")


@query("p3_tag", f"{_TAGGED} SELECT doc_id, variety FROM t")
def p3_tag(spark, d):
    docs = run_of(spark, d).p3
    return lid.tag_variety(docs.select("doc_id"), _second_pass(spark, d)(docs))


@query("dialect_coverage", f"{_TAGGED} SELECT v AS variety, count(t.doc_id) AS n_docs FROM (VALUES ('en'), ('{SISTER}')) x(v) LEFT JOIN t ON t.variety = x.v GROUP BY 1")
def dialect_coverage(spark, d):
    return C.variety_counts(p3_tag(spark, d), ["en", SISTER])


@query("p3_leakage", f"WITH {RAW}, {P1}, {P2}, g AS (SELECT lang AS label FROM p2 WHERE lang <> 'en') SELECT label, count(*) AS n_docs, round(count(*) / (SELECT count(*) FROM g), 6) AS share FROM g GROUP BY 1")
def p3_leakage(spark, d):
    return C.leakage(run_of(spark, d))


@query("p3_leakage_profile", f"WITH {RAW}, {P1}, {P2}, {IDENTIFIED}, g AS (SELECT label FROM pred WHERE place = 1 AND NOT (label = 'en' AND prob >= 0.5)) SELECT label, count(*) AS n_docs, round(count(*) / (SELECT count(*) FROM g), 6) AS share FROM g GROUP BY 1")
def p3_leakage_profile(spark, d):
    return C.leakage(run_of(spark, d, None))


RANKS = """rk AS (SELECT label, gram, row_number() OVER (PARTITION BY label ORDER BY sum(c) DESC, gram) AS place FROM cnt GROUP BY label, gram QUALIFY place <= 300),
mine AS (SELECT doc_id, gram, row_number() OVER (PARTITION BY doc_id ORDER BY sum(m) DESC, gram) AS mine FROM bag GROUP BY doc_id, gram QUALIFY mine <= 300),
dist AS (SELECT mine.doc_id, l.label, sum(CASE WHEN rk.place IS NULL THEN 300 ELSE abs(mine.mine - rk.place) END) AS distance, count(rk.place) AS met FROM mine CROSS JOIN (SELECT DISTINCT label FROM rk) l LEFT JOIN rk ON rk.gram = mine.gram AND rk.label = l.label GROUP BY ALL)"""


@query("lid_rank_order", f"WITH {RAW}, {P1}, {TRAIN}, {TEST}, {RANKS} SELECT doc_id, label, CAST(distance AS BIGINT) AS distance FROM dist WHERE met > 0 QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY distance, label) = 1")
def lid_rank_order(spark, d):
    ranks = _once(spark, d, "lid-ranks", lambda: lid.train_ranks(_unique(spark, d).filter("doc_id % 2 = 0")))
    return lid.predict_rank_order(snippets(spark, d), ranks)


_LISTS = " UNION ALL ".join(f"SELECT '{k}' AS label, [{', '.join(repr(w) for w in v)}] AS ws" for k, v in sorted(lid.FUNCTION_WORDS.items()))


@query("lid_function_words", f"WITH lists AS ({_LISTS}), w AS (SELECT doc_id, string_split(trim(regexp_replace(lower(text), '{WS}', ' ', 'g')), ' ') AS x FROM documents), h AS (SELECT doc_id, label, CAST(len(list_filter(x, lambda t: list_contains(ws, t))) AS BIGINT) AS hits FROM w, lists) SELECT doc_id, CASE WHEN hits > 0 THEN label END AS label, hits FROM h QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY hits DESC, label) = 1")
def lid_function_words(spark, d):
    return lid.predict_function_words(table(spark, d))


@query("lid_cascade")
def lid_cascade(spark, d):
    test = snippets(spark, d, 1)
    first = lid.predict_profile(test, lid.Profile.of(_profile(spark, d)))
    second = lid.predict_function_words(test).select("doc_id", "label", F.lit(0.5).alias("prob"))
    return _with_gold(test, lid.cascade(first, second))


@query("lid_accuracy", f"{PRED} SELECT count(*) AS n, count(*) FILTER (gold = predicted) AS n_correct, round(count(*) FILTER (gold = predicted) / count(*), 6) AS accuracy FROM res")
def lid_accuracy(spark, d):
    return metrics.accuracy(benchmark_rows(spark, d))


_CELLS = "cells AS (SELECT l AS label, count(*) FILTER (gold = l AND predicted = l) AS tp, count(*) FILTER (gold <> l AND predicted = l) AS fp, count(*) FILTER (gold = l AND predicted <> l) AS fn FROM res, (VALUES ('de'), ('en'), ('es'), ('fr')) x(l) GROUP BY 1)"


@query("lid_prf", f"{PRED}, {_CELLS} SELECT label, tp, fp, fn, round(CASE WHEN tp + fp = 0 THEN 0 ELSE tp / (tp + fp) END, 6) AS precision, round(CASE WHEN tp + fn = 0 THEN 0 ELSE tp / (tp + fn) END, 6) AS recall, round(CASE WHEN 2 * tp + fp + fn = 0 THEN 0 ELSE 2 * tp / (2 * tp + fp + fn) END, 6) AS f1 FROM cells")
def lid_prf(spark, d):
    return metrics.prf(benchmark_rows(spark, d))


@query("lid_f1_summary", f"{PRED}, {_CELLS} SELECT round(avg(round(2 * tp / (2 * tp + fp + fn), 6)), 6) AS macro_f1, round(2 * sum(tp) / (2 * sum(tp) + sum(fp) + sum(fn)), 6) AS micro_f1 FROM cells")
def lid_f1_summary(spark, d):
    return metrics.f1_summary(benchmark_rows(spark, d))


@query("lid_confusion", f"{PRED} SELECT gold, " + ", ".join(f"count(*) FILTER (predicted = '{x}') AS {x}" for x in LABELS) + ", count(*) FILTER (predicted NOT IN ('de', 'en', 'es', 'fr')) AS other FROM res GROUP BY 1")
def lid_confusion(spark, d):
    return metrics.confusion(benchmark_rows(spark, d), LABELS)


@query("lid_misses", f"{PRED} SELECT predicted, count(*) AS n FROM res WHERE gold = 'en' AND predicted <> 'en' GROUP BY 1")
def lid_misses(spark, d):
    return metrics.misses(benchmark_rows(spark, d), "en")


def _boot(rows: str, name: str) -> str:
    """The interval of the target's F1 over resamples of `rows(gold, predicted)`: draws fall on the confusion cells in order."""
    hit, gold = "coalesce(predicted = 'en', false)", "gold = 'en'"
    return f"""{name}_n AS (SELECT count(*) FILTER ({gold} AND {hit}) AS a, count(*) FILTER (NOT {gold} AND {hit}) AS b, count(*) FILTER ({gold} AND NOT {hit}) AS c, count(*) AS n FROM {rows}),
{name}_d AS (SELECT r, a, b, c, CAST('0x' || substr(md5('0|' || r || '|' || i), 1, 8) AS BIGINT) % n AS place FROM {name}_n, range(500) x(r), range((SELECT n FROM {name}_n)) y(i)),
{name}_f AS (SELECT r, count(*) FILTER (place < a) AS tp, count(*) FILTER (place >= a AND place < a + b) AS fp, count(*) FILTER (place >= a + b AND place < a + b + c) AS fn FROM {name}_d GROUP BY 1),
{name}_ci AS (SELECT '{name}' AS model, round(quantile_cont(f, 0.025), 6) AS low, round(quantile_cont(f, 0.975), 6) AS high FROM (SELECT CASE WHEN 2 * tp + fp + fn = 0 THEN 0 ELSE 2 * tp / (2 * tp + fp + fn) END AS f FROM {name}_f))"""


@query("lid_bootstrap", f"{PRED}, {_boot('res', 'profile')} SELECT low, high FROM profile_ci")
def lid_bootstrap(spark, d):
    return metrics.bootstrap(benchmark_rows(spark, d), "en")


_RANKED = f"{RANKS}, ranked AS (SELECT doc_id, label FROM dist WHERE met > 0 QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY distance, label) = 1), rres AS (SELECT gold, label AS predicted FROM snip LEFT JOIN ranked USING (doc_id))"
_WORDED = f"wl AS ({_LISTS}), wh AS (SELECT doc_id, label, len(list_filter(string_split(trim(regexp_replace(lower(text), '{WS}', ' ', 'g')), ' '), lambda t: list_contains(ws, t))) AS hits FROM snip, wl), wres AS (SELECT gold, label AS predicted FROM snip LEFT JOIN (SELECT doc_id, CASE WHEN hits > 0 THEN label END AS label FROM wh QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY hits DESC, label) = 1) USING (doc_id))"
_THREE = f"{PRED}, {_RANKED}, {_WORDED}, every AS (SELECT 'profile' AS model, gold, predicted FROM res UNION ALL SELECT 'rank_order', gold, predicted FROM rres UNION ALL SELECT 'function_words', gold, predicted FROM wres)"


def _compared(spark, d) -> DataFrame:
    """(model, gold, predicted) of the three identifiers that SQL can follow, over the same snippets."""
    test = snippets(spark, d)
    ranks = _once(spark, d, "lid-ranks", lambda: lid.train_ranks(_unique(spark, d).filter("doc_id % 2 = 0")))
    answers = {"rank_order": lid.predict_rank_order(test, ranks), "function_words": lid.predict_function_words(test)}
    rows = [benchmark_rows(spark, d).select(F.lit("profile").alias("model"), "gold", "predicted")]
    for name, got in answers.items():
        rows.append(test.join(got.select("doc_id", F.col("label").alias("predicted")), "doc_id", "left").select(F.lit(name).alias("model"), "gold", "predicted"))
    return _once(spark, d, "lid-compared", lambda: reduce(DataFrame.union, rows))


@query("lid_ci_overlap", f"{_THREE}, {_boot('res', 'profile')}, {_boot('rres', 'rank_order')}, {_boot('wres', 'function_words')}, ci AS (SELECT * FROM profile_ci UNION ALL SELECT * FROM rank_order_ci UNION ALL SELECT * FROM function_words_ci) SELECT a.model AS model_a, b.model AS model_b, a.low <= b.high AND b.low <= a.high AS overlap FROM ci a, ci b WHERE a.model < b.model")
def lid_ci_overlap(spark, d):
    """Which of the measured intervals of the target's F1 overlap."""
    rows = _compared(spark, d)
    each = (metrics.bootstrap(rows.filter(F.col("model") == m), "en").withColumn("model", F.lit(m)) for m in ("profile", "rank_order", "function_words"))
    return metrics.ci_overlap(staged(reduce(DataFrame.union, each), "intervals"))


@query("lid_prf_models", f"{_THREE}, cells AS (SELECT model, l AS label, count(*) FILTER (gold = l AND predicted = l) AS tp, count(*) FILTER (gold <> l AND predicted = l) AS fp, count(*) FILTER (gold = l AND predicted IS DISTINCT FROM l) AS fn FROM every, (VALUES ('de'), ('en'), ('es'), ('fr')) x(l) GROUP BY 1, 2) SELECT model, label, tp, fp, fn, round(CASE WHEN tp + fp = 0 THEN 0 ELSE tp / (tp + fp) END, 6) AS precision, round(CASE WHEN tp + fn = 0 THEN 0 ELSE tp / (tp + fn) END, 6) AS recall, round(CASE WHEN 2 * tp + fp + fn = 0 THEN 0 ELSE 2 * tp / (2 * tp + fp + fn) END, 6) AS f1 FROM cells")
def lid_prf_models(spark, d):
    return metrics.prf(_compared(spark, d), "model")


@query("lid_misses_models", f"{_THREE} SELECT model, predicted, count(*) AS n FROM every WHERE gold = 'en' AND predicted IS DISTINCT FROM 'en' GROUP BY 1, 2")
def lid_misses_models(spark, d):
    """Where each model's missed rows of the target went (null: no answer)."""
    return metrics.misses(_compared(spark, d), "en", "model")


@query("lid_kappa", f"{PRED}, fw_l AS ({_LISTS}), fw AS (SELECT doc_id, label, len(list_filter(string_split(trim(regexp_replace(lower(text), '{WS}', ' ', 'g')), ' '), lambda t: list_contains(ws, t))) AS hits FROM test, fw_l), second AS (SELECT doc_id, CASE WHEN hits > 0 THEN label ELSE 'none' END AS second FROM fw QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY hits DESC, label) = 1), ab AS (SELECT predicted AS first, second FROM res JOIN second USING (doc_id)), t AS (SELECT count(*) AS n, count(*) FILTER (first = second) / count(*) AS po FROM ab), c AS (SELECT sum(x.n * y.n) / any_value(t.n * t.n) AS pe FROM (SELECT first AS l, count(*) AS n FROM ab GROUP BY 1) x JOIN (SELECT second AS l, count(*) AS n FROM ab GROUP BY 1) y USING (l), t) SELECT n, round(po, 6) AS agreement, round((po - pe) / (1 - pe), 6) AS kappa FROM t, c")
def lid_kappa(spark, d):
    first = benchmark_rows(spark, d).select("doc_id", F.col("predicted").alias("first"))
    second = lid.predict_function_words(snippets(spark, d, 0)).select("doc_id", F.coalesce("label", F.lit("none")).alias("second"))
    return metrics.kappa(first.join(second, "doc_id"))


def models(spark, d):
    """The benchmark's identifiers: each turns (doc_id, text) into (doc_id, label, prob)."""
    train = _unique(spark, d).filter("doc_id % 2 = 0")
    profile = lid.Profile.of(_profile(spark, d))
    return {
        "fast": lid.train_linear(train, features=1 << 12, grams=(2, 3), iterations=10),
        "dialect": lid.train_linear(train, features=1 << 14, grams=(2, 4), words=True, iterations=15),
        "profile": lambda df: lid.predict_profile(df, profile),
    }


def _benchmarked(spark, d) -> dict[str, tuple[DataFrame, float]]:
    """The answers of the three models on the same two-word snippets, and the seconds each took."""
    test, out = staged(snippets(spark, d), "snippets"), {}
    for name, predict in models(spark, d).items():
        began = time.time()
        out[name] = (staged(_with_gold(test, predict(test)), f"bench-{name}"), time.time() - began)
    return out


@query("lid_benchmark")
def lid_benchmark(spark, d):
    """Accuracy, target F1 with interval, and throughput of the three models; all learn from whole texts."""
    out = []
    for name, (rows, took) in _benchmarked(spark, d).items():
        acc, f1 = metrics.accuracy(rows).first(), metrics.prf(rows).filter("label = 'en'").first()
        ci = metrics.bootstrap(rows, "en").first()
        out.append((name, acc["n"], acc["accuracy"], f1["f1"] if f1 else 0.0, ci["low"], ci["high"], acc["n"] / took))
    return spark.createDataFrame(out, "model string, n long, accuracy double, f1 double, low double, high double, docs_per_s double")


@query("lid_confusion_models")
def lid_confusion_models(spark, d):
    """The confusion matrix of each of the three models, its rows of the target being the misses."""
    rows = ((name, rows) for name, (rows, _) in _benchmarked(spark, d).items())
    return reduce(DataFrame.union, (metrics.confusion(x, LABELS).select(F.lit(name).alias("model"), "gold", *LABELS, "other") for name, x in rows))


@query("lid_by_length")
def lid_by_length(spark, d):
    """Accuracy of the profile model on snippets of 1, 2, 3 and 10 words and on whole texts (0)."""
    rows = (metrics.accuracy(benchmark_rows(spark, d, n)).withColumn("words", F.lit(n)) for n in (1, 2, 3, 10, 0))
    return reduce(DataFrame.union, rows)
