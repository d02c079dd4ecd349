import itertools
import json
import os
import random
import time
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from corpuskit import session
from corpuskit.config import Config
from corpuskit.functions import grams, metrics
from corpuskit.operators import charlm, clean, exact, lid, neardup, order_stats, quality, release, tokenizer
from corpuskit.operators.components import connected
from corpuskit.operators.relational import sized_join
from corpuskit.plans import corpus, objective
from corpuskit.session import new_path, scratch, staged
from tests.conftest import SMALL


@pytest.fixture(scope="module")
def run(spark):
    return corpus.CorpusRun(spark.read.parquet(f"{SMALL}/documents.parquet"))


# clean and exact


def test_word_limit_is_at_fifty(spark):
    docs = spark.createDataFrame([(n, "\t".join(["w%d" % i for i in range(n)])) for n in (48, 49, 50, 51)], "doc_id long, text string")
    assert sorted(r["doc_id"] for r in clean.min_words(clean.normalize(docs)).collect()) == [50, 51]


def test_cleaning_is_idempotent_and_dedup_modes_differ(spark, run):
    once = run.cleaned.select("doc_id", F.col("clean").alias("text"))
    assert clean.normalize(once).filter("text != clean").count() == 0
    docs = spark.createDataFrame([(1, "A b", 0), (2, "a  b", 0), (3, "A b", 0)], "doc_id long, text string, source_rank int")
    assert [r["doc_id"] for r in exact.drop_exact(docs).collect()] == [1]
    assert sorted(r["doc_id"] for r in exact.drop_exact(docs, "raw").collect()) == [1, 2]


def test_repeated_and_null_ids_lose_no_row_and_keep_no_copy(spark):
    rows = [(1, "a", 0), (1, "a", 0), (2, "a", 0), (2, "b", 0), (2, "b", 1), (None, "c", 0), (None, "a", 0), (None, None, 3), (7, None, 3), (8, "B", 0), (9, "d", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source_rank int")
    for mode in ("normalized", "raw"):
        form = lambda df: sorted(map(str, df.select("doc_id", F.lower("text"), "source_rank").collect()))
        fast, window = form(exact.drop_exact(docs, mode)), form(exact.drop_exact_window(docs, mode))
        assert fast == window and len(fast) == len({None if t is None else t.lower() if mode == "normalized" else t for _, t, _ in rows})
    assert exact.drop_exact(docs.limit(0)).count() == 0
    seen = exact.keyed(docs.filter("doc_id = 7 OR text = 'c'")).select("content_key")
    assert sorted(r["text"].lower() for r in exact.drop_exact_incremental(docs, seen).collect()) == ["a", "b", "d"]
    unique = spark.createDataFrame([(i, f"t{i % 3}", 0) for i in range(9)], "doc_id long, text string, source_rank int")
    assert sorted(r["doc_id"] for r in exact.drop_exact(unique).collect()) == [0, 1, 2]


def test_config_file(spark):
    path = new_path(spark, "config")
    spark.createDataFrame([(json.dumps({"target": "de", "bands": 8, "roles": [["src1", "A"]]}, indent=1),)], "value string").coalesce(1).write.text(path)
    config = Config.load(spark, path)
    assert (config.target, config.bands, config.roles, config.rows) == ("de", 8, (("src1", "A"),), Config().rows)
    assert config.digest() != Config().digest()
    spark.createDataFrame([('{"colour": 1}',)], "value string").coalesce(1).write.mode("overwrite").text(path)
    with pytest.raises(ValueError, match="colour"):
        Config.load(spark, path)


def test_config_is_checked_and_hashed():
    assert Config().digest() == Config().digest() != Config(seed=1).digest()
    for bad in ({"bands": 32}, {"tau": 0.0}, {"drop_percent": 100}, {"key_mode": "x"}):
        with pytest.raises(ValueError):
            Config(**bad)


# components


def components(spark, edges):
    return {r["node"]: r["root"] for r in connected(spark.createDataFrame(edges, "a long, b long")).collect()}


def test_paths_stars_cliques_and_messy_edges(spark):
    path = [(i, i + 1) for i in range(100, 132)]
    star = [(500, 500 + i) for i in range(1, 9)]
    cliques = [*itertools.combinations(range(200, 205), 2), *itertools.combinations(range(205, 210), 2), (204, 209)]
    messy = [(7, 7), (8, 9), (9, 8), (8, 9), (None, 3)]
    got = components(spark, path + star + cliques + messy)
    want = {i: 100 for i in range(100, 133)} | {i: 500 for i in range(500, 509)} | {i: 200 for i in range(200, 210)} | {8: 8, 9: 8}
    assert got == want
    assert components(spark, [(1, 1)]) == {}


def test_random_graphs_equal_union_find(spark):
    draw = random.Random(1)
    edges = [(draw.randrange(80), draw.randrange(80)) for _ in range(60)]
    root = list(range(80))

    def find(x):
        return x if root[x] == x else find(root[x])

    for a, b in edges:
        root[max(find(a), find(b))] = min(find(a), find(b))
    touched = {x for a, b in edges if a != b for x in (a, b)}
    assert components(spark, edges) == {x: find(x) for x in touched}


# near duplicates


def sets_of(spark, lists):
    return spark.createDataFrame([(i, sorted(set(x))) for i, x in enumerate(lists)], "doc_id long, hashes array<long>")


def test_jaccard_boundary_is_kept(spark):
    base = list(range(1000, 1009))
    sets = sets_of(spark, [base, base[:8] + [1], list(range(1000, 1004)), base[:8], [], base])
    pairs = spark.createDataFrame([(0, 1), (0, 2), (0, 3), (0, 5)], "a long, b long")
    got = {(r["a"], r["b"]): r["jaccard"] for r in neardup.verify(pairs, sets, 0.8).collect()}
    assert got == {(0, 1): pytest.approx(0.8), (0, 3): pytest.approx(8 / 9), (0, 5): 1.0}


def test_prefix_join_equals_brute_force(spark):
    draw = random.Random(2)
    lists = []
    for _ in range(25):
        base = draw.sample(range(3000), draw.randrange(3, 40))
        lists += [base, [x if draw.random() > 0.06 else draw.randrange(3000) for x in base]]
    sets = sets_of(spark, lists)
    for tau in (0.5, 0.8, 1.0):
        key = lambda df: sorted((r["a"], r["b"], round(r["jaccard"], 9)) for r in df.collect())
        assert key(neardup.prefix_join(sets, tau)) == key(neardup.brute_force(sets, tau))


def test_blocks_of_any_size_count_every_pair_without_shuffling_pairs(spark):
    """Equal, nested and disjoint sets, negative ids, an element that all have: pairs are counted inside tasks."""
    draw = random.Random(11)
    lists = [sorted(draw.sample(range(60), draw.randrange(1, 12))) for _ in range(120)] + [[900 + i] for i in range(5)] + [[1], [1], []]
    lists = [x + [500] if i % 2 else x for i, x in enumerate(lists)]
    sets = spark.createDataFrame([(i - 40, x) for i, x in enumerate(lists)], "doc_id long, hashes array<long>")
    want, bins = {}, {}
    for (i, x), (j, y) in itertools.combinations(enumerate(map(set, lists)), 2):
        if x & y:
            want[i - 40, j - 40] = len(x & y) / len(x | y)
            place = min(int(want[i - 40, j - 40] * 10), 9)
            bins[place] = bins.get(place, 0) + 1
    for docs in (7, 32_768):
        for tau in (0.0, 0.5):
            found = neardup.brute_force(sets, tau, docs=docs)
            assert {(r["a"], r["b"]): r["jaccard"] for r in found.collect()} == {k: v for k, v in want.items() if v >= tau}
        assert dict(neardup.similarity_histogram(sets, docs=docs).collect()) == bins
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan  # before, a join of all pairs by their shared elements


def test_signatures_agree_and_estimate_within_error(spark):
    draw = random.Random(3)
    a = draw.sample(range(10**6), 400)
    lists = [a] + [a[: 400 - k * 40] + draw.sample(range(10**6), k * 40) for k in range(1, 10)]
    sets = sets_of(spark, lists)
    fast = {r["doc_id"]: r["signature"] for r in neardup.signatures(sets).collect()}
    slow = {r["doc_id"]: r["signature"] for r in neardup.signatures_native(sets).collect()}
    assert fast == slow
    errors = []
    for i, j in itertools.combinations(range(10), 2):
        true = len(set(lists[i]) & set(lists[j])) / len(set(lists[i]) | set(lists[j]))
        errors.append(sum(x == y for x, y in zip(fast[i], fast[j], strict=True)) / 64 - true)
    assert np.sqrt(np.mean(np.square(errors))) <= 0.0625 * 1.3


def test_tables_follow_threshold_and_recall():
    assert neardup.tables_for(0.95, 12, 0.999) < neardup.tables_for(0.9, 12, 0.999) < neardup.tables_for(0.9, 12, 0.9999)


def test_s_curve_values():
    assert neardup.s_curve_value(0.8, 16, 4) == pytest.approx(0.99978, abs=1e-5)
    assert neardup.s_curve_value(0.5, 16, 4) == pytest.approx(0.64393, abs=1e-5)
    assert neardup.midpoint(16, 4) == 0.5 and neardup.std_error(0.5) == 0.0625


def test_copies_make_no_pairs_and_longest_stays(spark):
    texts = {9: "a b c d e", 10: "a b c d e", 100: "a b c d e", 11: "x y z", 12: "q"}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, clean string")
    near = neardup.NearDuplicates(docs)
    assert near.pairs.count() == 0
    clusters = near.clusters()
    assert {r["doc_id"]: r["component"] for r in clusters.collect()} == {9: 9, 10: 9, 100: 9}
    assert sorted(r["doc_id"] for r in neardup.survivors(docs, clusters).collect()) == [10, 11, 12]  # '10' comes before '9'
    stats = neardup.cluster_stats(clusters).first()
    assert stats["n_covered"] - stats["n_clusters"] == stats["n_removed"] == 2


def test_a_bucket_of_fifty_thousand_near_copies_costs_its_length(spark):
    ids = spark.range(50_000)
    common = F.sequence(F.lit(1), F.lit(40)).cast("array<long>")
    sets = staged(ids.select(F.col("id").alias("doc_id"), F.array_append(common, F.col("id") + 1000).alias("hashes")), "sets")
    buckets = staged(ids.select(F.lit(7).cast("long").alias("bucket"), F.col("id").alias("doc_id")), "buckets")
    found = neardup.bucket_links(buckets, sets)
    assert found.count() == 49_999 and found.filter("a != 0").isEmpty()


def test_links_of_a_bucket_connect_all_its_pairs(spark):
    draw = random.Random(9)
    base = list(range(30))
    lists = [sorted(set(base) - set(draw.sample(base, draw.randrange(8))) | {100 * i + k for k in range(draw.randrange(4))}) for i in range(60)]
    sets = staged(sets_of(spark, lists), "sets")
    buckets = staged(sets.select(F.lit(1).cast("long").alias("bucket"), "doc_id"), "buckets")
    true = neardup.brute_force(sets, 0.8)
    roots = lambda links: {r["node"]: r["root"] for r in connected(links).collect()}
    assert roots(neardup.bucket_links(buckets, sets)) == roots(true) and not true.isEmpty()


def test_near_vectors_are_met(spark):
    draw = np.random.default_rng(4)
    m = draw.normal(size=(300, 48))
    other = m + draw.normal(size=m.shape) * 0.45  # cosine about 0.91
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(np.r_[m, other])] + [(1000, [0.0] * 48), (1001, None)]
    cosine = lambda x, y: float(x @ y / np.linalg.norm(x) / np.linalg.norm(y))
    want = {(i, 300 + i) for i in range(300) if cosine(m[i], other[i]) >= 0.9}
    got = {(r["a"], r["b"]) for r in neardup.vector_pairs(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), 0.9).collect()}
    assert got <= want and len(got) >= 0.99 * len(want) and len(want) > 100


def test_every_near_vector_is_met(spark):
    """Of 4,000 pairs at the threshold random planes with a recall of 0.999 miss some."""
    draw = np.random.default_rng(5)
    m = draw.normal(size=(4000, 16))
    other = m + draw.normal(size=m.shape) * 0.45
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(np.r_[m, other])]
    u = np.r_[m, other] / np.linalg.norm(np.r_[m, other], axis=1)[:, None]
    x, y = np.nonzero(np.triu(u @ u.T >= 0.9, 1))
    docs = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    for block in (700, 32_768):
        got = [(r["a"], r["b"]) for r in neardup.vector_pairs(docs, 0.9, block).collect()]
        assert sorted(got) == sorted(zip(x.tolist(), y.tolist(), strict=True))


def test_joins_of_hot_keys_equal_plain_ones(spark):
    big = spark.createDataFrame([(k, i) for i, k in enumerate([1] * 500 + [None] * 100 + list(range(2, 60)))], "k long, v long")
    small = big.groupBy("k").agg(F.count("*").alias("n"), F.max("v").alias("most"))
    got = sized_join(big, small, "k", parts=10)
    assert "BroadcastExchange" in got._jdf.queryExecution().executedPlan().toString()
    key = lambda df: sorted(map(str, df.select("k", "v", "most").collect()))
    want = big.join(small.withColumnRenamed("k", "j"), F.col("k").eqNullSafe(F.col("j")))
    assert key(got) == key(sized_join(big, small, "k", parts=10**6)) == key(want) and got.count() == 658
    assert sized_join(big, small.drop("n"), "k", parts=10, sizes=small.select("k", "n")).count() == 658


def test_star_links_are_a_subset(run):
    banded = neardup.bands(neardup.signatures(run.near.sets))
    every = {tuple(r) for r in neardup.candidates(banded).collect()}
    assert {tuple(r) for r in neardup.star_candidates(banded).collect()} <= every


# quality and order statistics


@pytest.mark.parametrize("n", [1, 20, 100, 1000])
def test_value_at_every_kind_of_place(spark, n):
    draw = random.Random(n)
    values = [round(draw.random() ** 3, 3) for _ in range(n)]
    df = spark.createDataFrame([(v,) for v in values], "v double")
    for k in {0, n * 15 // 100, n - 1}:
        assert order_stats.value_at(df, "v", k) == sorted(values)[k]
        assert order_stats.value_at(df, "v", k, most=1) == sorted(values)[k]
    assert order_stats.value_at(df, "v", n) is None


def test_floor_rule_drops_exactly_and_keeps_ties(spark):
    df = spark.createDataFrame([(i, i / 1000) for i in range(1000)], "doc_id long, coverage double")
    assert quality.drop_bottom(df).count() == 850
    assert quality.drop_bottom(df, 15, "interpolated").count() == 850
    ties = spark.createDataFrame([(i, 0.5) for i in range(20)], "doc_id long, coverage double")
    assert quality.drop_bottom(ties).count() == 20 and quality.drop_bottom(ties.limit(0)).count() == 0


def test_seed_documents_cover_themselves(run):
    own = run.seed.select("doc_id").join(run.scored, "doc_id")
    assert own.filter("coverage != 1.0").count() == 0


def test_short_texts_have_coverage_zero(spark):
    docs = spark.createDataFrame([(1, "abcd"), (2, ""), (3, "abcdef"), (4, None)], "doc_id long, clean string")
    got = {r["doc_id"]: (r["hits"], r["total"], r["coverage"]) for r in quality.coverage(docs, docs.filter("doc_id = 3")).collect()}
    assert got == {1: (0, 0, 0.0), 2: (0, 0, 0.0), 3: (2, 2, 1.0), 4: (0, 0, 0.0)}


def test_gram_hashes_are_those_of_each_text():
    doc, h = grams.gram_hashes(["abc", "", "a", "bcd\U0001f600"], 2)
    assert doc.tolist() == [0, 0, 3, 3, 3] and h[1] == h[2] and len(set(h.tolist())) == 4


# the pipeline


def test_phases_are_subsets_and_partitioning_changes_nothing(spark, run):
    ids = [{r["doc_id"] for r in df.select("doc_id").collect()} for df in (run.raw, run.unique, run.cleaned, run.p3, run.p4, run.corpus)]
    assert all(b <= a for a, b in zip(ids, ids[1:], strict=False)) and ids[-1]
    again = corpus.CorpusRun(spark.read.parquet(f"{SMALL}/documents.parquet").repartition(7))
    assert {r["doc_id"] for r in again.corpus.select("doc_id").collect()} == ids[-1]
    assert len(ids[4]) - len(ids[5]) == len(ids[4]) * 15 // 100
    split = {r["doc_id"]: r["split"] for r in run.released.select("doc_id", "split").collect()}
    assert set(split) == ids[-1] and Counter(split.values())["train"] == len(ids[-1]) * 95 // 100


def test_printed_retention_recomputes(spark):
    n = [1372052, 1182360, 1080040, 1077804, 963908, 819322]
    stages = spark.createDataFrame([(x, 1) for x, k in zip(corpus.STAGES, n, strict=True) for _ in range(k // 10_000)], "stage string, n_words long")
    table = {r["stage"]: r for r in corpus.retention(stages).collect()}
    assert round(table["p5"]["cumulative_pct"], 1) == round(100 * (n[-1] // 10_000) / (n[0] // 10_000), 1)
    assert table["raw"]["step_drop_pct"] is None and table["p1"]["n_docs"] == n[1] // 10_000
    drops = [round(100 * (1 - b / a), 2) for a, b in zip(n, n[1:], strict=False)]
    assert drops == [13.83, 8.65, 0.21, 10.57, 15.0] and round(100 * n[-1] / n[0], 2) == 59.72
    assert 963908 * 15 // 100 == 963908 - 819322 and 196575 - 82679 == 113896


def test_release_round_trip_and_card(spark, run):
    path = new_path(spark, "release")
    manifest = release.write(run.released.select("doc_id", "clean", "split"), path)
    back = spark.read.parquet(f"{path}/data")
    assert back.count() == run.corpus.count() == sum(manifest["counts"].values())
    text = release.card("corpus", run.config, {"retention": corpus.retention(run.stage_rows())})
    assert "| stage |" in text and run.config.digest() in text


def test_runs_without_a_phase_keep_more(run):
    full = run.corpus.count()
    assert run.without(5).corpus.count() == run.p4.count() > full
    assert run.without(3).p3_ids.count() == run.cleaned.count()
    assert run.without(1).cleaned.count() >= run.cleaned.count()


def test_zipped_json_lines(spark):
    from corpuskit import sources

    path = new_path(spark, "jsonl")
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "source", "text")
    docs.write.option("compression", "gzip").json(path)
    assert sorted(sources.read_jsonl(spark, path, parts=3).collect()) == sorted(docs.collect())


# language


def test_a_profile_too_large_to_broadcast_is_joined(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    profile = lid.stage_profile(docs.filter("doc_id % 2 = 0"))
    asked = docs.filter("doc_id % 2 = 1")
    answers = [{r["doc_id"]: (r["label"], round(r["prob"], 6)) for r in lid.identifier(profile, "text", most)(asked).collect()} for most in (10**9, 1)]
    assert answers[0] == answers[1]


def test_trials_end_early_and_agree_with_whole_texts(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").orderBy("doc_id").collect()
    model = lid.Profile.of(lid.stage_profile(spark.read.parquet(f"{SMALL}/documents.parquet")))
    texts = [f" {' '.join(r['text'].lower().split())} " for r in docs if len(r["text"]) > 500]
    whole = model.scores(texts)[0].argmax(axis=1)
    odds, looked = model.sampled(texts, list(range(len(texts))), lid.Draws(trials=3))
    assert (odds.argmax(axis=1) == whole).mean() > 0.98 and np.allclose(odds.sum(axis=1), 1)
    assert looked.mean() < 0.5 * 3 * lid.Draws().most


def test_models_identify_whole_texts_and_draws_do_not_depend_on_partitions(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    model = lid.Profile.of(lid.train_profile(docs.filter("doc_id % 2 = 0"), top=3000))
    test = docs.filter("doc_id % 2 = 1").select("doc_id", "lang", lid.snippet(F.col("text"), 10).alias("text"))
    good = lid.predict_profile(test, model).join(test, "doc_id").filter("label = lang").count()
    assert good / test.count() > 0.9
    a, b = (sorted(lid.predict_profile(t, model, draws=lid.Draws(trials=5, most=40)).collect()) for t in (test, test.repartition(5)))
    assert a == b
    empty = spark.createDataFrame([(1, None)], "doc_id long, text string")
    assert lid.predict_profile(empty, model).first()["prob"] <= 1


def test_linear_model_beats_chance(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").withColumn("text", F.substring("text", 1, 300))
    predict = lid.train_linear(docs.filter("doc_id % 2 = 0"), features=1 << 10, iterations=8)
    test = docs.filter("doc_id % 2 = 1")
    assert predict(test).join(test, "doc_id").filter("label = lang").count() / test.count() > 0.85


# measures


def cells(spark, counts):
    return metrics.prf_from_counts(spark.createDataFrame(counts, "tp long, fp long, fn long")).collect()


def test_bootstrap_draws_from_the_cells(spark):
    rows = [("en", "en")] * 30 + [("en", "de")] * 5 + [("de", "en")] * 3 + [("de", "de")] * 22 + [("en", None)]
    got = metrics.bootstrap(spark.createDataFrame(rows, "gold string, predicted string"), "en").first()
    draw, f1s = np.random.default_rng(0), []
    for _ in range(2000):
        tp, fp, fn, _ = draw.multinomial(61, np.array([30, 3, 6, 22]) / 61)
        f1s.append(2 * tp / (2 * tp + fp + fn))
    assert abs(got["low"] - np.quantile(f1s, 0.025)) < 0.02 and abs(got["high"] - np.quantile(f1s, 0.975)) < 0.02


def test_printed_f1s_recompute(spark):
    rows = cells(spark, [(3, 0, 37), (29, 1, 11), (38, 8, 2), (0, 0, 0)])
    assert [round(r["f1"], 4) for r in sorted(rows, key=lambda r: r["f1"])] == [0.0, 0.1395, 0.8286, 0.8837]


def test_printed_fertility_recomputes(spark):
    rows = spark.createDataFrame([(35867, 23322, "a"), (35854, 23322, "b"), (60010, 23322, "c"), (5, 0, "a")], "n_tokens long, n_words long, t string")
    assert {r["t"]: round(r["micro"], 3) for r in metrics.fertility(rows, "t").collect()} == {"a": 1.538, "b": 1.537, "c": 2.573}
    saved, times = metrics.savings(35867, 60010)
    assert round(100 * saved, 1) == 40.2 and round(times, 2) == 1.67


def test_kappa(spark):
    rows = [("a", "a")] * 20 + [("a", "b")] * 5 + [("b", "a")] * 10 + [("b", "b")] * 15
    got = metrics.kappa(spark.createDataFrame(rows, "first string, second string")).first()
    assert got["agreement"] == 0.7 and got["kappa"] == pytest.approx(0.4)


def near_sets(spark, n=120):
    draw = random.Random(8)
    rows = []
    for i in range(n):
        x = set(draw.sample(range(4000), 40)) if i % 4 == 0 else (x - set(draw.sample(sorted(x), 2))) | set(draw.sample(range(4000), 2))
        rows.append((i, sorted(x)))
    return spark.createDataFrame(rows, "doc_id long, hashes array<long>")


def test_library_minhash_pairs_without_its_join(spark):
    from pyspark.ml.feature import HashingTF, MinHashLSH

    sets = near_sets(spark)
    text = sets.select("doc_id", F.transform("hashes", lambda x: x.cast("string")).alias("terms"))
    vectors = HashingTF(inputCol="terms", outputCol="features", numFeatures=1 << 18, binary=True).transform(text)
    model = MinHashLSH(inputCol="features", outputCol="h", numHashTables=2, seed=0).fit(vectors)
    joined = model.approxSimilarityJoin(vectors, vectors, 1 - 0.8, "d").filter("datasetA.doc_id < datasetB.doc_id")
    expected = sorted((r["a"], r["b"], r["j"]) for r in joined.select(F.col("datasetA.doc_id").alias("a"), F.col("datasetB.doc_id").alias("b"), (1 - F.col("d")).alias("j")).collect())
    found = neardup.mllib_candidates(sets, tables=2)
    assert len(expected) > 20 and sorted(tuple(r) for r in found.select("a", "b", "jaccard").collect()) == expected
    assert "datasetA" not in found._jdf.queryExecution().optimizedPlan().toString()


# tokenizer and character model


def test_merges_of_a_small_example():
    counts = [("low", 5), ("lower", 2), ("newest", 6), ("widest", 3)]
    model = tokenizer.train_from_counts(counts, 10_000)
    assert model.merges[:3] == [("e", "s"), ("es", "t"), ("l", "o")]
    for text in ("lowest newer", "widest", "日本 x\U0001f600", "low  lower"):
        assert tokenizer.Tokenizer.decode(model.encode(text)) == " ".join(text.split())


def naive_merges(counts, rounds):
    words, out = [([tokenizer.START, *w], n) for w, n in counts], []
    for _ in range(rounds):
        pairs = Counter()
        for s, n in words:
            for p in zip(s, s[1:], strict=False):
                pairs[p] += n
        if not pairs or max(pairs.values()) < 2:
            break
        best = min(pairs, key=lambda p: (-pairs[p], p))
        out.append(best)
        merged = []
        for s, n in words:
            t, i = [], 0
            while i < len(s):
                if tuple(s[i : i + 2]) == best:
                    t.append(s[i] + s[i + 1])
                    i += 2
                else:
                    t.append(s[i])
                    i += 1
            merged.append((t, n))
        words = merged
    return out


def test_merges_equal_a_plain_trainer():
    draw = random.Random(4)
    counts = [("".join(draw.choices("abcd", k=draw.randrange(1, 9))), draw.randrange(1, 9)) for _ in range(60)]
    assert tokenizer.train_from_counts(counts, 100_000).merges[:60] == naive_merges(counts, 60)


def test_sweep_counts_candidates_where_they_meet(spark):
    sets = near_sets(spark)
    settings = ((16, 4), (32, 2))
    found = neardup.sweep(sets, settings=settings)
    assert "Distinct" not in found._jdf.queryExecution().logical().toString()
    truth = {(r["a"], r["b"]) for r in neardup.brute_force(sets, 0.8).collect()}
    for b, r in settings:
        pairs = {(x["a"], x["b"]) for x in neardup.candidates(neardup.bands(neardup.signatures(sets), b, r)).collect()}
        row = found.filter(F.col("bands") == b).first()
        assert (row["candidates"], row["true_pairs"]) == (len(pairs), len(pairs & truth)) and len(pairs) > len(pairs & truth) > 0


def test_sweep_makes_every_candidate_and_looks_it_up(spark, monkeypatch):
    sets, asked, made = near_sets(spark), [], neardup.candidates
    monkeypatch.setattr(neardup, "candidates", lambda banded, marks=None, docs=None: asked.append(marks) or made(banded, marks, docs))
    neardup.sweep(sets, settings=((16, 4), (32, 2)))
    assert len(asked) == 2 and None not in asked  # before, only true pairs were compared
    banded = neardup.bands(neardup.signatures(sets), 32, 2)
    pairs = sorted(tuple(r) for r in made(banded).collect())
    keys = {}
    for r in banded.collect():
        keys.setdefault((r["band"], r["key"]), set()).add(r["doc_id"])
    assert pairs == sorted({p for ids in keys.values() for p in itertools.combinations(sorted(ids), 2)})
    marks = [*pairs[::3], (pairs[0][0], 10**12)]
    rows = made(banded, spark.createDataFrame(marks, "a long, b long"), 7).collect()
    assert sorted((r["a"], r["b"]) for r in rows) == pairs and sorted((r["a"], r["b"]) for r in rows if r["marked"]) == marks[:-1]


def test_a_merge_costs_what_it_changes():
    word = "".join(random.Random(6).choices("abcdefghij", k=200_000))
    began = time.process_time()
    model = tokenizer.train_from_counts([(word, 1), ("aaaaa", 3), ("abab", 2)], 259 + 11 + 400)
    assert len(model.merges) == 400 and time.process_time() - began < 20
    few = [(word[:3000], 1), ("aaaaa", 3), ("abab", 2), ("aa" * 7, 5)]
    assert tokenizer.train_from_counts(few, 259 + 11 + 60).merges == naive_merges(few, 60)


def test_words_left_in_the_cluster_give_the_same_merges(spark):
    draw = random.Random(5)
    counts = {"".join(draw.choices("abcdef", weights=[9, 7, 5, 3, 2, 1], k=draw.randrange(1, 9))): draw.randrange(1, 60) for _ in range(80)}
    table = spark.createDataFrame(sorted(counts.items()), "word string, n long")
    here = tokenizer.train_from_counts(sorted(counts.items()), 259 + 7 + 25)
    assert len(here.merges) == 25 and tokenizer.train_distributed(table, 259 + 7 + 25).merges == here.merges
    docs = spark.createDataFrame([(" ".join([w] * n),) for w, n in counts.items()], "clean string")
    assert tokenizer.train(docs, 259 + 7 + 8, most=5).merges == here.merges[:8]


def test_a_few_rounds_give_all_merges_of_words_left_in_the_cluster(spark, monkeypatch):
    """Symbols of one spelling come about in several ways; words are cut, merged in rounds, and still merged as one by one."""
    draw, rounds, merged = random.Random(12), [], tokenizer._merged
    parts = ["".join(draw.choices("abcde", k=draw.randrange(2, 5))) for _ in range(12)]
    counts = {"".join(draw.choices(parts, k=draw.randrange(1, 4))): draw.choice([1, 1, 2, draw.randrange(1, 400)]) for _ in range(400)}
    monkeypatch.setattr(tokenizer, "_merged", lambda pairs, room: rounds.append(len(pairs.kind)) or merged(pairs, room))
    table = spark.createDataFrame(sorted(counts.items()), "word string, n long")
    found = tokenizer.train_distributed(table, 259 + 6 + 150).merges
    assert found == naive_merges(sorted(counts.items()), 150)
    assert 1 < len(rounds) < 10  # before, a round counted all pairs for a few merges


def test_batches_of_merges_equal_one_by_one():
    """Whatever is merged at once, in the order of a plain trainer."""
    draw = random.Random(6)
    for _ in range(30):
        counts = [("".join(draw.choices("abcdefgh", k=draw.randrange(2, 6))), draw.randrange(1, 40)) for _ in range(40)]
        words, merges = [([tokenizer.START, *w], n) for w, n in counts], []
        while True:
            pairs = Counter()
            for s, n in words:
                for p in zip(s, s[1:], strict=False):
                    pairs[p] += n
            top = sorted(((x, y, n) for (x, y), n in pairs.items()), key=lambda r: (-r[2], r[0], r[1]))
            onward, before = {}, {}
            for x, y, n in top:
                onward[x], before[y] = max(n, onward.get(x, 0)), max(n, before.get(y, 0))
            batch = tokenizer.safe_batch(top, onward, before, 2, 10**6)
            if not batch:
                break
            merges += batch
            rows = pa.RecordBatch.from_arrays([pa.array([s for s, _ in words]), pa.array([n for _, n in words])], ["s", "n"])
            words = [(r["s"], r["n"]) for b in tokenizer._merge_batches(batch)(iter([rows])) for r in b.to_pylist()]
        assert merges == naive_merges(counts, 10**6)


def test_joined_character_counts_score_alike(spark, run):
    val, train = run.released.filter("split = 'val'").select("doc_id", "clean"), run.released.filter("split = 'train'")
    val = val.unionByName(spark.createDataFrame([(-1, ""), (-2, "x"), (-3, None)], "doc_id long, clean string"))
    bits = lambda model: {r["doc_id"]: (round(r["bits"], 4), r["n_chars"]) for r in charlm.score(val, model).collect()}
    joined = charlm.train(train, 3, most=10)
    assert isinstance(joined, charlm.GramCounts) and bits(joined) == bits(charlm.train(train, 3))


def test_tokenizer_is_saved_and_counts_tokens(spark, run):
    model = tokenizer.train(run.corpus, 400)
    path = new_path(spark, "tok")
    model.save(spark, path)
    again = tokenizer.Tokenizer.load(spark, path)
    assert again.merges == model.merges and len(model.vocabulary) <= 400
    sents = spark.createDataFrame([(1, "the of the"), (2, ""), (3, "über")], "sent_id long, text string")
    got = {r["sent_id"]: (r["n_tokens"], r["n_words"]) for r in tokenizer.token_counts(sents, again).collect()}
    assert got[1] == (len(model.encode("the of the")), 3) and 2 not in got


def test_higher_orders_predict_better(spark, run):
    val, train = run.released.filter("split = 'val'"), run.released.filter("split = 'train'")
    bits = [charlm.loss(val, charlm.train(train, n)) for n in (1, 2, 3)]
    assert bits[0] > bits[1] > bits[2] > 0
    native = charlm.entropy_native(train, val, 1).first()["bits_per_char"]
    assert bits[0] == pytest.approx(native, abs=1e-5)


def test_objective_prefers_the_cleaner_corpus(spark, run):
    raw = run.raw.withColumn("clean", F.trim(F.regexp_replace("text", "\\s+", " ")))
    sents = spark.read.parquet(f"{SMALL}/benchmark.parquet").withColumnRenamed("item_id", "sent_id")
    best, found = objective.search({"raw": raw, "curated": run.corpus}, sents, alpha=0.1, beta=1.0, gamma=1.0, target="en", n_min=10, vocab=350, share=True)
    assert best == "curated" and found["raw"].impurity > found["curated"].impurity == 0
    assert objective.search({"raw": raw}, sents, alpha=1, beta=1, gamma=1, target="en", n_min=10**6, vocab=350)[0] is None


# a whole run


def test_phase_three_is_the_trained_model_unless_told_otherwise(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    blind = corpus.CorpusRun(docs)
    right = blind.predicted.join(docs.select("doc_id", "lang"), "doc_id").filter("label = lang").count()
    assert 0.9 < right / blind.predicted.count() <= 1
    assert blind.p3_ids.count() == blind.predicted.filter("label = 'en' AND prob >= 0.5").count()


def test_a_source_of_one_language_with_leakage_loses_the_leakage(spark):
    """Sources that are partitions of the target language already, with every 17th other document among them."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    leaky = docs.filter("lang = 'en' OR doc_id % 17 = 0")
    run = corpus.CorpusRun(leaky, identify=corpus.profile_identifier(docs.filter("doc_id % 2 = 0")))
    rows = {r["stage"]: r for r in corpus.retention(run.stage_rows()).collect()}
    assert 0 < rows["p3"]["step_drop_pct"] < 10 and [rows[s]["n_docs"] for s in corpus.STAGES] == sorted((r["n_docs"] for r in rows.values()), reverse=True)


def test_rows_without_an_id_and_odd_texts_go_through(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "source", "text", "lang")
    odd = [(None, "src1", "the of and to in " * 40, "en"), (10_000, None, None, None), (10_001, "src0", "", "en"), (10_001, "src2", "x" * 5000, "fr")]
    both = docs.unionByName(spark.createDataFrame(odd, docs.schema))
    run = corpus.CorpusRun(both, identify=corpus.gold)
    stages = {(r["stage"], r["doc_id"]) for r in run.stage_rows().filter("doc_id IS NULL OR doc_id >= 10000").collect()}
    assert {("raw", None), ("p1", None), ("p2", None), ("p3", None), ("p4", None), ("raw", 10_000), ("p1", 10_000)} <= stages
    assert ("p2", 10_000) not in stages and corpus.CorpusRun(both.limit(0), identify=corpus.gold).p4_ids.count() == 0


# staged tables


def test_scratch_deletes_what_is_not_kept(spark):
    with scratch(spark) as keep:
        gone, kept = staged(spark.range(3), "gone"), keep(staged(spark.range(4), "kept"))
    assert kept.count() == 4 and not os.path.exists(gone.staged_at.replace("file:", ""))


def test_an_own_folder_is_refused_where_executors_are_elsewhere():
    class Context:
        master = "spark://somewhere:7077"
        getConf = staticmethod(lambda: {})
        getCheckpointDir = staticmethod(lambda: None)

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        session.shared_dir(type("S", (), {"sparkContext": Context})())


def test_hashes_are_found_among_keys_as_by_a_search():
    draw = np.random.default_rng(3)
    for keys in (draw.integers(0, 2**64, 5000, np.uint64), draw.integers(0, 2**44, 3000, np.uint64), np.array([0, 2**64 - 1], np.uint64)):
        keys = np.unique(keys)
        asked = np.r_[draw.permutation(keys), draw.integers(0, 2**64, 4000, np.uint64), keys[:50] + np.uint64(1), np.uint64(2**64 - 1)]
        at, known = grams.Places(keys).of(asked)
        assert np.array_equal(known, np.isin(asked, keys)) and np.array_equal(keys[at[known]], asked[known])
    assert not len(grams.Places(keys).of(np.zeros(0, np.uint64))[1])


def test_paragraph_baseline_computes_its_texts_and_scores_once(spark, run):
    seen = spark.sparkContext.accumulator(0)

    def counted(batches):
        for batch in batches:
            seen.add(batch.num_rows)
            yield batch

    docs = run.docs.select("doc_id", "text", "lang")
    rows = docs.select("doc_id", "text").mapInArrow(counted, "doc_id long, text string")
    out = objective.paragraph_pipeline(rows, lambda t: t.join(docs.select("doc_id", F.col("lang").alias("label")), "doc_id"), "en", run.p3)
    assert out.count() and seen.value <= 2 * docs.count()  # lines once for the first places, once for the texts


def test_sets_hashed_outside_of_sql_are_the_same(spark):
    texts = [None, "", "a", "a b", "a b c", "a  b c ", " a b c a b c", "é ü 漢字 \U0001f600", "x " * 300, "a b c"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id int, clean string")
    for n in (1, 3):
        sets = {r["doc_id"]: r["hashes"] for r in neardup.hashed(neardup.shingles(docs, n), "md5").collect()}
        rows = neardup.keyed_sets(docs, n).collect()
        assert {r["doc_id"]: r["hashes"] for r in rows} == sets and len(rows) == len(sets)
        assert all((a["key"] == b["key"]) == (a["hashes"] == b["hashes"]) for a in rows for b in rows)


def test_runs_without_a_phase_share_clean_texts_and_join_none_to_themselves(spark, run):
    whole = corpus.CorpusRun(run.docs, identify=corpus.gold)
    folders = {f.rsplit("/", 1)[0] for k in (2, 3, 4, 5) for f in whole.without(k).cleaned.inputFiles()}
    assert folders == {f.rsplit("/", 1)[0] for f in whole.cleaned.inputFiles()}
    assert "Join" not in whole.without(3).p3._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" in whole.p3._jdf.queryExecution().optimizedPlan().toString()
    assert whole.without(3).p3.count() == whole.cleaned.count() > whole.p3.count()


def test_distinct_pairs_of_texts():
    draw = np.random.default_rng(4)
    doc, hashes = np.sort(draw.integers(0, 40, 3000)), draw.integers(0, 60, 3000).astype(np.uint64)
    got = grams.distinct(doc, hashes)
    assert list(zip(*(x.tolist() for x in got), strict=True)) == sorted(set(zip(doc.tolist(), hashes.tolist(), strict=True)))
    assert not len(grams.distinct(doc[:0], hashes[:0])[0])
