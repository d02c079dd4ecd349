"""Phase 6: order, split, tokenizer, fertility, character model."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.functions import metrics
from corpuskit.operators import charlm, release, tokenizer
from corpuskit.plans import objective
from corpuskit.queries.corpus import P1, P2, P3, RAW, UP5, WS, run_of
from corpuskit.queries.registry import query, table, version
from corpuskit.session import staged

_TOKENIZERS: dict[tuple, tokenizer.Tokenizer] = {}


@query("p6_shuffle", f"{UP5} SELECT doc_id, row_number() OVER (ORDER BY md5('0|' || doc_id), doc_id) AS place FROM p5")
def p6_shuffle(spark, d):
    return release.places(run_of(spark, d).corpus)


@query("p6_split_exact", f"{UP5} SELECT doc_id, CASE WHEN row_number() OVER (ORDER BY md5('0|' || doc_id)) <= (SELECT count(*) FROM p5) * 95 // 100 THEN 'train' ELSE 'val' END AS split FROM p5")
def p6_split_exact(spark, d):
    return run_of(spark, d).released.select("doc_id", "split")


@query("p6_split_hash", "SELECT doc_id, CASE WHEN CAST('0x' || substr(md5('0|' || doc_id), 1, 8) AS BIGINT) < 4294967296 * 95 // 100 THEN 'train' ELSE 'val' END AS split FROM documents")
def p6_split_hash(spark, d):
    return release.split(table(spark, d), how="hash").select("doc_id", "split")


def _sentences(spark, d) -> DataFrame:
    return table(spark, d, "benchmark").select(F.col("item_id").alias("sent_id"), "text")


def _grams(name: str, source: str, text: str) -> str:
    return f"{name} AS (SELECT id, unnest(CASE WHEN len(ws) >= 8 THEN list_distinct(list_transform(range(1, len(ws) - 6), lambda i: array_to_string(ws[i:i+7], ' '))) ELSE [] END) AS g FROM (SELECT id, string_split({text}, ' ') AS ws FROM {source}))"


_CONTAMINATED = f"pd AS (SELECT doc_id AS id, clean FROM p3), bd AS (SELECT item_id AS id, trim(regexp_replace(text, '{WS}', ' ', 'g')) AS t FROM benchmark), {_grams('dg', 'pd', 'clean')}, {_grams('bg', 'bd', 't')}, bad AS (SELECT DISTINCT id FROM dg WHERE g IN (SELECT g FROM bg))"


@query("decontam", f"WITH {RAW}, {P1}, {P2}, {P3}, {_CONTAMINATED} SELECT doc_id FROM p3 WHERE doc_id NOT IN (SELECT id FROM bad)")
def decontam(spark, d):
    return release.decontaminate(run_of(spark, d).p3, _sentences(spark, d)).select("doc_id")


_WORDS = f"{UP5}, wc AS (SELECT word, count(*) AS n FROM (SELECT unnest(string_split(clean, ' ')) AS word FROM p5) WHERE word <> '' GROUP BY 1)"
_PAIRS = f"{_WORDS}, m AS (SELECT list_concat(['▁'], string_split(word, '')) AS s, n FROM wc), pr AS (SELECT s[i] AS left, s[i+1] AS right, sum(n) AS n FROM (SELECT s, n, unnest(range(1, len(s))) AS i FROM m) GROUP BY 1, 2)"


@query("tok_word_counts", f"{_WORDS} SELECT word, n FROM wc")
def tok_word_counts(spark, d):
    return tokenizer.word_counts(run_of(spark, d).corpus)


@query("tok_pair_counts", f"{_PAIRS} SELECT \"left\", \"right\", CAST(n AS BIGINT) AS n FROM pr")
def tok_pair_counts(spark, d):
    return tokenizer.pair_counts(tokenizer.word_counts(run_of(spark, d).corpus))


@query("tok_first_merge", f"{_PAIRS} SELECT \"left\", \"right\" FROM pr ORDER BY n DESC, \"left\", \"right\" LIMIT 1")
def tok_first_merge(spark, d):
    pairs = tokenizer.pair_counts(tokenizer.word_counts(run_of(spark, d).corpus))
    return pairs.orderBy(F.desc("n"), "left", "right").limit(1).select("left", "right")


#: Entries of the tokenizers compared, as published: two of one size, and a general one several times as large.
VOCAB, GENERAL_VOCAB = 16_000, 100_000


def tokenizers(spark, d, vocab: int = VOCAB, general: int = GENERAL_VOCAB) -> dict[str, tokenizer.Tokenizer]:
    """Curated, curated without evaluation passages, raw source A (control), raw union, and a larger one of other languages."""
    run = run_of(spark, d, None)
    docs = run.raw.withColumn("clean", F.col("text"))
    parts = {
        "curated": (run.corpus, vocab),
        "curated_decontaminated": (release.decontaminate(run.corpus, _sentences(spark, d)), vocab),
        "raw_control": (docs.filter("role = 'A' AND lang = 'en'"), vocab),
        "raw_union": (docs, vocab),
        "other_languages": (docs.filter("lang != 'en'"), general),
    }
    out = {}
    for name, (rows, size) in parts.items():
        key = (*version(spark, d), name, size)
        if key not in _TOKENIZERS:
            _TOKENIZERS[key] = tokenizer.train(rows, size)
        out[name] = _TOKENIZERS[key]
    return out


def _english(spark, d) -> DataFrame:
    """Benchmark sentences that the function-word baseline takes for the target language."""
    from corpuskit.operators import lid

    sents = _sentences(spark, d)
    named = lid.predict_function_words(sents.withColumnRenamed("sent_id", "doc_id")).filter("label = 'en'")
    return sents.join(named.select(F.col("doc_id").alias("sent_id")), "sent_id", "left_semi")


def _counts(spark, d) -> DataFrame:
    sents = staged(_english(spark, d), "sentences")
    return reduce(DataFrame.union, (tokenizer.token_counts(sents, m).withColumn("tokenizer", F.lit(name)) for name, m in tokenizers(spark, d).items()))


@query("fert_tokenizers")
def fert_tokenizers(spark, d):
    """Macro and micro fertility of every tokenizer, with the share of the reference's tokens saved."""
    table_ = metrics.fertility(_counts(spark, d), "tokenizer")
    other = table_.filter("tokenizer = 'other_languages'").select(F.col("n_tokens").alias("ref"))
    return table_.crossJoin(other).select("*", F.round(1 - F.col("n_tokens") / F.col("ref"), 6).alias("savings"), F.round(F.col("ref") / F.col("n_tokens"), 6).alias("multiplier")).drop("ref")


@query("fert_hist_trained")
def fert_hist_trained(spark, d):
    return metrics.fertility_histogram(_counts(spark, d), 0.25, "tokenizer")


def _bounds_sql(select: str) -> str:
    return f"WITH s AS (SELECT item_id, trim(regexp_replace(text, '{WS}', ' ', 'g')) AS t FROM benchmark), c AS (SELECT k AS tokenizer, len(string_split(t, ' ')) AS n_words, CASE k WHEN 'words' THEN len(string_split(t, ' ')) WHEN 'chars' THEN length(replace(t, ' ', '')) ELSE strlen(replace(t, ' ', '')) END AS n_tokens FROM s, (VALUES ('words'), ('chars'), ('bytes')) x(k) WHERE t <> '') SELECT tokenizer, {select} FROM c GROUP BY 1"


def _bounds(spark, d) -> DataFrame:
    return reduce(DataFrame.union, (tokenizer.trivial(_sentences(spark, d), k).withColumn("tokenizer", F.lit(k)) for k in ("words", "chars", "bytes")))


@query("fert_bounds", _bounds_sql("count(*) AS n_sentences, CAST(sum(n_tokens) AS BIGINT) AS n_tokens, CAST(sum(n_words) AS BIGINT) AS n_words, round(avg(n_tokens / n_words), 6) AS macro, round(sum(n_tokens) / sum(n_words), 6) AS micro"))
def fert_bounds(spark, d):
    return metrics.fertility(_bounds(spark, d), "tokenizer")


@query("fert_hist", _bounds_sql("bin, count(*) AS n_sentences").replace("FROM c GROUP BY 1", "FROM (SELECT tokenizer, CAST(floor(n_tokens / n_words / 0.25) AS BIGINT) AS bin FROM c) GROUP BY 1, 2"))
def fert_hist(spark, d):
    """Sentences by fertility, of the bounds: a token for each word, character or byte."""
    return metrics.fertility_histogram(_bounds(spark, d), 0.25, "tokenizer")


@query("fert_macro", _bounds_sql("round(avg(n_tokens / n_words), 6) AS macro"))
def fert_macro(spark, d):
    return metrics.fertility(_bounds(spark, d), "tokenizer").select("tokenizer", "macro")


@query("fert_micro", _bounds_sql("round(sum(n_tokens) / sum(n_words), 6) AS micro"))
def fert_micro(spark, d):
    return metrics.fertility(_bounds(spark, d), "tokenizer").select("tokenizer", "micro")


def _lm_sql(n: int) -> str:
    split = f"{UP5}, sp AS (SELECT clean, row_number() OVER (ORDER BY md5('0|' || doc_id)) <= (SELECT count(*) FROM p5) * 95 // 100 AS tr FROM p5)"
    g = lambda name, m, cond: f"{name} AS (SELECT g, count(*) AS c FROM (SELECT unnest(list_transform(range(1, length(clean) - {m} + 2), lambda i: substr(clean, i, {m}))) AS g FROM sp WHERE {cond}) GROUP BY 1)"
    parts = f"{split}, {g('t1', 1, 'tr')}, {g('tn', n, 'tr')}, {g('vn', n, 'NOT tr')}, v AS (SELECT count(*) + 1 AS v FROM t1)"
    context = "(SELECT sum(c) FROM t1)" if n == 1 else "coalesce(t1.c, 0)"
    join = "" if n == 1 else "LEFT JOIN t1 ON t1.g = substr(vn.g, 1, 1)"
    return f"{parts} SELECT CAST(sum(vn.c) AS BIGINT) AS n_grams, round(-sum(vn.c * log2((coalesce(tn.c, 0) + 0.1) / ({context} + 0.1 * v))) / sum(vn.c), 6) AS bits_per_char FROM vn LEFT JOIN tn ON tn.g = vn.g {join}, v"


@query("charlm_unigram", _lm_sql(1))
def charlm_unigram(spark, d):
    docs = run_of(spark, d).released
    return charlm.entropy_native(docs.filter("split = 'train'"), docs.filter("split = 'val'"), 1)


@query("charlm_bigram", _lm_sql(2))
def charlm_bigram(spark, d):
    docs = run_of(spark, d).released
    return charlm.entropy_native(docs.filter("split = 'train'"), docs.filter("split = 'val'"), 2)


@query("charlm_loss")
def charlm_loss(spark, d):
    """Validation bits per character by model order."""
    docs = run_of(spark, d).released
    train, val = docs.filter("split = 'train'"), docs.filter("split = 'val'")
    return spark.createDataFrame([(n, charlm.loss(val, charlm.train(train, n))) for n in (1, 2, 3, 4)], "n int, bits_per_char double")


@query("ablation")
def ablation(spark, d):
    return objective.ablation(run_of(spark, d), _english(spark, d), 1000, order=3)


@query("obj_loss")
def obj_loss(spark, d):
    """The composite loss of the curated corpus and of the raw union."""
    run = run_of(spark, d)
    raw = run.raw.withColumn("clean", F.trim(F.regexp_replace("text", WS, " ")))
    _, found = objective.search({"curated": run.corpus, "raw": raw}, _english(spark, d), alpha=1.0, beta=1.0, gamma=1.0, target="en", n_min=20, share=True)
    return spark.createDataFrame([(k, x.fertility, x.redundancy, x.impurity, x.n_docs, x.value, x.feasible) for k, x in found.items()], "corpus string, fertility double, redundancy double, impurity long, n_docs long, loss double, feasible boolean")
