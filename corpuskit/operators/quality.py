"""Quality by coverage of character n-grams against a clean seed, and its alternatives."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.config import DEFAULT
from corpuskit.functions import metrics
from corpuskit.functions.grams import Places, distinct, gram_hashes, pieces
from corpuskit.functions.text import char_grams, word_count
from corpuskit.operators import charlm
from corpuskit.operators.order_stats import value_at
from corpuskit.session import ship, staged

#: Seed grams that are broadcast at most (8 bytes each); a larger seed is joined.
BROADCAST_GRAMS = 20_000_000


def seed_docs(docs: DataFrame, source: str = "src0", least: int = DEFAULT.seed_min_words, text: str = "clean") -> DataFrame:
    return docs.filter((F.col("source") == source) & (word_count(F.col(text)) >= least))


def labelled_seed(docs: DataFrame, labels: DataFrame, least: int = DEFAULT.seed_min_words, text: str = "clean") -> DataFrame:
    good = labels.filter("quality = 1").select("doc_id")
    return docs.filter(word_count(F.col(text)) >= least).join(good, "doc_id", "left_semi")


def seed_grams(seed: DataFrame, n: int = DEFAULT.char_n, text: str = "clean") -> DataFrame:
    return seed.select(F.explode(char_grams(F.col(text), n)).alias("gram")).distinct()


def coverage_joined(docs: DataFrame, grams: DataFrame, n: int = DEFAULT.char_n, text: str = "clean") -> DataFrame:
    """(doc_id, hits, total, coverage) by exploding and joining; a seed of any size. No n-gram: coverage 0."""
    items = docs.select("doc_id", F.explode(char_grams(F.col(text), n)).alias("gram"))
    met = items.join(grams.withColumn("seen", F.lit(1)), "gram", "left")
    counted = met.groupBy("doc_id").agg(F.count("seen").alias("hits"), F.count("*").alias("total"))
    full = docs.select("doc_id").join(counted, "doc_id", "left").na.fill(0, ["hits", "total"])
    return full.withColumn("coverage", F.when(F.col("total") > 0, F.col("hits") / F.col("total")).otherwise(0.0))


def _text_grams(n: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in pieces(whole, "text"):
                _, hashes = gram_hashes([t or "" for t in batch.column("text").to_pylist()], n)
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(hashes).view(np.int64))], ["gram"])

    return run


def hashed_seed(seed: DataFrame, n: int = DEFAULT.char_n, text: str = "clean") -> DataFrame:
    """(gram): the seed's distinct n-grams as hashes."""
    ship(seed.sparkSession)
    return seed.select(F.col(text).alias("text")).mapInArrow(_text_grams(n), "gram long").distinct()


def coverage(docs: DataFrame, seed: DataFrame, n: int = DEFAULT.char_n, text: str = "clean", most: int = BROADCAST_GRAMS) -> DataFrame:
    """The same in one narrow pass with the seed's n-grams broadcast as sorted hashes, if they are few enough."""
    spark = docs.sparkSession
    grams = staged(hashed_seed(seed, n, text), "seed-grams")
    if grams.count() > most:
        return coverage_joined(docs, seed_grams(seed, n, text), n, text)
    shared = spark.sparkContext.broadcast(np.sort(grams.toArrow().column("gram").to_numpy().view(np.uint64)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Places(shared.value) if len(shared.value) else None
        for whole in batches:
            for batch in pieces(whole, "text"):
                doc, flat = distinct(*gram_hashes([t or "" for t in batch.column("text").to_pylist()], n))
                hit = known.of(flat)[1] if known else np.zeros(len(flat), bool)
                total = np.bincount(doc, minlength=batch.num_rows)
                hits = np.bincount(doc[hit], minlength=batch.num_rows)
                share = np.where(total > 0, hits / np.maximum(total, 1), 0.0)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(hits, pa.int64()), pa.array(total, pa.int64()), pa.array(share)], ["doc_id", "hits", "total", "coverage"])

    return docs.select("doc_id", F.col(text).alias("text")).mapInArrow(run, "doc_id long, hits long, total long, coverage double")


def threshold(scored: DataFrame, percent: int = DEFAULT.drop_percent, rule: str = "floor", column: str = "coverage") -> float | None:
    """The least score kept. floor: the value at place floor(q N); interpolated: the usual quantile; approx: a sketch's."""
    n = scored.count()
    if not n:
        return None
    if rule == "floor":
        return value_at(scored, column, n * percent // 100)
    if rule == "interpolated":
        place = (n - 1) * percent / 100
        low, part = int(place), place - int(place)
        a = value_at(scored, column, low)
        return a + part * (value_at(scored, column, low + 1) - a) if part else a
    if rule == "approx":
        return scored.agg(F.percentile_approx(column, percent / 100, 10_000)).first()[0]
    raise ValueError(f"no rule {rule}")


def drop_bottom(scored: DataFrame, percent: int = DEFAULT.drop_percent, rule: str = "floor", column: str = "coverage") -> DataFrame:
    """Rows at the threshold or above; ties stay."""
    least = threshold(scored, percent, rule, column)
    return scored if least is None else scored.filter(F.col(column) >= least)


def drop_below(scored: DataFrame, least: float, column: str = "coverage") -> DataFrame:
    return scored.filter(F.col(column) >= least)


def drop_bottom_by(scored: DataFrame, by: str, percent: int = DEFAULT.drop_percent, column: str = "coverage") -> DataFrame:
    """The floor rule inside each group, from counts of distinct scores rather than a sort of rows."""
    counts = scored.groupBy(by, column).agg(F.count("*").alias("n"))
    w = Window.partitionBy(by).orderBy(column)
    upto = counts.withColumns({"upto": F.sum("n").over(w), "of": F.sum("n").over(Window.partitionBy(by))})
    least = upto.filter(F.col("upto") > F.floor(F.col("of") * percent / 100)).groupBy(by).agg(F.min(column).alias("least"))
    return scored.join(least, by).filter(F.col(column) >= F.col("least")).drop("least")


def histogram(scored: DataFrame, bins: int = 20, column: str = "coverage") -> DataFrame:
    place = F.least(F.floor(F.col(column) * bins), F.lit(bins - 1)).cast("long")
    return scored.groupBy(place.alias("bin")).agg(F.count("*").alias("n_docs"))


def auc(scored: DataFrame, labels: DataFrame, column: str = "coverage", label: str = "quality", bins: int = 10_000) -> DataFrame:
    """Area under the ROC curve by rank sums over distinct scores in [0, 1]; ties count a half. Ranks are summed over
    bins first, so that no task has to order all scores."""
    place = F.least(F.floor(F.col(column) * bins), F.lit(bins - 1)).alias("bin")
    cells = scored.join(labels.select("doc_id", label), "doc_id").groupBy(place, column).agg(F.sum(label).alias("pos"), F.sum(1 - F.col(label)).alias("neg"))
    lower = lambda w: F.coalesce(F.sum("neg").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # one row for each bin
    before = cells.groupBy("bin").agg(F.sum("neg").alias("neg")).select("bin", lower(Window.orderBy("bin")).alias("before"))
    within = cells.withColumn("within", lower(Window.partitionBy("bin").orderBy(column)))
    below = within.join(before, "bin").withColumn("below", F.col("before") + F.col("within"))
    return below.agg(F.sum("pos").alias("n_pos"), F.sum("neg").alias("n_neg"), F.round(F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2)) / (F.sum("pos") * F.sum("neg")), 6).alias("auc"))


def evaluate_drop(scored: DataFrame, kept: DataFrame, labels: DataFrame, label: str = "quality") -> DataFrame:
    """(n_labelled, n_poor, n_dropped, n_hit, precision, recall) of a drop as a finder of poor documents (label 0)."""
    rows = scored.select("doc_id").join(labels.select("doc_id", label), "doc_id").join(kept.select("doc_id", F.lit(1).alias("k")).distinct(), "doc_id", "left")
    poor, gone = F.col(label) == 0, F.col("k").isNull()
    cells = rows.agg(F.count("*").alias("n_labelled"), F.count_if(poor).alias("n_poor"), F.count_if(gone).alias("n_dropped"), F.count_if(poor & gone).alias("n_hit"))
    hit = F.col("n_hit")
    return cells.withColumns({"precision": F.round(metrics.ratio(hit, F.col("n_dropped")), 6), "recall": F.round(metrics.ratio(hit, F.col("n_poor")), 6)})


def perplexity_score(docs: DataFrame, seed: DataFrame, order: int = 4, text: str = "clean") -> DataFrame:
    """(doc_id, coverage): the alternative score, from a character model of the clean seed: 2 to the power of minus the
    bits of a character, so that it lies between 0 and 1 and the better texts have more. No text: 0."""
    scored = charlm.score(docs, charlm.train(seed, order, text=text), text)
    return scored.select("doc_id", F.when(F.col("n_chars") > 0, F.pow(F.lit(2.0), -F.col("bits_per_char"))).otherwise(0.0).alias("coverage"))


def train_classifier(docs: DataFrame, labels: DataFrame, features: int = 1 << 16, n: int = 3, text: str = "clean"):
    """The trained alternative: logistic regression on hashed character n-grams. Returns (doc_id, probability) of a DataFrame."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF
    from pyspark.ml.functions import vector_to_array

    hashing = HashingTF(inputCol="grams", outputCol="features", numFeatures=features, binary=True)
    vectors = lambda df: hashing.transform(df.withColumn("grams", char_grams(F.col(text), n)))
    fit = vectors(docs.join(labels.select("doc_id", F.col("quality").cast("double").alias("label")), "doc_id"))
    model = LogisticRegression(maxIter=30, regParam=0.01).fit(fit.select("features", "label"))
    return lambda df: model.transform(vectors(df)).select("doc_id", vector_to_array("probability")[1].alias("probability"))
