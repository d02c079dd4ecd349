"""Measures over small tables: classification, intervals, agreement, fertility."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PREDICTED = ("gold", "predicted")


def confusion(rows: DataFrame, labels: list[str]) -> DataFrame:
    """gold x predicted counts with zeros; predictions outside `labels`, and none, count as `other`."""
    named = rows.withColumn("p", F.when(F.col("predicted").isin(labels), F.col("predicted")).otherwise("other"))
    return named.groupBy("gold").pivot("p", [*labels, "other"]).agg(F.count(F.lit(1))).na.fill(0)


def accuracy(rows: DataFrame, *by: str) -> DataFrame:
    hit = F.sum(F.when(F.col("gold") == F.col("predicted"), 1).otherwise(0))
    return rows.groupBy(*by).agg(F.count("*").alias("n"), hit.alias("n_correct"), F.round(hit / F.count("*"), 6).alias("accuracy"))


def ratio(a: Column, b: Column) -> Column:
    """a / b, and 0 for 0 / 0."""
    return F.when(b != 0, a / F.when(b != 0, b)).otherwise(0.0)


def prf(rows: DataFrame, *by: str) -> DataFrame:
    """Precision, recall and F1 of every label that occurs on either side."""
    sides = rows.select(*by, F.explode(F.array_distinct(F.array("gold", "predicted"))).alias("label"), "gold", "predicted").filter("label is not null")
    tp = F.sum(F.when(F.col("gold") == F.col("predicted"), 1).otherwise(0))
    fp = F.sum(F.when((F.col("predicted") == F.col("label")) & ~F.col("gold").eqNullSafe(F.col("predicted")), 1).otherwise(0))
    fn = F.sum(F.when((F.col("gold") == F.col("label")) & ~F.col("gold").eqNullSafe(F.col("predicted")), 1).otherwise(0))
    cells = sides.groupBy(*by, "label").agg(tp.alias("tp"), fp.alias("fp"), fn.alias("fn"))
    return prf_from_counts(cells)


def prf_from_counts(cells: DataFrame) -> DataFrame:
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return cells.withColumns({"precision": F.round(ratio(tp, tp + fp), 6), "recall": F.round(ratio(tp, tp + fn), 6), "f1": F.round(ratio(2 * tp, 2 * tp + fp + fn), 6)})


def f1_summary(rows: DataFrame, *by: str) -> DataFrame:
    cells = prf(rows, *by)
    tp, fp, fn = F.sum("tp"), F.sum("fp"), F.sum("fn")
    return cells.groupBy(*by).agg(F.round(F.avg("f1"), 6).alias("macro_f1"), F.round(2 * tp / (2 * tp + fp + fn), 6).alias("micro_f1"))


def misses(rows: DataFrame, target: str, *by: str) -> DataFrame:
    """Where the target's missed rows went."""
    gone = rows.filter((F.col("gold") == target) & ~F.col("predicted").eqNullSafe(F.lit(target)))
    return gone.groupBy(*by, "predicted").agg(F.count("*").alias("n"))


def bootstrap(rows: DataFrame, target: str, draws: int = 500, seed: int = 0) -> DataFrame:
    """(low, high): the 2.5 and 97.5 percentiles of the target's F1 over resamples of a test set.

    F1 needs only the counts of hits, false alarms and misses, so draws fall on these cells laid in a row: draw i of
    resample r on place MD5(seed|r|i) mod n, the same everywhere. The rows themselves are counted once.
    """
    is_gold, is_hit = F.col("gold") == target, F.col("predicted").eqNullSafe(F.lit(target))
    cells = rows.agg(F.count("*").alias("n"), F.count_if(is_gold & is_hit).alias("a"), F.count_if(~is_gold & is_hit).alias("b"), F.count_if(is_gold & ~is_hit).alias("c"))
    spark = rows.sparkSession
    turns = spark.range(draws).select(F.col("id").alias("r")).crossJoin(F.broadcast(cells)).filter("n > 0")
    drawn = turns.select("r", "a", "b", "c", "n", F.explode(F.sequence(F.lit(0), F.col("n").cast("int") - 1)).alias("i"))
    place = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), "r", "i")), 1, 8), 16, 10).cast("long") % F.col("n")
    cell = drawn.select("r", "a", "b", "c", place.alias("p"))
    each = cell.groupBy("r").agg(F.count_if(F.expr("p < a")).alias("tp"), F.count_if(F.expr("p >= a AND p < a + b")).alias("fp"), F.count_if(F.expr("p >= a + b AND p < a + b + c")).alias("fn"))
    f1 = each.select(ratio(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")).alias("f1"))
    return f1.agg(F.round(F.percentile("f1", 0.025), 6).alias("low"), F.round(F.percentile("f1", 0.975), 6).alias("high"))


def ci_overlap(intervals: DataFrame) -> DataFrame:
    """(model_a, model_b, overlap) for pairs of rows of intervals(model, low, high)."""
    a, b = (intervals.select(*(F.col(c).alias(f"{c}_{x}") for c in ("model", "low", "high"))) for x in "ab")
    return a.join(b, F.col("model_a") < F.col("model_b")).select("model_a", "model_b", ((F.col("low_a") <= F.col("high_b")) & (F.col("low_b") <= F.col("high_a"))).alias("overlap"))


def kappa(rows: DataFrame, a: str = "first", b: str = "second") -> DataFrame:
    """Cohen's agreement of two annotators' columns."""
    cells = rows.groupBy(a, b).agg(F.count("*").alias("n"))
    n = cells.agg(F.sum("n").alias("all"), F.sum(F.when(F.col(a) == F.col(b), F.col("n")).otherwise(0)).alias("same"))
    by_a, by_b = cells.groupBy(F.col(a).alias("x")).agg(F.sum("n").alias("na")), cells.groupBy(F.col(b).alias("x")).agg(F.sum("n").alias("nb"))
    chance = by_a.join(by_b, "x").agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).alias("c"))
    po, pe = F.col("same") / F.col("all"), F.col("c") / (F.col("all") * F.col("all"))
    return n.crossJoin(chance).select(F.col("all").alias("n"), F.round(po, 6).alias("agreement"), F.round(F.when(pe == 1, 1.0).otherwise((po - pe) / (1 - pe)), 6).alias("kappa"))


def pair_prf(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision and recall of pairs (a, b) against true pairs."""
    both = found.select("a", "b", F.lit(1).alias("f")).join(truth.select("a", "b", F.lit(1).alias("t")), ["a", "b"], "full")
    count = lambda c: F.coalesce(F.sum(F.when(c, 1).otherwise(0)), F.lit(0))
    f, t = F.col("f").isNotNull(), F.col("t").isNotNull()
    return prf_from_counts(both.agg(count(f & t).alias("tp"), count(f & ~t).alias("fp"), count(~f & t).alias("fn")))


def fertility(counts: DataFrame, *by: str) -> DataFrame:
    """counts(n_tokens, n_words), sentences without a word left out: macro is the mean of ratios, micro the ratio of sums."""
    some = counts.filter("n_words > 0")
    return some.groupBy(*by).agg(
        F.count("*").alias("n_sentences"),
        F.sum("n_tokens").alias("n_tokens"),
        F.sum("n_words").alias("n_words"),
        F.round(F.avg(F.col("n_tokens") / F.col("n_words")), 6).alias("macro"),
        F.round(F.sum("n_tokens") / F.sum("n_words"), 6).alias("micro"),
    )


def fertility_histogram(counts: DataFrame, width: float = 0.25, *by: str) -> DataFrame:
    place = F.floor(F.col("n_tokens") / F.col("n_words") / width).cast("long")
    return counts.filter("n_words > 0").groupBy(*by, place.alias("bin")).agg(F.count("*").alias("n_sentences"))


def savings(tokens: int, reference: int) -> tuple[float, float]:
    """Share of the reference's tokens saved, and how many times as many the reference needs."""
    return 1 - tokens / reference, reference / tokens
