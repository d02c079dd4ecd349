"""Language identification: n-gram profiles, linear models on hashed n-grams, and cheap baselines."""

from __future__ import annotations

import dataclasses
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.functions.grams import Places, gram_hashes, mix, pieces
from corpuskit.functions.text import char_gram_bag, collapse_ws
from corpuskit.session import ship, staged

ORDERS = (1, 2, 3)
#: Rows of a profile that are broadcast as arrays at most (about 60 bytes each); a larger one is joined.
BROADCAST_ROWS = 4_000_000


def prepared(text: Column) -> Column:
    """Lower case, white space collapsed, a space on either side."""
    return F.concat(F.lit(" "), collapse_ws(F.lower(text)), F.lit(" "))


def gram_rows(docs: DataFrame, *keep: str, text: str = "text") -> DataFrame:
    """(keep..., n, gram): every character n-gram of every document, repeats included."""
    ready = docs.select(*keep, prepared(F.col(text)).alias("t")).filter("t is not null")
    each = ready.select(*keep, F.explode(F.array(*(F.struct(F.lit(n).alias("n"), char_gram_bag(F.col("t"), n).alias("g")) for n in ORDERS))).alias("x"))
    return each.select(*keep, "x.n", F.explode("x.g").alias("gram"))


def _count_batches(labels: str):
    """Counts of packed n-grams by label; a code holds up to three characters of 21 bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in pieces(whole, "t"):
                names = batch.column(labels).dictionary_encode()
                label = names.indices.to_numpy(zero_copy_only=False)
                texts = batch.column("t").to_pylist()
                points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
                doc = np.repeat(np.arange(len(texts)), [len(t) for t in texts])
                for n in ORDERS:
                    m = max(len(points) - n + 1, 0)
                    code = np.zeros(m, np.uint64)
                    for j in range(n):
                        code = (code << np.uint64(21)) | points[j : j + m]
                    at = np.flatnonzero(doc[:m] == doc[n - 1 :])
                    for k, name in enumerate(names.dictionary.to_pylist()):
                        found, times = np.unique(code[at[label[doc[at]] == k]], return_counts=True)
                        letters = np.stack([(found >> np.uint64(21 * (n - 1 - j))) & np.uint64(0x1FFFFF) for j in range(n)], axis=1).astype("<u4")
                        row = letters.tobytes().decode("utf-32-le", "surrogatepass")
                        grams = [row[i : i + n] for i in range(0, len(row), n)]
                        columns = [pa.array([name] * len(grams), pa.string()), pa.array(np.full(len(grams), n, np.int32)), pa.array(grams, pa.string()), pa.array(times, pa.int64())]
                        yield pa.RecordBatch.from_arrays(columns, ["label", "n", "gram", "c"])

    return run


def gram_counts(docs: DataFrame, label: str = "lang", text: str = "text") -> DataFrame:
    """(label, n, gram, c): how often documents of each label hold each character n-gram; counted in the batches first."""
    ship(docs.sparkSession)
    ready = docs.select(F.col(label).alias("label"), prepared(F.col(text)).alias("t")).filter("t is not null and label is not null")
    return ready.mapInArrow(_count_batches("label"), "label string, n int, gram string, c long").groupBy("label", "n", "gram").agg(F.sum("c").alias("c"))


def train_profile(docs: DataFrame, label: str = "lang", alpha: float = 0.5, text: str = "text", top: int | None = None) -> DataFrame:
    """(label, n, gram, logp, unknown): smoothed log probabilities of the n-grams a label has, and of those it hasn't.

    Documents without a label or text don't teach. top: of each label and order, only the most frequent n-grams.
    """
    counts = staged(gram_counts(docs, label, text), "gram-counts")
    vocabulary = counts.groupBy("n").agg(F.count_distinct("gram").alias("v"))
    if top:
        w = Window.partitionBy("label", "n").orderBy(F.desc("c"), "gram")
        counts = counts.withColumn("place", F.row_number().over(w)).filter(F.col("place") <= top).drop("place")
    totals = counts.groupBy("label", "n").agg(F.sum("c").alias("t"))
    # a row for each label and order
    full = counts.join(F.broadcast(totals), ["label", "n"]).join(F.broadcast(vocabulary), "n")
    below = F.col("t") + alpha * F.col("v")
    return full.select("label", "n", "gram", F.log((F.col("c") + alpha) / below).alias("logp"), F.log(alpha / below).alias("unknown"))


def _posterior(scored: DataFrame, temper: float | None) -> DataFrame:
    """scored(doc_id, label, score, grams) to (doc_id, label, prob): the softmax of the scores, its top label."""
    heat = F.greatest(F.lit(1.0), F.col("grams") / F.lit(float(temper))) if temper else F.lit(1.0)
    warm = scored.withColumn("s", F.col("score") / heat)
    best = warm.groupBy("doc_id").agg(F.min(F.struct((-F.col("s")).alias("s"), "label")).alias("x"), F.collect_list("s").alias("all"))
    odds = F.aggregate("all", F.lit(0.0), lambda acc, s: acc + F.exp(s + F.col("x.s")))
    return best.select("doc_id", F.col("x.label").alias("label"), (1 / odds).alias("prob"))


def predict_profile_joined(docs: DataFrame, profile: DataFrame, temper: float | None = None, text: str = "text") -> DataFrame:
    """(doc_id, label, prob) by joining n-gram counts with the profile; any size of profile."""
    bag = gram_rows(docs, "doc_id", text=text).groupBy("doc_id", "n", "gram").agg(F.count("*").alias("m"))
    unknown = profile.select("label", "n", "unknown").distinct()
    met = bag.join(profile.select("label", "n", "gram", "logp", "unknown"), ["n", "gram"])
    gain = met.groupBy("doc_id", "label").agg(F.sum(F.col("m") * (F.col("logp") - F.col("unknown"))).alias("gain"))
    sizes = bag.groupBy("doc_id", "n").agg(F.sum("m").alias("size"))
    base = sizes.join(unknown, "n").groupBy("doc_id", "label").agg(F.sum(F.col("size") * F.col("unknown")).alias("base"), F.sum("size").alias("grams"))
    return _posterior(base.join(gain, ["doc_id", "label"], "left").select("doc_id", "label", (F.col("base") + F.coalesce("gain", F.lit(0.0))).alias("score"), "grams"), temper)


@dataclasses.dataclass
class Profile:
    """A profile as arrays, for narrow scoring. identifier() checks its size first."""

    labels: list[str]
    keys: np.ndarray
    gains: np.ndarray  # key x label: logp less unknown
    unknown: np.ndarray  # order x label

    @classmethod
    def of(cls, profile: DataFrame) -> Profile:
        rows = profile.toArrow().to_pandas()
        labels = sorted(rows["label"].unique())
        number = {x: i for i, x in enumerate(labels)}
        hashes = np.zeros(len(rows), np.uint64)
        for n in ORDERS:
            here = (rows["n"] == n).to_numpy()
            hashes[here] = gram_hashes(rows["gram"][here].tolist(), n)[1]
        keys = np.unique(hashes)
        gains = np.zeros((len(keys), len(labels)))
        gains[np.searchsorted(keys, hashes), rows["label"].map(number)] = rows["logp"] - rows["unknown"]
        unknown = np.zeros((len(ORDERS), len(labels)))
        for label, n, u in rows[["label", "n", "unknown"]].drop_duplicates().itertuples(index=False):
            unknown[n - 1, number[label]] = u
        return cls(labels, keys, gains, unknown)

    @cached_property
    def _places(self) -> Places:
        return Places(self.keys)

    def _gains(self, doc: np.ndarray, hashes: np.ndarray, order: np.ndarray, n: int) -> np.ndarray:
        """Summed log probabilities of n-grams by text and label."""
        at, known = self._places.of(hashes)
        out = np.zeros((n, len(self.labels)))
        for j in range(len(self.labels)):
            out[:, j] = np.bincount(doc, self.unknown[order, j] + np.where(known, self.gains[at, j], 0.0), n)
        return out

    def _grams(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        parts = [gram_hashes(texts, n) for n in ORDERS]
        order = np.repeat(np.arange(len(ORDERS)), [len(d) for d, _ in parts])
        return np.concatenate([d for d, _ in parts]), np.concatenate([h for _, h in parts]), order

    def scores(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Log scores and n-gram counts."""
        doc, hashes, order = self._grams(texts)
        return self._gains(doc, hashes, order, len(texts)), np.bincount(doc, minlength=len(texts)).astype(float)

    def sampled(self, texts: list[str], ids: list[int], draws: Draws) -> tuple[np.ndarray, np.ndarray]:
        """Posteriors from drawn n-grams, the mean over trials, and how many n-grams were looked at.

        A trial draws in steps and ends early once one label is sure enough. Draws are hashes of seed, document, trial
        and turn: the same however rows are dealt.
        """
        doc, hashes, order = self._grams(texts)
        by = np.argsort(doc, kind="stable")
        hashes, order = hashes[by], order[by]
        sizes = np.bincount(doc, minlength=len(texts))
        first = np.cumsum(sizes) - sizes
        some = np.flatnonzero(sizes)
        own = np.array([(ids[i] if ids[i] is not None else -1) % 2**64 for i in some], np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(draws.seed)
        mean, looked = np.zeros((len(texts), len(self.labels))), np.zeros(len(texts))
        for trial in range(draws.trials):
            score, open_ = np.zeros((len(some), len(self.labels))), np.arange(len(some))
            for step in range(0, draws.most, draws.step):
                turn = np.arange(step, min(step + draws.step, draws.most), dtype=np.uint64) + np.uint64(trial << 32)
                spread = mix(own[open_])[:, None] + turn[None, :]
                place = first[some[open_]][:, None] + (mix(spread) % sizes[some[open_]][:, None].astype(np.uint64)).astype(np.int64)
                of = np.repeat(np.arange(len(open_)), len(turn))
                score[open_] += self._gains(of, hashes[place.ravel()], order[place.ravel()], len(open_))
                looked[some[open_]] += len(turn)
                odds = np.exp(score[open_] - score[open_].max(axis=1, keepdims=True))
                open_ = open_[1 / odds.sum(axis=1) < draws.sure]
                if not len(open_):
                    break
            odds = np.exp(score - score.max(axis=1, keepdims=True))
            mean[some] += odds / odds.sum(axis=1, keepdims=True) / draws.trials
        return mean, looked


@dataclasses.dataclass(frozen=True)
class Draws:
    """How the sampled mode draws: trials, n-grams of a trial at most and in a step, and the probability that ends a trial."""

    trials: int = 7
    most: int = 1000
    step: int = 20
    sure: float = 0.99999
    seed: int = 0


def predict_profile(docs: DataFrame, profile: Profile, temper: float | None = None, text: str = "text", draws: Draws | None = None) -> DataFrame:
    """(doc_id, label, prob) in one narrow pass over a broadcast profile; a text without an n-gram has no label."""
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(profile)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = shared.value
        for whole in batches:
            for batch in pieces(whole, "t"):
                texts = [t or "" for t in batch.column("t").to_pylist()]
                if draws:
                    odds, size = p.sampled(texts, batch.column("doc_id").to_pylist(), draws)
                    best, prob = odds.argmax(axis=1), odds.max(axis=1)
                else:
                    score, size = p.scores(texts)
                    if temper:
                        score /= np.maximum(1.0, size / temper)[:, None]
                    best, prob = score.argmax(axis=1), 1 / np.exp(score - score.max(axis=1, keepdims=True)).sum(axis=1)
                none = size == 0
                labels = [None if x else p.labels[b] for b, x in zip(best, none, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(labels, pa.string()), pa.array(np.where(none, 0.0, prob))], ["doc_id", "label", "prob"])

    return docs.select("doc_id", prepared(F.col(text)).alias("t")).mapInArrow(run, "doc_id long, label string, prob double")


def identifier(profile: DataFrame, text: str = "clean", most: int = BROADCAST_ROWS):
    """docs to (doc_id, label, prob) by a staged profile: in one narrow pass if the profile is small enough, else by joins."""
    if profile.count() <= most:
        model = Profile.of(profile)
        return lambda docs: predict_profile(docs, model, text=text)
    return lambda docs: predict_profile_joined(docs, profile, text=text)


def verify(predicted: DataFrame, target: str, least: float = 0.5) -> DataFrame:
    """Documents whose top label is the target with probability `least` or more."""
    return predicted.filter((F.col("label") == target) & (F.col("prob") >= least))


def tag_variety(docs: DataFrame, second: DataFrame) -> DataFrame:
    """docs with `variety`, the second model's label: a tag, not a filter."""
    return docs.join(second.select("doc_id", F.col("label").alias("variety")), "doc_id", "left")


def cascade(first: DataFrame, second: DataFrame, least: float = 0.9) -> DataFrame:
    """The first model's answer where it is sure enough, else the second's."""
    both = first.join(second.toDF("doc_id", "label2", "prob2"), "doc_id", "left")
    unsure = (F.col("prob") < least) & F.col("label2").isNotNull()
    return both.select("doc_id", F.when(unsure, F.col("label2")).otherwise(F.col("label")).alias("label"), F.when(unsure, F.col("prob2")).otherwise(F.col("prob")).alias("prob"))


def train_linear(docs: DataFrame, label: str = "lang", text: str = "text", features: int = 1 << 14, grams: tuple[int, int] = (2, 3), words: bool = False, iterations: int = 25):
    """A multinomial linear model on hashed character n-grams, and words if asked. Returns (doc_id, label, prob) of a DataFrame."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, StringIndexer
    from pyspark.ml.functions import vector_to_array

    hashing = HashingTF(inputCol="terms", outputCol="features", numFeatures=features, binary=True)

    def vectors(df: DataFrame) -> DataFrame:
        t = prepared(F.col(text))
        terms = [char_gram_bag(t, n) for n in range(grams[0], grams[1] + 1)] + ([F.split(F.trim(t), " ")] if words else [])
        return hashing.transform(df.withColumn("terms", F.concat(*terms)))

    indexer = StringIndexer(inputCol=label, outputCol="y", stringOrderType="alphabetAsc").fit(docs)
    model = LogisticRegression(labelCol="y", maxIter=iterations, regParam=1e-3).fit(vectors(indexer.transform(docs)).select("y", "features"))
    names = F.array(*(F.lit(x) for x in indexer.labels))

    def predict(df: DataFrame) -> DataFrame:
        p = model.transform(vectors(df)).withColumn("p", vector_to_array("probability"))
        return p.select("doc_id", F.get(names, F.col("prediction").cast("int")).alias("label"), F.array_max("p").alias("prob"))

    return predict


def train_ranks(docs: DataFrame, label: str = "lang", top: int = 300, text: str = "text") -> DataFrame:
    """(label, gram, place): the most frequent n-grams of each label in order."""
    counts = gram_rows(docs, label, text=text).groupBy(F.col(label).alias("label"), "gram").agg(F.count("*").alias("c"))
    w = Window.partitionBy("label").orderBy(F.desc("c"), "gram")
    return counts.withColumn("place", F.row_number().over(w).cast("long")).filter(F.col("place") <= top).drop("c")


def predict_rank_order(docs: DataFrame, ranks: DataFrame, top: int = 300, text: str = "text") -> DataFrame:
    """(doc_id, label, distance): the least sum of rank differences; an n-gram that a label lacks counts `top`."""
    mine = gram_rows(docs, "doc_id", text=text).groupBy("doc_id", "gram").agg(F.count("*").alias("c"))
    w = Window.partitionBy("doc_id").orderBy(F.desc("c"), "gram")
    mine = mine.withColumn("mine", F.row_number().over(w).cast("long")).filter(F.col("mine") <= top).drop("c")
    sizes = mine.groupBy("doc_id").agg(F.count("*").alias("n"))
    near = mine.join(ranks, "gram").groupBy("doc_id", "label").agg(F.sum(top - F.abs(F.col("mine") - F.col("place"))).alias("saved"))
    best = near.join(sizes, "doc_id").withColumn("distance", F.col("n") * top - F.col("saved")).groupBy("doc_id").agg(F.min(F.struct("distance", "label")).alias("x"))
    return best.select("doc_id", "x.label", "x.distance")


# fixed values: frequent function words
FUNCTION_WORDS = {
    "en": ["the", "of", "and", "to", "in", "that", "is", "was", "for", "with"],
    "fr": ["le", "la", "les", "de", "des", "et", "un", "une", "dans", "que"],
    "de": ["der", "die", "das", "und", "von", "mit", "den", "ist", "nicht", "zu"],
    "es": ["el", "los", "las", "de", "que", "y", "del", "una", "por", "con"],
}


def predict_function_words(docs: DataFrame, lists: dict[str, list[str]] | None = None, text: str = "text") -> DataFrame:
    """(doc_id, label, hits): the language with most function words; ties go to the first label, no hit to none."""
    words = F.split(collapse_ws(F.lower(F.col(text))), " ")
    counted = docs.select("doc_id", words.alias("w"))
    for label, own in (lists or FUNCTION_WORDS).items():
        counted = counted.withColumn(f"n_{label}", F.size(F.filter("w", lambda x: x.isin(own))).cast("long"))  # noqa: B023  called at once
    best = F.array_min(F.array(*(F.struct((-F.col(f"n_{x}")).alias("s"), F.lit(x).alias("label")) for x in sorted(lists or FUNCTION_WORDS))))
    return counted.select("doc_id", best.alias("b")).select("doc_id", F.when(F.col("b.s") < 0, F.col("b.label")).alias("label"), (-F.col("b.s")).alias("hits"))


def test_set(docs: DataFrame, per_label: int = 40, label: str = "lang") -> DataFrame:
    """A balanced sample of odd ids by least MD5 of the id: training takes the even ids."""
    w = Window.partitionBy(label).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id")
    return docs.filter("doc_id % 2 = 1").withColumn("place", F.row_number().over(w)).filter(F.col("place") <= per_label).drop("place")


def snippet(text: Column, words: int) -> Column:
    """The first words of a text."""
    return F.concat_ws(" ", F.slice(F.split(collapse_ws(text), " "), 1, words))


def stage_profile(docs: DataFrame, **options) -> DataFrame:
    return staged(train_profile(docs, **options), "profile")
