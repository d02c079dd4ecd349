"""Quality grades by ordinal cumulative-link regression on hashed text.

P(grade <= k) is the logistic function of threshold k less the document's score; thresholds are ordered, and all
grades share one weight for each hashed feature. Features are the presence of lower-cased words and of a text's
shape (densities of punctuation, capitals, digits, repeated neighbours, distinct words, in buckets). The grades of
rated documents are 0 toxic, 1 poor, 2 good. A document gets its expected grade and the probability of the top
grade; it is kept if that probability is a half or more.

The training sample is bounded: for each grade the `PER_GRADE` rated documents with the least hash of doc_id, of
texts of up to `SAMPLE_CHARS` characters. Every document is scored over its whole text.

Defined results: a null or empty text has the shape features alone; ratings that are null in either column don't
teach; without any rated document the expected grade and the probability are null and all are kept; repeated rows
each get a row; an empty table gives an empty result. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.llm.batches import Words, mix, pieces
from corpuskit.session import ship

BITS, GRADES = 18, 3
PER_GRADE, SAMPLE_CHARS = 4_000, 20_000
#: A feature needs so many sample documents; strength of the penalty; gradient steps.
LEAST_DOCS, PENALTY, STEPS = 8, 2e-4, 250
RESULT = "doc_id long, expected_grade double, tail_probability double, kept boolean"
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_PUNCTUATION = [i for i in range(33, 127) if not chr(i).isalnum()]


def features(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature numbers of each text in order, and where each text's begin."""
    words = Words(texts)
    n, lengths = words.n, np.diff(words.offsets)
    counts = np.diff(words.first)
    raw = pc.fill_null(texts.cast(pa.large_string()), "")
    size, begin = int(words.offsets[-1]), int(np.frombuffer(raw.buffers()[1], np.int64, 1, 8 * raw.offset)[0]) if n else 0
    data = np.frombuffer(raw.buffers()[2], np.uint8, size, begin) if size else np.zeros(0, np.uint8)
    place = np.repeat(np.arange(n), lengths)
    table = np.bincount(place * 256 + data, minlength=256 * n).reshape(n, 256)
    per = lambda x, of: np.where(x > 0, np.ceil(np.log2(1 + 1000 * x / np.maximum(of, 1))), 0).astype(np.int64)
    again = np.r_[False, (words.hash[1:] == words.hash[:-1]) & (words.doc[1:] == words.doc[:-1])] if len(words.hash) else np.zeros(0, bool)
    repeats = np.bincount(words.doc[again], minlength=n)
    own = np.unique(words.hash ^ mix(words.doc.astype(np.uint64) + np.uint64(7)), return_index=True)[1]
    distinct = np.bincount(words.doc[own], minlength=n)
    shape = [per(table[:, c], lengths) for c in _PUNCTUATION]
    shape += [per(table[:, 65:91].sum(axis=1), lengths), per(table[:, 48:58].sum(axis=1), lengths), per(repeats, counts), np.floor(10 * distinct / np.maximum(counts, 1)).astype(np.int64), np.floor(np.log2(1 + counts)).astype(np.int64)]
    kinds = np.arange(len(shape), dtype=np.uint64)[:, None]
    shaped = mix((kinds << np.uint64(32)) + np.stack(shape).astype(np.uint64) + np.uint64(0xABCD0000_00000000))
    doc = np.concatenate([words.doc, np.tile(np.arange(n), len(shape))]).astype(np.int64)
    number = np.concatenate([words.hash, shaped.ravel()]) >> np.uint64(64 - BITS)
    codes = np.sort((doc << BITS) | number.astype(np.int64))
    if len(codes):
        codes = codes[np.r_[True, codes[1:] != codes[:-1]]]
    return codes & ((1 << BITS) - 1), np.searchsorted(codes, np.arange(n + 1) << BITS)


class Ordinal:
    """Weights and ordered thresholds, fitted by full-batch adaptive gradient steps."""

    def __init__(self, numbers: np.ndarray, first: np.ndarray, grades: np.ndarray, rated: np.ndarray | None = None, steps: int = STEPS):
        """rated: how many documents have each grade in all; the sample's documents stand for so many."""
        n = len(grades)
        self.weights, self.thresholds = np.zeros(1 << BITS), np.zeros(0)
        if not n:
            return
        frequent = np.bincount(numbers, minlength=1 << BITS) >= min(LEAST_DOCS, max(1, n // 4))
        doc = np.repeat(np.arange(n), np.diff(first))
        keep = frequent[numbers]
        own, inverse = np.unique(numbers[keep], return_inverse=True)
        doc = doc[keep]
        sampled = np.maximum(np.bincount(grades, minlength=GRADES), 1)
        share = np.maximum(sampled if rated is None else rated, 1).astype(float)
        below = np.cumsum(share)[:-1] / share.sum()
        start = np.log(below / (1 - below))
        pars = np.r_[np.zeros(len(own)), start[0], np.log(np.maximum(np.diff(start), 1e-2))]
        m1, m2 = np.zeros_like(pars), np.zeros_like(pars)
        level = (share / sampled)[grades]
        level /= level.mean()
        for step in range(1, steps + 1):
            slope = self._slope(pars, own, inverse, doc, grades, level, n)
            m1 = 0.9 * m1 + 0.1 * slope
            m2 = 0.99 * m2 + 0.01 * slope**2
            pars -= 0.05 * (1 - step / (steps + 1)) * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.99**step)) + 1e-8)
        self.weights[own] = pars[: len(own)]
        self.thresholds = np.cumsum(np.r_[pars[len(own)], np.exp(pars[len(own) + 1 :])])

    @staticmethod
    def _slope(pars, own, inverse, doc, grades, level, n):
        weights, base, gaps = pars[: len(own)], pars[len(own)], np.exp(pars[len(own) + 1 :])
        cuts = np.r_[-np.inf, np.cumsum(np.r_[base, gaps]), np.inf]
        score = np.bincount(doc, weights[inverse], n)
        high, low = _logistic(cuts[grades + 1] - score), _logistic(cuts[grades] - score)
        inner = np.maximum(high - low, 1e-12)
        d_high, d_low = level * high * (1 - high) / inner / n, level * low * (1 - low) / inner / n
        of_score = d_high - d_low  # of the loss
        out = np.empty_like(pars)
        out[: len(own)] = np.bincount(inverse, of_score[doc], len(own)) + PENALTY * weights
        of_cut = np.bincount(grades + 1, -d_high, GRADES + 1) + np.bincount(grades, d_low, GRADES + 1)
        inner_cuts = of_cut[1:GRADES]
        out[len(own)] = inner_cuts.sum()
        out[len(own) + 1 :] = np.cumsum(inner_cuts[::-1])[::-1][1:] * gaps
        return out

    def judge(self, numbers: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Expected grade and probability of the top grade."""
        n = len(first) - 1
        score = np.bincount(np.repeat(np.arange(n), np.diff(first)), self.weights[numbers], n)
        above = 1 - _logistic(self.thresholds[None, :] - score[:, None])
        return np.round(above.sum(axis=1), 6), np.round(above[:, -1], 6)


def _logistic(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -500, 500)))


def _sample_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in pieces(whole, "text"):
            numbers, first = features(batch.column("text"))
            rows = [numbers[s:e].astype("<i4").tobytes() for s, e in zip(first[:-1], first[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("grade"), batch.column("turn"), batch.column("doc_id"), pa.array(rows, pa.binary())], ["grade", "turn", "doc_id", "numbers"])


def fit(docs: DataFrame, labels: DataFrame, per_grade: int = PER_GRADE) -> Ordinal:
    """labels(doc_id, quality, toxic), each 0 or 1."""
    ship(docs.sparkSession)
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 0, 1).otherwise(2).cast("int")
    rated = labels.filter("doc_id is not null and quality is not null and toxic is not null").select(F.col("doc_id").cast("long"), grade.alias("grade"), F.xxhash64("doc_id").alias("turn"))
    of_grade = dict(rated.groupBy("grade").count().collect())
    order = Window.partitionBy("grade").orderBy("turn", "doc_id")
    # PER_GRADE rows for each of three grades at most
    chosen = rated.distinct().withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= per_grade).drop("rank")
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).filter(F.char_length("text") <= SAMPLE_CHARS)
    rows = texts.join(F.broadcast(chosen), "doc_id").mapInArrow(_sample_batches, "grade int, turn long, doc_id long, numbers binary").toArrow()
    rows = rows.sort_by([("turn", "ascending"), ("doc_id", "ascending"), ("grade", "ascending"), ("numbers", "ascending")])
    lists = [np.frombuffer(x, "<i4") for x in rows.column("numbers").to_pylist()]
    first = np.r_[0, np.cumsum([len(x) for x in lists])].astype(np.int64)
    numbers = np.concatenate(lists).astype(np.int64) if lists else np.zeros(0, np.int64)
    counts = np.array([of_grade.get(g, 0) for g in range(GRADES)])
    return Ordinal(numbers, first, rows.column("grade").to_numpy().astype(np.int64), counts)


def _judge_batches(model: Broadcast):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in pieces(whole, "text"):
                if not len(model.value.thresholds):
                    none = pa.nulls(batch.num_rows, pa.float64())
                    columns = [none, none, pa.array(np.ones(batch.num_rows, bool))]
                else:
                    grade, tail = model.value.judge(*features(batch.column("text")))
                    columns = [pa.array(grade), pa.array(tail), pa.array(tail >= 0.5)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *columns], ["doc_id", "expected_grade", "tail_probability", "kept"])

    return run


def grade(docs: DataFrame, labels: DataFrame, model: Ordinal | None = None) -> DataFrame:
    """(doc_id, expected_grade, tail_probability, kept) for every row of docs(doc_id, text)."""
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model or fit(docs, labels))
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return rows.mapInArrow(_judge_batches(shared), RESULT)
