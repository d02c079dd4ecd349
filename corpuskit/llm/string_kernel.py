"""Language identification by string kernels.

The blended-spectrum presence kernel of two texts is the number of distinct letter n-grams (n = 1, 2, 3) that both
hold, over the root of the product of what each holds. Landmark texts give the Nyström features; one kernel ridge
regression for each language, one against the rest, is solved on them. Scoring is two matrix products for a batch:
which landmark n-grams the texts hold, times which the landmarks hold, times the solved weights.

Texts are lower-cased; a run of anything but letters is one boundary. The training sample is bounded: for each
language the `PER_LANGUAGE` eligible documents with the least hash of doc_id, of texts of up to `SAMPLE_CHARS`
characters, and `MOST_SAMPLE` over all languages. Every document is scored over its whole text.

Defined results: a null text, or one without a letter, is `und` with score 0; of equal scores the first language in
order wins; documents without lang or without a letter don't teach; if nothing teaches, every text is `und`; held_out
is false where doc_id is null; repeated rows each get a row; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.llm.batches import pieces
from corpuskit.session import ship

PER_LANGUAGE, LANDMARKS, SAMPLE_CHARS, RIDGE = 400, 32, 20_000, 1e-3
#: Steepness of the scores' softmax.
STEEP = 6.0
RESULT = "doc_id long, held_out boolean, lang_pred string, score double"

#: Texts whose n-grams are told apart by 16 bits of a code.
AT_ONCE = 1 << 16
#: Sample texts and landmarks over all languages at most; many languages share them evenly.
MOST_SAMPLE, MOST_LANDMARKS = 40_000, 2_048
#: Of each language, so many times the sample's size is drawn by hash before it is ranked.
DRAWN = 8

_LETTER = np.fromiter((chr(i).isalpha() for i in range(65536)), bool, 65536)


def grams(texts: list[str], at_once: int = AT_ONCE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct n-grams of each text as codes in order, where each text's begin, and which texts hold a letter.

    A code holds three 16-bit letters, 0 for a boundary. Letters beyond the basic plane share the numbers of its private
    area, which holds no letter.
    """
    parts = [_grams(texts[s : s + at_once]) for s in range(0, len(texts), at_once)] or [_grams([])]
    if len(parts) == 1:
        return parts[0]
    begins = np.cumsum([0, *(len(codes) for codes, _, _ in parts)])
    first = [f[:-1] + b for (_, f, _), b in zip(parts, begins, strict=False)]
    return np.concatenate([c for c, _, _ in parts]), np.r_[(*first, begins[-1:])], np.concatenate([x for _, _, x in parts])


def _grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4")
    doc = np.repeat(np.arange(len(texts), dtype=np.uint64), lengths)
    code = points.astype(np.uint64) & np.uint64(0xFFFF)
    letter = _LETTER[code.astype(np.int64)]
    if len(points) and points.max() > 0xFFFF:
        high = np.flatnonzero(points > 0xFFFF)
        letter[high] = [chr(x).isalpha() for x in points[high].tolist()]
        code[high] = np.uint64(0xE000) + points[high].astype(np.uint64) % np.uint64(0x1900)
    code[~letter] = 0
    keep = np.ones(len(code), bool)
    keep[1:] = (code[1:] != 0) | (code[:-1] != 0) | (doc[1:] != doc[:-1])
    code, doc = code[keep], doc[keep]
    s16, s32, s48 = np.uint64(16), np.uint64(32), np.uint64(48)
    one = (np.uint64(0xFFFFFFFE0000) | code) | (doc << s48)
    parts = [one[code != 0]]
    if len(code) > 1:
        both = (np.uint64(0xFFFF00000000) | (code[:-1] << s16) | code[1:]) | (doc[1:] << s48)
        parts.append(both[doc[1:] == doc[:-1]])
    if len(code) > 2:
        three = ((code[:-2] << s32) | (code[1:-1] << s16) | code[2:]) | (doc[2:] << s48)
        parts.append(three[doc[2:] == doc[:-2]])
    found = np.sort(np.concatenate(parts))
    if len(found):
        found = found[np.r_[True, found[1:] != found[:-1]]]
    first = np.searchsorted(found, np.arange(len(texts) + 1, dtype=np.uint64) << s48)
    first[-1] = len(found)
    lettered = np.bincount(doc[code != 0].astype(np.int64), minlength=len(texts)) > 0
    return found & np.uint64(0xFFFFFFFFFFFF), first, lettered


class Model:
    """Fitted landmarks and weights."""

    def __init__(self, texts: list[str], langs: list[str], landmarks: int = LANDMARKS, ridge: float = RIDGE):
        codes, first, lettered = grams(texts)
        self.langs = sorted({lang for lang, x in zip(langs, lettered, strict=True) if x})  # a text without a letter doesn't teach
        if not self.langs:
            return
        landmarks = max(1, min(landmarks, MOST_LANDMARKS // len(self.langs)))
        rank: dict[str, int] = {}
        chosen = []
        for k, lang in enumerate(langs):  # texts come in order of their hash
            if rank.setdefault(lang, 0) < landmarks and first[k + 1] > first[k]:
                rank[lang] += 1
                chosen.append(k)
        self.codes = np.unique(np.concatenate([codes[first[k] : first[k + 1]] for k in chosen]))
        self.held = np.zeros((len(self.codes), len(chosen)), np.float32)
        for j, k in enumerate(chosen):
            self.held[np.searchsorted(self.codes, codes[first[k] : first[k + 1]]), j] = 1
        self.root = np.sqrt(self.held.sum(axis=0))
        self.weights = np.eye(len(chosen), dtype=np.float64)
        kernel = self._kernel(codes, first)
        among = kernel[chosen]
        aims = np.where(np.array(langs)[:, None] == np.array(self.langs)[None, :], 1.0, -1.0)
        n = int(lettered.sum())
        left = kernel.T @ kernel / n + ridge * among + 1e-9 * np.eye(len(chosen))
        self.weights = np.linalg.solve(left, kernel[lettered].T @ aims[lettered] / n)

    def _kernel(self, codes: np.ndarray, first: np.ndarray) -> np.ndarray:
        n = len(first) - 1
        sizes = np.diff(first)
        out = np.empty((n, len(self.root)))
        doc = np.repeat(np.arange(n), sizes)
        place = np.minimum(np.searchsorted(self.codes, codes), len(self.codes) - 1)
        met = self.codes[place] == codes
        doc, place = doc[met], place[met]
        for s in range(0, n, 256):
            e = min(n, s + 256)
            i, j = np.searchsorted(doc, [s, e])
            present = np.zeros((e - s, len(self.codes)), np.float32)
            present[doc[i:j] - s, place[i:j]] = 1
            out[s:e] = present @ self.held
        return out / (np.sqrt(np.maximum(sizes, 1))[:, None] * self.root[None, :])

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        codes, first, lettered = grams(texts)
        if not self.langs:
            return ["und"] * len(texts), np.zeros(len(texts))
        values = STEEP * (self._kernel(codes, first) @ self.weights)
        best = values.argmax(axis=1)
        odds = np.exp(values - values.max(axis=1, keepdims=True))
        score = np.where(lettered, 1 / odds.sum(axis=1), 0.0)
        return [self.langs[b] if x else "und" for b, x in zip(best, lettered, strict=True)], score


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")) % 5 == 0, F.lit(False))


def sample(docs: DataFrame, per_language: int = PER_LANGUAGE, chars: int = SAMPLE_CHARS) -> DataFrame:
    """(lang, text, turn, doc_id): the bounded training sample."""
    fit = docs.filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    slim = fit.filter(F.char_length("text") <= chars).select("lang", "doc_id", F.xxhash64("doc_id").alias("turn"))
    counts = slim.groupBy("lang").agg(F.count("*").alias("n"))
    shares = counts.crossJoin(F.broadcast(counts.agg(F.count("*").alias("langs"))))
    per = F.greatest(F.lit(1), F.least(F.lit(per_language), F.floor(MOST_SAMPLE / F.col("langs"))))
    # a row for each language; the draw leaves DRAWN times the sample, so that no task ranks a whole language
    drawn = slim.join(F.broadcast(shares.select("lang", per.alias("per"), (DRAWN * per / F.col("n")).alias("share"))), "lang")
    drawn = drawn.filter((F.col("turn") / float(1 << 64) + 0.5) <= F.col("share")).select("lang", "doc_id", "turn", "per").distinct()
    order = Window.partitionBy("lang").orderBy("turn", "doc_id")
    chosen = drawn.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= F.col("per")).drop("rank", "per")
    # MOST_SAMPLE rows at most, or one for each language
    return fit.join(F.broadcast(chosen), ["lang", "doc_id"]).select("lang", "text", "turn", "doc_id")


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE, landmarks: int = LANDMARKS, ridge: float = RIDGE) -> Model:
    rows = sample(docs, per_language).orderBy("turn", "doc_id", "text").collect()
    return Model([r["text"].lower() for r in rows], [r["lang"] for r in rows], landmarks, ridge)


def _predict(model: Broadcast):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in pieces(whole, "text"):
                texts = pc.utf8_lower(pc.fill_null(batch.column("text").cast(pa.large_string()), "")).to_pylist()
                langs, scores = model.value.predict(texts)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id"), batch.column("held_out"), pa.array(langs, pa.string()), pa.array(scores)], ["doc_id", "held_out", "lang_pred", "score"]
                )

    return run


def identify(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row of docs(doc_id, text, lang); lang is read by the fit alone."""
    spark = docs.sparkSession
    ship(spark)
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.col("lang").cast("string"))
    shared = spark.sparkContext.broadcast(model or fit(docs))
    rows = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text")
    return rows.mapInArrow(_predict(shared), RESULT)
