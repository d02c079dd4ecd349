"""Quality rules by tokeniser fertility.

Every word is encoded by a public vocabulary with byte fallback. A document gets its characters per token, the share
of its tokens that are byte pieces, and the entropy of its tokens. Bands for each language come from the exact
quartiles of these figures over all documents that pass the base rules: a document is rejected where a figure lies
beyond the fences. Entropy grows with length, so its bands are those of a language and a length class (powers of two).

Defined results: a null or empty text has no word and fails the base rules; a null language is `und`; a language with
fewer than `MIN_GROUP` documents takes the bands of all documents, and a length class of a language that of all
languages; where these are too few as well there is no band; repeated rows each count; no rows, no result.
"""

from __future__ import annotations

import itertools
import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from corpuskit.llm.batches import mix, pieces
from corpuskit.llm.vocab import fertility_model, vocab_path
from corpuskit.session import ship, staged

WINDOW, MIN_WORDS, MOST_REPEATED = 8, 20, 30
#: Fences lie this many interquartile ranges out; a range counts as the least width at least.
FENCE = 2.0
LEAST_WIDTH = {"chars_per_token": 0.2, "byte_share": 0.02, "entropy": 0.25}
MIN_GROUP = 50
#: Bands that are broadcast at most; more are joined by a shuffle.
BROADCAST_BANDS = 100_000
_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_WHITE, _SYMBOLS = " \t\n\v\f\r", "#*$%&|<>"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_tokens", "n_byte_tokens"]
FIGURES = ", ".join(f"{c} long" for c in COUNTS) + ", entropy double"


def _repeated(numbers: np.ndarray, first: np.ndarray) -> np.ndarray:
    """For each text, how many of its words stand in a window of eight words that the text holds twice or more."""
    docs = len(first) - 1
    out, n = np.zeros(docs, np.int64), len(numbers)
    if n < 2 * WINDOW - 7:
        return out
    doc = np.repeat(np.arange(docs), np.diff(first))
    m = n - WINDOW + 1
    spread = mix(numbers.astype(np.uint64) + np.uint64(1))
    total = mix(doc[:m].astype(np.uint64) + np.uint64(0x5851F42D4C957F2D))
    for j in range(WINDOW):
        total = total * np.uint64(0x9E3779B97F4A7C15) + spread[j : j + m]
    at = np.flatnonzero(doc[:m] == doc[WINDOW - 1 :])
    keys = mix(total[at])
    order = np.sort(keys)
    twice = order[1:][order[1:] == order[:-1]]
    if len(twice):
        begin = at[np.isin(keys, twice)]
        change = np.bincount(begin, minlength=n + 1) - np.bincount(begin + WINDOW, minlength=n + 1)
        out += np.bincount(doc[np.cumsum(change)[:n] > 0], minlength=docs)
    return out


def _entropy(ids: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Shannon entropy in bits of each text's tokens; counts: tokens of each text, in a row in ids."""
    doc = np.repeat(np.arange(len(counts), dtype=np.int64), counts)
    keys = np.sort((doc << 32) | ids)
    edge = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
    times = np.diff(np.r_[edge, len(keys)])
    part = np.bincount(keys[edge] >> 32, times * np.log2(times), len(counts)) if len(keys) else np.zeros(len(counts))
    n = np.maximum(counts, 1)
    return np.round(np.maximum(np.log2(n) - part / n, 0), 6)


def _measure(path: str, names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with fertility_model(path) as model:
            for whole in batches:
                for batch in pieces(whole, "text"):
                    texts = [x or "" for x in batch.column("text").to_pylist()]
                    words = [_WORD.findall(x) for x in texts]
                    n_words = np.fromiter(map(len, words), np.int64, len(words))
                    first = np.r_[0, np.cumsum(n_words)]
                    numbers = model.numbers(words)
                    ids = model.ids_of(numbers)
                    length = model.at[numbers + 1] - model.at[numbers]
                    upto = np.r_[0, np.cumsum(length)][first]
                    fallback = np.r_[0, np.cumsum(model.is_byte[ids])]
                    tokens = np.diff(upto)
                    lines = [[x for x in t.split("\n") if x.strip(_WHITE)] for t in texts]
                    figures = [
                        n_words,
                        [len(t) - sum(map(t.count, _WHITE)) for t in texts],
                        [sum(map(t.count, _SYMBOLS)) for t in texts],
                        [len(x) - len(set(x)) for x in lines],
                        _repeated(numbers, first),
                        tokens,
                        np.diff(fallback[upto]),
                    ]
                    columns = [batch.column(c) for c in names]
                    columns += [pa.array(x, pa.int64()) for x in figures] + [pa.array(_entropy(ids, tokens), pa.float64())]
                    yield pa.RecordBatch.from_arrays(columns, [*names, *COUNTS, "entropy"])

    return run


def measure(docs: DataFrame, keep: list[str], vocab: str | None = None) -> DataFrame:
    """The columns `keep` of docs and the figures of each text."""
    ship(docs.sparkSession)
    path = vocab_path("piece_bpe_32k.model", vocab)
    names = list(dict.fromkeys([*keep, "text"]))
    schema = StructType([*docs.select(*keep).schema.fields, *StructType.fromDDL(FIGURES).fields])
    return docs.select(*names).mapInArrow(_measure(path, keep), schema)


def _with_base(figures: DataFrame) -> DataFrame:
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * F.col("n_words"))
    tokens = F.greatest("n_tokens", F.lit(1))
    return figures.withColumns(
        {
            "base_failed": failed,
            "band": F.coalesce("lang", F.lit("und")),
            "length_class": F.floor(F.log2(tokens)).cast("int"),
            "chars_per_token": F.round(F.col("word_chars") / tokens, 3),
            "byte_share": F.round(F.col("n_byte_tokens") / tokens, 3),
        }
    )


def _fences(rows: DataFrame, by: list[str], figures: list[str], mark: str) -> DataFrame:
    """Lower and upper fences of each group that has enough documents, named after figure and mark.

    The figures are rounded, so a group's state is the counts of a few thousand values.
    """
    rows = rows.withColumns({c: F.round(c, 3) for c in figures})
    some = rows.groupBy(*by).agg(F.count("*").alias("n"), *(F.percentile(c, [0.25, 0.75]).alias(c) for c in figures)).filter(F.col("n") >= MIN_GROUP)
    out = []
    for c in figures:
        width = FENCE * F.greatest(F.col(c)[1] - F.col(c)[0], F.lit(LEAST_WIDTH[c]))
        out += [(F.col(c)[0] - width).alias(f"{c}_low{mark}"), (F.col(c)[1] + width).alias(f"{c}_high{mark}")]
    return some.select(*by, *out)


def _small(fences: DataFrame) -> DataFrame:
    """Fences to join with: broadcast if they are few, so that rows with their texts stay where they are."""
    fences = staged(fences, "fences")
    return F.broadcast(fences) if fences.count() <= BROADCAST_BANDS else fences


def judge(figures: DataFrame) -> DataFrame:
    """figures (read more than once) with base_failed, kept, and which band each rejected one is beyond."""
    rows = _with_base(figures)
    slim = _with_base(figures.select("lang", *COUNTS, "entropy")).filter("not base_failed")
    own, every = ["chars_per_token", "byte_share"], F.lit(0).alias("every")
    judged = rows.withColumn("every", F.lit(0))
    for by, of, mark in ((["band"], own, ""), (["every"], own, "_all"), (["band", "length_class"], ["entropy"], ""), (["length_class"], ["entropy"], "_all")):
        judged = judged.join(_small(_fences(slim.select("*", every), by, of, mark)), by, "left")
    beyond = {}
    for c in LEAST_WIDTH:
        low, high = (F.coalesce(f"{c}_{side}", f"{c}_{side}_all") for side in ("low", "high"))
        beyond[f"beyond_{c}"] = ~F.col("base_failed") & ~F.coalesce(F.col(c).between(low, high), F.lit(True))
    marked = judged.withColumns(beyond)
    return marked.withColumn("kept", ~reduce(Column.__or__, (F.col(c) for c in beyond), F.col("base_failed")))


def quality(docs: DataFrame, vocab: str | None = None) -> DataFrame:
    """One row for each document: the base counts, the fertility figures and the verdict."""
    figures = staged(measure(docs, ["doc_id", "lang"], vocab), "fertility")
    return judge(figures).select(
        "doc_id", *(F.col(c) for c in COUNTS[:5]), "base_failed", "kept", "n_tokens", "chars_per_token", "byte_share", "entropy"
    )


def keep_good(docs: DataFrame, vocab: str | None = None) -> DataFrame:
    """docs without the rejected rows; the rows are measured once and wait in the shared folder for the bands."""
    inner = {c: c if c in ("text", "lang") else f"in_{i}" for i, c in enumerate(docs.columns)}  # no name of ours begins so
    plain = docs.select(*(F.col(f"`{c.replace('`', '``')}`").alias(n) for c, n in inner.items()))
    rows = staged(measure(plain, plain.columns, vocab), "measured")
    return judge(rows).filter("kept").select(*(F.col(n).alias(c) for c, n in inner.items()))


def words_of(text: str | None) -> list[str]:
    return _WORD.findall(text or "")


def token_lists(texts: list[str | None], vocab: str | None = None) -> list[list[int]]:
    """The tokens that are counted, for tests: those of each word in a row."""
    model = fertility_model(vocab_path("piece_bpe_32k.model", vocab)).model
    return [list(itertools.chain.from_iterable(model.encode(words_of(t)))) if words_of(t) else [] for t in texts]
