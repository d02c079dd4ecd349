"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over word positions; a window's hash takes only the positions that count, so a substitution
at an ignored position leaves it whole. Hashes of benchmark windows meet those of training windows; each diagonal
that was hit is then compared word by word, and any window of it counts that is long enough and holds few substitutions.
The masks leave no window out: of 13 to 25 words with four fifths equal, however the others lie, each has a hit, and a
longer window splits into such lengths, one of which has four fifths equal too.

The benchmark goes to the executors in blocks of bounded bytes; every block passes over all documents, so a benchmark
of any size is searched whole. Words are runs of ASCII letters, digits and non-ASCII bytes of the lower-cased text.

Defined results: null and empty texts hold nothing; items without a word are never found; items with the same words
are one item, named by the least item_id; an item shorter than the least window is sought as a whole, with four fifths
of its words equal; of one document and item the best overlap is reported (longest, then earliest), without the
substituted words at its ends, so it may be shorter than the window that counted; repeated rows report each; empty
tables give an empty result.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.batches import Words, pieces, windows
from corpuskit.session import ship

#: 1: the position counts, 0: it is ignored.
MASKS = ("1111000010101", "11101111", "110111011", "11010001111", "1010110000111", "1100101111", "1110110101")
#: Words an overlap needs (or the whole of a shorter item), and the share of them that must be equal.
MIN_WORDS, MIN_SHARE = 13, 0.8
#: Equal words that make up for one substitution at this share.
_PER_SUBSTITUTION = 4
#: Bytes of benchmark text in one broadcast.
BLOCK_BYTES = 16_000_000
_FILTER_BITS = 20
#: Hits that are brought to their diagonals at once.
HITS = 500_000
FOUND = "doc_id long, item_id long, doc_word long, item_word long, length long, matches long"


def _positions(mask: str) -> list[int]:
    return [i for i, c in enumerate(mask) if c == "1"]


def _short_masks(n: int) -> list[list[int]]:
    """Masks over an item of n words, one of which holds no substitution as long as four fifths are equal."""
    spare = n // (_PER_SUBSTITUTION + 1)
    parts = [list(map(int, p)) for p in np.array_split(np.arange(n), spare + 2 if spare else 1)]
    return [sum(chosen, []) for chosen in itertools.combinations(parts, len(parts) - spare)]


class Seeds:
    """The hashed benchmark windows of one block."""

    def __init__(self, items: list[tuple[int, str]]):
        texts = pc.utf8_lower(pa.array([t for _, t in items], pa.large_string()))
        words = Words(texts)
        self.items, self.ids = [], []
        seen: set[bytes] = set()
        for k, (item_id, _) in enumerate(items):
            own = words.hash[words.first[k] : words.first[k + 1]]
            if len(own) and own.tobytes() not in seen:
                seen.add(own.tobytes())
                self.items.append(own)
                self.ids.append(item_id)
        short = sorted({len(x) for x in self.items if len(x) < MIN_WORDS})
        sought = [(_positions(m), None) for m in MASKS] + [(m, n) for n in short for m in _short_masks(n)]
        self.masks = [m for m, _ in sought]
        self.tables = []
        for m, only in sought:
            own = _Row(self.items, only)
            at, keys = windows(own, m)
            order = np.argsort(keys, kind="stable")
            keys, at = keys[order], at[order]
            sieve = np.zeros(1 << _FILTER_BITS, bool)
            sieve[(keys >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)] = True
            self.tables.append((keys, own.doc[at], own.place[at], sieve))

    def find(self, words: Words) -> list[tuple[int, int, int, int, int, int]]:
        """(document, item id, word in the document, word in the item, length, matches), the best for each pair."""
        met = []
        for m, (keys, item, place, sieve) in zip(self.masks, self.tables, strict=True):
            at, own = windows(words, m)
            some = np.flatnonzero(sieve[(own >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)])
            at, own = at[some], own[some]
            low, high = np.searchsorted(keys, own), np.searchsorted(keys, own, side="right")
            some = np.flatnonzero(high > low)
            upto = np.cumsum((high - low)[some])
            for part in np.split(some, np.searchsorted(upto, np.arange(HITS, upto[-1] if len(upto) else 0, HITS))):
                n = (high - low)[part]  # a word repeated in both would meet itself everywhere: few hits at once, of few diagonals
                entry = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low[part], n)
                where = np.repeat(at[part], n)
                met.append(np.unique(np.stack([words.doc[where], item[entry], where - place[entry]], axis=1), axis=0))
        best: dict[tuple[int, int], tuple] = {}
        for doc, k, diagonal in np.unique(np.concatenate(met), axis=0).tolist() if met else []:
            item = self.items[k]
            low, high = max(0, words.first[doc] - diagonal), min(len(item), words.first[doc + 1] - diagonal)
            same = item[low:high] == words.hash[diagonal + low : diagonal + high]
            s, e, hits = _longest(same, min(MIN_WORDS, len(item)))
            if hits:
                found = (e - s, -(diagonal + low + s), low + s, hits)
                best[doc, k] = max(found, best.get((doc, k), found))
        return [(doc, self.ids[k], int(-w - words.first[doc]), int(i), int(n), int(hits)) for (doc, k), (n, w, i, hits) in best.items()]


class _Row:
    """Items in a row, as windows() takes them."""

    def __init__(self, items: list[np.ndarray], only: int | None):
        chosen = [k for k, x in enumerate(items) if only is None or len(x) == only]
        lengths = [len(items[k]) for k in chosen]
        self.hash = np.concatenate([items[k] for k in chosen]) if chosen else np.zeros(0, np.uint64)
        self.doc = np.repeat(np.array(chosen, np.int64), lengths)
        self.place = np.concatenate([np.arange(n) for n in lengths]) if chosen else np.zeros(0, np.int64)


def _longest(same: np.ndarray, least: int) -> tuple[int, int, int]:
    """Start, end and matches of the longest, then earliest window of `least` words or more with enough of them equal.

    Substituted words at its ends are left off. All 0 if there is none.
    """
    sums = np.r_[0, np.cumsum(np.where(same, 1, -_PER_SUBSTITUTION))]
    most = np.maximum.accumulate(sums[::-1])[::-1]  # of all ends from here on
    length = np.searchsorted(-most, -sums, side="right") - 1 - np.arange(len(sums))
    s = int(np.argmax(length))
    inside = s + np.flatnonzero(same[s : s + length[s]])
    if length[s] < least or not len(inside):
        return 0, 0, 0
    return int(inside[0]), int(inside[-1]) + 1, len(inside)


def _blocks(benchmark: DataFrame) -> list[Broadcast]:
    spark = benchmark.sparkSession
    items = benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).filter("item_id is not null and text is not null")
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = -(-size // BLOCK_BYTES) or 1
    out = []
    for k in range(n):
        rows = items.filter(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k).orderBy("item_id", "text").collect()
        out.append(spark.sparkContext.broadcast(Seeds([(r[0], r[1]) for r in rows])))
    return out


def _search(block: Broadcast, drop: bool, names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seeds = block.value
        for whole in batches:
            for batch in pieces(whole, "text"):
                text = pc.utf8_lower(pc.fill_null(batch.column("text").cast(pa.large_string()), ""))
                found = seeds.find(Words(text))
                if drop:
                    clean = np.ones(batch.num_rows, bool)
                    clean[[x[0] for x in found]] = False
                    yield batch.filter(pa.array(clean))
                elif found:
                    doc = batch.column("doc_id").take(pa.array([x[0] for x in found], pa.int64()))
                    rest = [pa.array([x[i] for x in found], pa.int64()) for i in range(1, 6)]
                    yield pa.RecordBatch.from_arrays([doc, *rest], names)

    return run


def overlaps(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, doc_word, item_word, length, matches): benchmark passages in documents, clean documents have no row."""
    ship(docs.sparkSession)
    names = [x.split()[0] for x in FOUND.split(", ")]
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return reduce(DataFrame.union, (rows.mapInArrow(_search(b, False, names), FOUND) for b in _blocks(benchmark)))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without the documents that hold a benchmark passage."""
    ship(docs.sparkSession)
    return reduce(lambda rows, b: rows.mapInArrow(_search(b, True, []), docs.schema), _blocks(benchmark), docs)
