"""Links between documents whose sets of five-word shingles have a Jaccard similarity of 0.8 or more.

A fingerprint has `POSITIONS` byte positions, each filled from the least value that one hash function takes on the set,
so two sets agree at a position about as often as they are similar. The index posts a set under groups of `ROWS` whole
minima. Pairs that meet in a posting list tally their equal positional bytes; those below `SAME` go, the rest is
verified on whole sets. Of the pairs at similarity 0.8, one in 30,000 meets in no list and one in 100,000 tallies too
little; above it both vanish quickly.

Only links that connect are sought. Each member of a list is first compared with the least of it, so a list of near
copies costs its length. What that leaves in different components is compared pair by pair inside the tasks, over blocks
of the list, and only pairs that tally enough leave a task. Where these would be many for each member, as in a family of
texts somewhat less alike, the list's whole sets are brought together instead, and only links between what is not yet
connected leave the task.

Documents of equal sets are one node, so exact copies make no pairs. Words are runs of anything but ASCII white space,
A-Z folded. A text of fewer than five words is one shingle; texts without a word are one node without links.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.batches import Words, mix, pieces, windows
from corpuskit.llm.sieve import sieve, slot_of, slots_in
from corpuskit.llm.vocab import forget_words
from corpuskit.operators.components import connected
from corpuskit.operators.neardup import compared
from corpuskit.operators.relational import sized_join
from corpuskit.session import settle, ship, staged

SHINGLE, LEAST = 5, 0.8
POSITIONS, ROWS, SAME = 80, 4, 48
#: Members of a list compared in one unit; a longer list is cut into blocks and every pair of blocks is a unit.
BLOCK = 2048
#: Pairs for each member of a unit beyond which its list is compared on whole sets in the task.
DENSE = 8
_DRAWN = np.random.Generator(np.random.PCG64(20260101)).integers(0, 2**64, (2, POSITIONS), dtype=np.uint64, endpoint=False)
_TIMES, _PLUS = _DRAWN[0] | np.uint64(1), _DRAWN[1]


def shingle_sets(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(document index, shingle hash) of every distinct shingle, in this order."""
    words = Words(texts, plain=False)
    sizes = np.diff(words.first)
    docs, keys = [], []
    for k in range(1, SHINGLE + 1):
        if k == SHINGLE or (sizes == k).any():
            at, key = windows(words, list(range(k)))
            doc = words.doc[at]
            some = sizes[doc] == k if k < SHINGLE else slice(None)
            docs.append(doc[some])
            keys.append(key[some])
    doc, key = np.concatenate(docs), np.concatenate(keys)
    order = np.lexsort((key, doc))
    doc, key = doc[order], key[order]
    first = np.ones(len(doc), bool)
    first[1:] = (doc[1:] != doc[:-1]) | (key[1:] != key[:-1])
    return doc[first], key[first]


def _nodes(counts: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """One number for each set: equal for equal sets."""
    sums = np.zeros(len(counts), np.uint64)
    some = np.flatnonzero(counts)
    if len(some):
        sums[some] = np.add.reduceat(mix(keys), (np.cumsum(counts) - counts)[some])
    return mix(sums + counts.astype(np.uint64)).view(np.int64)


def minima(counts: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """The least value of each hash function on each set; counts: sizes of the sets, in a row in keys, none empty."""
    starts = np.cumsum(counts) - counts
    out = np.empty((len(counts), POSITIONS), np.uint64)
    for i in range(POSITIONS):
        out[:, i] = np.minimum.reduceat(keys * _TIMES[i] + _PLUS[i], starts)
    return out


def marks_and_keys(least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The positional bytes of each set, and the lists it is posted in."""
    mixed = mix(least)
    lists = [mix(mixed[:, i : i + ROWS] @ _TIMES[:ROWS] + np.uint64(i)) for i in range(0, POSITIONS, ROWS)]
    return (mixed >> np.uint64(56)).astype(np.uint8), np.stack(lists, axis=1)


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    forget_words()
    for whole in batches:
        for batch in pieces(whole, "text"):
            doc, key = shingle_sets(batch.column("text"))
            yield batch, key, np.bincount(doc, minlength=batch.num_rows)


def _print_batches(fingerprint: Callable[[pa.Array], np.ndarray] | None):
    """(doc_id, node, marks, lists, print) of every text; one without a word has neither marks nor lists."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, key, counts in _texts(batches):
            some = np.flatnonzero(counts)
            marks, lists = marks_and_keys(minima(counts[some], key))
            has = counts > 0
            every = pa.array(np.where(has, np.cumsum(has) - 1, 0), mask=~has)
            packed = pa.array([m.tobytes() for m in marks], pa.binary()).take(every)
            posted = pa.ListArray.from_arrays(pa.array(np.arange(len(some) + 1, dtype=np.int32) * lists.shape[1]), pa.array(lists.ravel().view(np.int64))).take(every)
            prints = pa.array(fingerprint(batch.column("text"))) if fingerprint else pa.nulls(batch.num_rows, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(_nodes(counts, key)), packed, posted, prints], ["doc_id", "node", "marks", "lists", "print"])

    return run


def _set_batches(wanted: Broadcast):
    """(node, doc_id, hashes) of the texts that the sieve may hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch, key, counts in _texts(iter([whole.filter(pa.array(slots_in(wanted.value, whole.column("slot"))))])):
                lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(counts)].astype(np.int32)), pa.array(key.view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(_nodes(counts, key)), batch.column("doc_id"), lists], ["node", "doc_id", "hashes"])

    return run


def _tally_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, POSITIONS) for c in ("x", "y"))
        yield batch.select(["a", "b"]).filter(pa.array((x == y).sum(axis=1) >= SAME))


def across(node: np.ndarray, part: np.ndarray, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of nodes of different parts whose positional bytes tally enough."""
    parts, number, n = np.unique(part, return_inverse=True, return_counts=True)
    a, b = [], []
    few = np.flatnonzero(number != n.argmax())  # the largest part needs no comparison among itself
    columns = np.ascontiguousarray(marks.T)
    for s in range(0, len(few), 256):
        own = few[s : s + 256]
        tally = np.zeros((len(own), len(node)), np.uint8)
        for row in columns:
            tally += row[own, None] == row[None, :]
        i, j = np.nonzero(tally >= SAME)
        i = own[i]
        other = part[i] != part[j]
        a.append(np.minimum(node[i[other]], node[j[other]]))
        b.append(np.maximum(node[i[other]], node[j[other]]))
    pairs = np.unique(np.stack([np.concatenate(a), np.concatenate(b)], axis=1), axis=0) if a else np.zeros((0, 2), np.int64)
    return pairs[:, 0], pairs[:, 1]


def _across_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(a, b, list): pairs, or for a list with too many of them a row without a pair."""
    for batch in batches:
        for key, row in zip(batch.column("list").to_pylist(), batch.column("members"), strict=True):
            own = row.values
            node, part = (own.field(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            marks = np.frombuffer(b"".join(own.field(2).to_pylist()), np.uint8).reshape(-1, POSITIONS)
            a, b = across(node, part, marks)
            if len(a) > DENSE * len(node):
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([key])], ["a", "b", "list"])
            else:
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array([key] * len(a), pa.int64())], ["a", "b", "list"])


def connecting(node: np.ndarray, part: np.ndarray, sizes: np.ndarray, keys: np.ndarray) -> list[tuple[int, int]]:
    """Links at the least similarity that connect parts, from whole sets; sizes: of the sets, in a row in keys."""
    _, place = np.unique(keys, return_inverse=True)
    starts = np.cumsum(sizes) - sizes
    label, held, out = np.unique(part, return_inverse=True)[1], np.zeros(len(place) + 1, bool), []
    for x in range(len(node) - 1):
        own = place[starts[x] : starts[x] + sizes[x]]
        held[own] = True
        rest = np.arange(x + 1, len(node))
        near = rest[(label[rest] != label[x]) & (np.minimum(sizes[rest], sizes[x]) >= LEAST * np.maximum(sizes[rest], sizes[x]))]
        if len(near):
            upto = np.cumsum(sizes[near])
            at = np.arange(upto[-1]) + np.repeat(starts[near] - (upto - sizes[near]), sizes[near])
            common = np.add.reduceat(held[place[at]].astype(np.int64), upto - sizes[near])
            for y in near[common / (sizes[x] + sizes[near] - common) >= LEAST].tolist():
                if label[y] != label[x]:
                    out.append((int(node[x]), int(node[y])))
                    label[label == label[y]] = label[x]
        held[own] = False
    return out


def _connecting_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = []
        for row in batch.column("members"):
            own = row.values
            node, part = (own.field(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            lists = own.field(2)
            found += connecting(node, part, np.asarray(lists.value_lengths(), np.int64), lists.flatten().to_numpy(zero_copy_only=False))
        yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in (0, 1)], ["a", "b"])


class Resemblance:
    """The index over docs(doc_id, text). rows: (doc_id, node) of every row; links(): (a, b), which connect like nodes.

    fingerprint: of texts, a number that prints has for every row beside the index's own."""

    def __init__(self, docs: DataFrame, block: int = BLOCK, fingerprint: Callable[[pa.Array], np.ndarray] | None = None):
        ship(docs.sparkSession)
        self.docs, self.block = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), block
        self.prints = staged(self.docs.mapInArrow(_print_batches(fingerprint), "doc_id long, node long, marks binary, lists array<long>, print long"), "prints")
        self.rows = self.prints.select("doc_id", "node")

    def _marks(self, nodes: DataFrame) -> DataFrame:
        """(node, marks), once for each of nodes(node)."""
        return self.prints.select("node", "marks").join(nodes, "node", "left_semi").dropDuplicates(["node"])

    def _sets(self, nodes: DataFrame) -> DataFrame:
        """(doc_id, hashes), staged: the set of each of nodes(node), under the node's number."""
        # one document stands for each node
        chosen = self.rows.join(nodes, "node", "left_semi").groupBy("node").agg(F.min(F.struct(F.col("doc_id").alias("doc_id"))).alias("x")).select("node", "x.doc_id")
        chosen = staged(chosen, "chosen")
        wanted = sieve(chosen.select(slot_of("doc_id").alias("slot")))
        sets = self.docs.withColumn("slot", slot_of("doc_id")).mapInArrow(_set_batches(wanted), "node long, doc_id long, hashes array<long>")
        same = sets["node"].eqNullSafe(chosen["node"]) & sets["doc_id"].eqNullSafe(chosen["doc_id"])
        return staged(sets.join(chosen, same, "left_semi").select(F.col("node").alias("doc_id"), "hashes"), "sets")

    def verified(self, pairs: DataFrame) -> DataFrame:
        """The pairs, staged, at the least similarity."""
        sets = self._sets(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct())
        return compared(pairs, sets).filter(F.col("jaccard") >= LEAST).select("a", "b")

    def links(self) -> DataFrame:
        posted = self.prints.select("node", F.explode("lists").alias("list")).distinct()
        # nodes are hashes, so the least is any; a group of near copies has the same in most of its lists
        drawn = staged(posted.groupBy("list").agg(F.min("node").alias("drawn"), F.count("*").alias("n")).filter("n > 1"), "drawn")
        met = staged(sized_join(posted, drawn, "list"), "met")  # the lists with two members or more
        stars = met.filter("node != drawn").select(F.col("drawn").alias("a"), F.col("node").alias("b")).distinct()
        marks = staged(self._marks(met.select("node").distinct()), "marks")
        stars = staged(stars, "stars")
        mine = stars.join(marks.toDF("b", "y"), "b")
        both = sized_join(mine, marks.toDF("a", "x"), "a", sizes=stars.groupBy("a").agg(F.count("*").alias("n")))
        first = staged(self.verified(staged(both.mapInArrow(_tally_batches, "a long, b long"), "tallied")), "links")
        settle(self.docs.sparkSession)
        return first.unionByName(self._across(met, marks, first))

    def _across(self, met: DataFrame, marks: DataFrame, found: DataFrame) -> DataFrame:
        """Links in lists whose members are not yet in one component."""
        part = connected(found)
        named = met.select("node", "list").join(part, "node", "left").select("list", "node", F.coalesce("root", "node").alias("part"))
        named = staged(named, "parts")
        mixed = named.groupBy("list").agg(F.count("*").alias("n"), F.min("part").alias("low"), F.max("part").alias("high")).filter("low != high").select("list", "n")
        mixed = staged(mixed.withColumn("members", F.col("n")), "mixed")
        opened = sized_join(named, mixed, "list")
        pairs = staged(self._units(opened.join(marks, "node"), "marks").mapInArrow(_across_batches, "a long, b long, list long"), "across")
        sparse = self.verified(staged(pairs.filter("a is not null").select("a", "b").distinct(), "across-pairs"))
        dense = pairs.filter("a is null").select("list").distinct()
        if dense.isEmpty():
            return sparse
        crowded = staged(opened.join(dense, "list", "left_semi"), "crowded")
        sets = self._sets(crowded.select("node").distinct()).withColumnRenamed("doc_id", "node")
        return sparse.unionByName(self._units(crowded.join(sets, "node"), "hashes").mapInArrow(_connecting_batches, "a long, b long"))

    def _units(self, members: DataFrame, what: str) -> DataFrame:
        """(list, members): what is compared in one go, a whole list or two blocks of a long one."""
        blocks = F.ceil(F.col("members") / self.block).cast("int")
        dealt = members.select("list", "node", "part", what, blocks.alias("blocks"), F.pmod(F.xxhash64("node"), blocks).cast("int").alias("own"))
        units = dealt.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
        return units.groupBy("list", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j")).agg(F.collect_list(F.struct("node", "part", what)).alias("members")).select("list", "members")
