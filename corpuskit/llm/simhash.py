"""SimHash near-duplicates found through a byte-position inverted index with count filtering.

A fingerprint has eight byte positions. Two fingerprints that differ in at most three bits share five positional
bytes or more. The index posts each distinct fingerprint under eight triples of positions, chosen so that any five
positions hold one triple whole: those inside the first four positions and those inside the last four. Pairs that
meet in a posting list are tallied over all eight positions, those with fewer than five shared bytes go, and the
rest is verified by differing bits. A list leaves its task as links to one member of each linked set, never as pairs.

A long list is posted anew: its pairs must share two bytes more, so it is cut by every two of the other five positions.
What is long even then shares five bytes, and is compared in blocks.

Defined results: a null or empty text has no word and the fingerprint zero; equal texts share a fingerprint; a null
doc_id keeps its row and never names a component, unless no other id is in it (then the component is null); repeated
rows come back as often as they went in; an empty table gives an empty result. Other columns are not read.
"""

from __future__ import annotations

import itertools
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.batches import pieces
from corpuskit.llm.resemblance import Resemblance
from corpuskit.llm.vocab import forget_words
from corpuskit.operators.components import connected
from corpuskit.operators.relational import sized_join
from corpuskit.session import scratch, ship, staged

SEED, SHINGLE, MAX_BITS = 42, 3, 3
#: Members of a posting list compared in one unit; a longer list is posted anew, and cut into blocks if that is of no use.
BLOCK = 2048
TRIPLES = [t for half in (range(4), range(4, 8)) for t in itertools.combinations(half, 3)]
_WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def shingle_hashes(text: bytes) -> list[int]:
    words = _WORD.findall(text.lower())  # bytes: A-Z only
    if not words:
        return []
    joined = b" ".join(words)
    if len(words) <= SHINGLE:
        return [xxhash.xxh64_intdigest(joined, SEED)]
    ends = list(itertools.accumulate(map(len, words), lambda a, n: a + n + 1))
    digest = xxhash.xxh64_intdigest
    return [digest(joined[s:e], SEED) for s, e in zip([0, *(x + 1 for x in ends)], ends[SHINGLE - 1 :], strict=False)]


def prints_of(column: pa.Array) -> np.ndarray:
    """The fingerprint of each text as a signed number."""
    found = [shingle_hashes(t) for t in pc.fill_null(column.cast(pa.binary()), b"").to_pylist()]
    counts = np.fromiter(map(len, found), np.int64, len(found))
    flat = np.fromiter(itertools.chain.from_iterable(found), np.uint64, int(counts.sum()))
    prints = np.zeros(len(found), np.uint64)
    if len(flat):
        some = np.flatnonzero(counts)
        bits = np.unpackbits(flat.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        ones = np.add.reduceat(bits, (np.cumsum(counts) - counts)[some], axis=0, dtype=np.int64)
        prints[some] = np.packbits(2 * ones > counts[some][:, None], axis=1).view(">u8").ravel()
    return prints.view(np.int64)


def _fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    forget_words()
    for whole in batches:
        for batch in pieces(whole, "text"):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(prints_of(batch.column("text")))], ["doc_id", "print"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, print): the 64-bit fingerprint of every row as a signed number."""
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_fingerprint_batches, "doc_id long, print long")


def _byte(value: Column, place: int) -> Column:
    return F.shiftrightunsigned(value, 8 * place).bitwiseAND(F.lit(255))


def _keys(value: Column) -> Column:
    return F.array(*(F.lit(k << 24).cast("long") + _byte(value, a) * 65536 + _byte(value, b) * 256 + _byte(value, c) for k, (a, b, c) in enumerate(TRIPLES)))


def _longer_keys(value: Column, key: Column) -> Column:
    """The keys of a member of a list with two more positions each."""
    def of(triple: tuple[int, ...]) -> Column:
        rest = itertools.combinations([p for p in range(8) if p not in triple], 2)
        return F.array(*((key * 16 + i) * 65536 + _byte(value, a) * 256 + _byte(value, b) for i, (a, b) in enumerate(rest)))

    return F.get(F.array(*map(of, TRIPLES)), F.shiftright(key, 24).cast("int"))


def linked_sets(values: np.ndarray, max_bits: int = MAX_BITS) -> list[tuple[int, int]]:
    """(root index, member index) for all members of linked sets of two or more."""
    n = len(values)
    by_place = values.view(np.uint8).reshape(n, 8).T
    near = np.zeros((n, n), bool)
    for s in range(0, n, 512):
        e = min(n, s + 512)
        tally = np.zeros((e - s, n), np.uint8)
        for place in by_place:
            tally += place[s:e, None] == place[None, :]
        x, y = np.nonzero(tally >= 8 - max_bits)
        good = np.bitwise_count(values[s + x] ^ values[y]) <= max_bits
        near[s + x[good], y[good]] = True
    out, left = [], np.ones(n, bool)
    for root in range(n):
        if left[root]:
            left[root] = False
            wave = np.array([root])
            while len(wave):
                found = np.flatnonzero(near[wave].any(axis=0) & left)
                left[found] = False
                out += [(root, int(x)) for x in found]
                wave = found
    return out


def _link_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        a, b = [], []
        for row in batch.column("prints"):
            values = np.unique(row.values.to_numpy(zero_copy_only=False)).view(np.uint64)
            if len(values) > 1:
                for i, j in linked_sets(values):
                    a.append(values[i])
                    b.append(values[j])
        yield pa.RecordBatch.from_arrays([pa.array(np.array(x, np.uint64).view(np.int64)) for x in (a, b)], ["a", "b"])


def _met(keyed: DataFrame) -> DataFrame:
    """(print, key, members) of the lists with two members or more."""
    sizes = staged(keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1").withColumn("members", F.col("n")), "lists")
    return sized_join(keyed, sizes, "key")


def links(prints: DataFrame, block: int = BLOCK) -> DataFrame:
    """(a, b) over distinct fingerprints in column `print`: enough links to connect all that are linked."""
    out = "a long, b long"
    whole = lambda met: met.filter(F.col("members") <= block).groupBy("key").agg(F.collect_list("print").alias("prints")).select("prints")
    first = _met(prints.select("print", F.explode(_keys(F.col("print"))).alias("key")))
    found = whole(first).mapInArrow(_link_batches, out)
    long = staged(first.filter(F.col("members") > block).select("print", F.explode(_longer_keys(F.col("print"), F.col("key"))).alias("key")), "long-lists")
    if long.isEmpty():
        return found
    second = _met(long)
    blocks = F.ceil(F.col("members") / block).cast("int")
    dealt = second.filter(F.col("members") > block).select("key", "print", blocks.alias("blocks"), F.pmod(F.xxhash64("print"), blocks).cast("int").alias("own"))
    units = dealt.select("key", "print", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    lists = units.groupBy("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j")).agg(F.collect_list("print").alias("prints"))
    return found.unionByName(whole(second).unionByName(lists.select("prints")).mapInArrow(_link_batches, out))


def _components(rows: DataFrame, linked: DataFrame, node: str) -> DataFrame:
    """(node, component_id): the least doc_id of each component of the nodes of rows(doc_id, node)."""
    classes = rows.groupBy(node).agg(F.min("doc_id").alias("least"))
    roots = connected(linked).withColumnRenamed("node", "member")
    member = classes.join(roots, classes[node] == roots["member"], "left").select(classes[node], "least", F.coalesce("root", node).alias("root"))
    named = member.groupBy("root").agg(F.min("least").alias("component_id"))
    return member.join(named, "root").select(node, "component_id")


def near_duplicates(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of docs(doc_id, text)."""
    rows = staged(fingerprints(docs), "prints")
    of = _components(rows, links(staged(rows.select("print").distinct(), "distinct-prints"), block), "print")
    of = staged(of.join(rows.groupBy("print").agg(F.count("*").alias("n")), "print"), "components")
    return sized_join(rows, of, "print").select("doc_id", F.lpad(F.lower(F.hex("print")), 16, "0").alias("fingerprint"), "component_id")


def alike(index: Resemblance, block: int = BLOCK) -> DataFrame:
    """(a, b), staged: nodes whose fingerprints are equal or linked, if an exact check finds them alike."""
    held = staged(index.prints.groupBy("print", "node").agg(F.count("*").alias("n")).select("print", "node"), "print-nodes")
    firsts = staged(held.groupBy("print").agg(F.min("node").alias("first"), F.count("*").alias("n")), "print-firsts")
    equal = sized_join(held, firsts.filter("n > 1"), "print").filter("node != first").select(F.col("first").alias("x"), F.col("node").alias("y"))
    linked = links(firsts.select("print"), block)
    near = linked.join(firsts.select(F.col("print").alias("a"), F.col("first").alias("x")), "a").join(firsts.select(F.col("print").alias("b"), F.col("first").alias("y")), "b").select("x", "y")
    pairs = equal.unionByName(near).filter("x != y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
    return staged(index.verified(staged(pairs, "print-pairs")), "print-links")


def keep_one(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """docs without the later documents of each component of texts alike; the document with the least doc_id stays.

    Texts are alike at a Jaccard similarity of 0.8 or more over five-word shingles. Fingerprints within three bits link
    them first, each link checked exactly; no number of bits meets all such pairs, so the index of resemblance adds what
    three bits leave apart. Rows that share a doc_id are one document and stay or go together. Rows without a doc_id stay.
    """
    with scratch(docs.sparkSession) as keep:
        index = Resemblance(docs, block, prints_of)
        linked = alike(index, block).unionByName(index.links())
        named = _components(index.rows, linked, "node")
        gone = keep(staged(index.rows.join(named, "node").filter("doc_id != component_id").select("doc_id").distinct(), "gone"))
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
