"""Near duplicates by MinHash, banding and exact Jaccard verification.

Documents with equal shingle sets form a class; one of them stands for it, so copies never make pairs among
themselves. Pairs between representatives are complete; class members follow through `members`.
"""

from __future__ import annotations

import hashlib
import math
import random
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpuskit.functions.grams import pieces
from corpuskit.functions.text import word_grams
from corpuskit.operators.components import connected
from corpuskit.operators.relational import sized_join
from corpuskit.session import ship, staged

PRIME = (1 << 31) - 1
#: A set that more than one part in so many of all pairs is in is broadcast to them.
HOT_SETS = 50
#: Vectors of a block at most, and cells of two blocks that are held at once.
VECTOR_BLOCK, STRIP_CELLS = 32_768, 1 << 22
#: Documents of a block whose pairs are counted in one task, and elements that they share with others, at most.
BLOCK_DOCS, BLOCK_ELEMENTS = 32_768, 4_000_000
#: In the place of a block: a row of a unit that is a pair to look for.
MARK = -1


def hash_family(k: int = 64, seed: int = 0) -> list[tuple[int, int]]:
    draw = random.Random(seed)
    return [(draw.randrange(1, PRIME), draw.randrange(PRIME)) for _ in range(k)]


def shingles(docs: DataFrame, n: int = 3, text: str = "clean") -> DataFrame:
    """(doc_id, shingles): the distinct word n-grams of documents that have any."""
    return docs.select("doc_id", word_grams(F.col(text), n).alias("shingles")).filter(F.size("shingles") > 0)


def portable_hash(c: Column) -> Column:
    """31 bits of MD5, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long").bitwiseAND(F.lit(PRIME))


def fast_hash(c: Column) -> Column:
    return F.xxhash64(c).bitwiseAND(F.lit(PRIME))


def hashed(sets: DataFrame, base: str = "md5") -> DataFrame:
    """(doc_id, hashes): sorted distinct 31-bit hashes of the shingles."""
    of = portable_hash if base == "md5" else fast_hash
    return sets.select("doc_id", F.array_sort(F.array_distinct(F.transform("shingles", of))).alias("hashes"))


def _firsts(keys: DataFrame) -> DataFrame:
    """(key, representative, n), staged: the least document of each set, and how many have it."""
    return staged(keys.groupBy("key").agg(F.min("doc_id").alias("representative"), F.count("*").alias("n")), "set-firsts")


def _set_key(column: str = "hashes") -> Column:
    """A SHA-256 that stands for a set."""
    return F.sha2(F.concat_ws(",", F.col(column)), 256).alias("key")


def classes(sets: DataFrame, column: str = "hashes") -> DataFrame:
    """(doc_id, representative): documents of equal sets share the least id."""
    keys = staged(sets.select("doc_id", _set_key(column)), "set-keys")
    return sized_join(keys, _firsts(keys), "key").select("doc_id", "representative")


def keyed_sets(docs: DataFrame, n: int = 3, base: str = "md5", text: str = "clean") -> DataFrame:
    """(doc_id, hashes, key): hashed(shingles()) and what stands for the set. MD5 of each shingle is taken outside of
    SQL, where it costs a fifth."""
    if base != "md5":
        return hashed(shingles(docs, n, text), base).select("doc_id", "hashes", _set_key())
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in pieces(whole, "text"):
                rows, sets, keys = [], [np.zeros(0, np.int64)], []
                for i, data in enumerate(batch.column("text").cast(pa.binary()).to_pylist()):
                    words = [] if data is None else data.split(b" ")
                    grams = {b" ".join(words[j : j + n]) for j in range(len(words) - n + 1)}
                    if grams:
                        heads = b"".join(hashlib.md5(g, usedforsecurity=False).digest()[:4] for g in grams)
                        rows.append(i)
                        sets.append(np.unique(np.frombuffer(heads, ">u4").astype(np.int64) & PRIME))
                        keys.append(hashlib.sha256(sets[-1].tobytes()).hexdigest())
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum([len(x) for x in sets]), pa.int32()), pa.array(np.concatenate(sets)))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(rows, pa.int64())), lists, pa.array(keys, pa.string())], ["doc_id", "hashes", "key"])

    asked = docs.select("doc_id", F.col(text).alias("text"))
    return asked.mapInArrow(run, f"doc_id {asked.schema['doc_id'].dataType.simpleString()}, hashes array<long>, key string")


def signatures(hashes: DataFrame, k: int = 64, seed: int = 0) -> DataFrame:
    """(doc_id, signature): k minima. One vectorised pass for each hash function over a whole batch."""
    ship(hashes.sparkSession)
    family = hash_family(k, seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("hashes")
            sizes = np.asarray(lists.value_lengths())
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            out = np.empty((len(sizes), k), np.int64)
            if len(sizes):
                starts = np.cumsum(sizes) - sizes
                for i, (a, c) in enumerate(family):
                    out[:, i] = np.minimum.reduceat((flat * a + c) % PRIME, starts)
            rows = pa.FixedSizeListArray.from_arrays(pa.array(out.ravel()), k).cast(pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), rows], ["doc_id", "signature"])

    return hashes.filter(F.size("hashes") > 0).select("doc_id", "hashes").mapInArrow(run, "doc_id long, signature array<long>")


def signatures_native(hashes: DataFrame, k: int = 64, seed: int = 0) -> DataFrame:
    """The same in SQL expressions alone."""
    def least(a: int, c: int) -> Column:
        return F.array_min(F.transform("hashes", lambda x: (x * a + c) % PRIME))

    minima = [least(a, c) for a, c in hash_family(k, seed)]
    return hashes.filter(F.size("hashes") > 0).select("doc_id", F.array(*minima).alias("signature"))


def estimate(a: Column, b: Column) -> Column:
    same = F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda s, x: s + x)
    return same / F.size(a)


def std_error(j: float, k: int = 64) -> float:
    return (j * (1 - j) / k) ** 0.5


def jaccard(a: Column, b: Column) -> Column:
    """Of two arrays without repeats."""
    common = F.size(F.array_intersect(a, b))
    return common / (F.size(a) + F.size(b) - common)


def bands(sigs: DataFrame, b: int = 16, r: int = 4) -> DataFrame:
    """(doc_id, band, key): slim rows, the band's minima joined."""
    parts = F.array(*(F.struct(F.lit(i).alias("band"), F.concat_ws("-", F.slice("signature", i * r + 1, r)).alias("key")) for i in range(b)))
    return sigs.select("doc_id", F.explode(parts).alias("x")).select("doc_id", "x.band", "x.key")


def candidates(banded: DataFrame, marks: DataFrame | None = None, docs: int | None = None) -> DataFrame:
    """(a, b), a < b: documents that agree on a whole band, each pair once, made in blocks inside tasks. The key is hashed so
    that rows stay slim; equal hashes of different keys only add candidates, which verification removes.

    marks(a, b): each candidate also says, as `marked`, whether it is one of these pairs; they go to the task that makes it.
    """
    ship(banded.sparkSession)
    keys = banded.groupBy("doc_id").agg(F.collect_set(F.xxhash64("band", "key")).alias("keys"))
    marked = marks is not None

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit = pa.Table.from_batches(list(batches))
        mark = pc.equal(unit.column("own"), MARK)
        known = _Pairs(unit.filter(mark))
        for a, b, _ in _met_in_unit(key[0].as_py(), key[1].as_py(), iter(unit.filter(pc.invert(mark)).to_batches())):
            rows = {"a": a, "b": b} | ({"marked": known.hold(a, b)} if marked else {})
            yield pa.RecordBatch.from_pydict(rows)

    units = _overlap_units(keys, "keys", docs or BLOCK_DOCS, marks)
    return units.groupBy("i", "j").applyInArrow(run, "a long, b long" + (", marked boolean" if marked else ""))


class _Pairs:
    """Pairs that are asked for, of the marks in a unit."""

    def __init__(self, marks: pa.Table):
        a = marks.column("doc_id").to_numpy()
        b = marks.column("xs").combine_chunks().flatten().to_numpy(zero_copy_only=False) if len(a) else a
        self.ids = np.unique(np.r_[a, b])
        self.codes = np.unique(np.searchsorted(self.ids, a) * len(self.ids) + np.searchsorted(self.ids, b))

    def hold(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if not len(self.ids):
            return np.zeros(len(a), bool)
        x, y = (np.minimum(np.searchsorted(self.ids, v), len(self.ids) - 1) for v in (a, b))
        codes = x * len(self.ids) + y
        at = np.minimum(np.searchsorted(self.codes, codes), len(self.codes) - 1)
        return (self.ids[x] == a) & (self.ids[y] == b) & (self.codes[at] == codes)


def star_candidates(banded: DataFrame) -> DataFrame:
    """Each bucket linked to its least document only: linear in the bucket, a subset of candidates()."""
    w = banded.groupBy("band", "key").agg(F.min("doc_id").alias("a"))
    return banded.join(w, ["band", "key"]).filter("a < doc_id").select("a", F.col("doc_id").alias("b")).distinct()


def bucket_report(banded: DataFrame, cap: int) -> DataFrame:
    """What a cap on bucket size would leave out; no cap is applied."""
    sizes = banded.groupBy("band", "key").agg(F.count("*").alias("m")).filter(F.col("m") > cap)
    return sizes.groupBy("band").agg(F.count("*").alias("buckets"), F.sum("m").alias("docs"), F.sum(F.expr("m * (m - 1) div 2 - (m - 1)")).alias("pairs_skipped"))


def verify(pairs: DataFrame, sets: DataFrame, tau: float = 0.8, column: str = "hashes") -> DataFrame:
    """(a, b, jaccard) of the pairs at tau or above. Sizes are compared first: sets of very different size can't reach tau."""
    sized = sets.select("doc_id", F.size(column).alias("n"))
    near = (
        pairs.join(sized.toDF("a", "na"), "a").join(sized.toDF("b", "nb"), "b").filter(F.least("na", "nb") >= tau * F.greatest("na", "nb")).select("a", "b")
    )
    full = sets.select("doc_id", column)
    both = near.join(full.toDF("a", "sa"), "a").join(full.toDF("b", "sb"), "b")
    return both.select("a", "b", jaccard(F.col("sa"), F.col("sb")).alias("jaccard")).filter(F.col("jaccard") >= tau)


def compared(pairs: DataFrame, sets: DataFrame, column: str = "hashes") -> DataFrame:
    """(a, b, jaccard) of all pairs, which are staged; many may share an a."""
    full = sets.select("doc_id", column)
    mine = pairs.join(full.toDF("b", "sb"), "b")
    both = sized_join(mine, full.toDF("a", "sa"), "a", parts=HOT_SETS, sizes=pairs.groupBy("a").agg(F.count("*").alias("n")))
    return both.select("a", "b", jaccard(F.col("sa"), F.col("sb")).alias("jaccard"))


def bucket_links(buckets: DataFrame, sets: DataFrame, tau: float = 0.8, column: str = "hashes") -> DataFrame:
    """(a, b, jaccard): verified pairs of one bucket that connect all its verified pairs.

    buckets(bucket, doc_id) is staged. Every member is compared with the least of its bucket, so a bucket of near copies
    costs its length and not its square. What is alike to the least needs no comparison among itself. Members that are
    not are compared with all they could still be alike to: Jaccard distance is a metric, so two members whose distances
    to the least differ by more than 1 - tau are not alike. No verified link between different components is lost.
    """
    least = staged(buckets.groupBy("bucket").agg(F.min("doc_id").alias("a"), F.count("*").alias("n")).filter("n > 1"), "bucket-firsts")
    met = staged(sized_join(buckets, least, "bucket").filter("a != doc_id").select("bucket", "a", F.col("doc_id").alias("b")), "bucket-stars")
    known = staged(compared(staged(met.select("a", "b").distinct(), "bucket-pairs"), sets, column), "bucket-compared")
    loose = known.filter(F.col("jaccard") < tau)
    found = known.filter(F.col("jaccard") >= tau)
    if loose.isEmpty():
        return found
    unsure = met.join(loose.select("a", "b", F.col("jaccard").alias("j")), ["a", "b"]).select("bucket", "a", "b", "j")
    beside = met.join(unsure.select("bucket").distinct(), "bucket", "left_semi").join(known, ["a", "b"])
    left, right = unsure.select("bucket", F.col("b").alias("x"), "j"), beside.select("bucket", F.col("b").alias("y"), F.col("jaccard").alias("k"))
    reach = (F.abs(F.col("j") - F.col("k")) <= 1 - tau + 1e-9) & (F.col("x") != F.col("y")) & ((F.col("k") >= tau) | (F.col("x") < F.col("y")))
    pairs = left.join(right, "bucket").filter(reach).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
    return found.unionByName(verify(pairs, sets, tau, column))


def _overlap_units(sets: DataFrame, column: str, docs: int, marks: DataFrame | None = None) -> DataFrame:
    """(i, j, own, doc_id, n, xs): every two blocks of documents, with those of their elements that others have too; and each
    of the pairs marks(a, b) where its documents meet, as doc_id and the only one of xs."""
    items = sets.filter("doc_id IS NOT NULL").select("doc_id", F.size(column).alias("n"), F.explode(column).alias("x"))
    again = items.groupBy("x").agg(F.count("*").alias("df")).filter("df > 1").select("x")
    slim = staged(items.join(again, "x").groupBy("doc_id", "n").agg(F.collect_list("x").alias("xs")), "shared-elements")
    count, elements = slim.agg(F.count("*"), F.coalesce(F.sum(F.size("xs")), F.lit(0))).first()
    blocks = max(1, math.ceil(count / docs), math.ceil(elements / BLOCK_ELEMENTS), min(8, count // 1024))
    block = lambda c: F.pmod(F.xxhash64(F.col(c).cast("long")), F.lit(blocks)).cast("int")
    dealt = slim.withColumn("own", block("doc_id"))
    units = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    units = units.select(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "doc_id", "n", "xs")
    if marks is None:
        return units
    i, j = F.least(block("a"), block("b")), F.greatest(block("a"), block("b"))
    return units.unionByName(marks.select(i.alias("i"), j.alias("j"), F.lit(MARK).alias("own"), F.col("a").alias("doc_id"), F.lit(0).alias("n"), F.array("b").alias("xs")))


def _met_in_unit(i: int, j: int, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Ids and Jaccard similarity of the pairs between blocks i and j that share an element, a strip of i at a time."""
    table = pa.Table.from_batches(list(batches)).combine_chunks()
    own, ids, n = (table.column(c).to_numpy() for c in ("own", "doc_id", "n"))
    lists = table.column("xs").combine_chunks()
    sizes, flat = np.asarray(lists.value_lengths()), lists.flatten().to_numpy(zero_copy_only=False)
    first = np.r_[0, np.cumsum(sizes, dtype=np.int64)]
    left, right = np.flatnonzero(own == i), np.flatnonzero(own == j)
    if not len(left) or not len(right):
        return
    place = np.full(len(own), -1)
    place[right] = np.arange(len(right))
    holder = np.repeat(place, sizes)
    mine = np.flatnonzero(holder >= 0)
    mine = mine[np.argsort(flat[mine], kind="stable")]
    keys, holder = flat[mine], holder[mine]
    wide = len(right)
    strip = max(1, STRIP_CELLS // wide)
    for s in range(0, len(left), strip):
        rows = left[s : s + strip]
        xs = np.concatenate([flat[first[r] : first[r + 1]] for r in rows])
        base = np.repeat(np.arange(len(rows)) * wide, sizes[rows])
        low = np.searchsorted(keys, xs, "left")
        many = np.searchsorted(keys, xs, "right") - low
        ends = np.cumsum(many)
        shared = np.zeros(len(rows) * wide, np.int64)
        at = 0
        while at < len(xs):  # some millions of meetings at once, one element's at least
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STRIP_CELLS, "right")))
            m = many[at:to]
            turn = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
            shared += np.bincount(np.repeat(base[at:to], m) + holder[np.repeat(low[at:to], m) + turn], minlength=len(shared))
            at = to
        cells = np.flatnonzero(shared)
        common, x, y = shared[cells], rows[cells // wide], right[cells % wide]
        good = ids[x] < ids[y] if i == j else ids[x] != ids[y]
        x, y, common = x[good], y[good], common[good]
        yield np.minimum(ids[x], ids[y]), np.maximum(ids[x], ids[y]), common / (n[x].astype(np.int64) + n[y] - common)


def brute_force(sets: DataFrame, tau: float = 0.0, column: str = "hashes", docs: int = BLOCK_DOCS) -> DataFrame:
    """Every pair that shares an element, with its exact Jaccard similarity, if that is at tau or above.

    Documents are dealt into blocks and every two blocks are counted inside one task, so pairs below tau never leave it.
    """
    ship(sets.sparkSession)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for a, b, jaccard in _met_in_unit(key[0].as_py(), key[1].as_py(), batches):
            kept = jaccard >= tau
            yield pa.RecordBatch.from_arrays([pa.array(a[kept]), pa.array(b[kept]), pa.array(jaccard[kept])], ["a", "b", "jaccard"])

    return _overlap_units(sets, column, docs).groupBy("i", "j").applyInArrow(run, "a long, b long, jaccard double")


def similarity_histogram(sets: DataFrame, bins: int = 10, column: str = "hashes", docs: int = BLOCK_DOCS) -> DataFrame:
    """(bin, n_pairs) of brute_force(), counted where the pairs are met."""
    ship(sets.sparkSession)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(bins, np.int64)
        for _, _, jaccard in _met_in_unit(key[0].as_py(), key[1].as_py(), batches):
            total += np.bincount(np.minimum(np.floor(jaccard * bins).astype(np.int64), bins - 1), minlength=bins)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(bins)), pa.array(total)], ["bin", "n"])

    counted = _overlap_units(sets, column, docs).groupBy("i", "j").applyInArrow(run, "bin long, n long")
    return counted.groupBy("bin").agg(F.sum("n").alias("n_pairs")).filter("n_pairs > 0")


def prefix_join(sets: DataFrame, tau: float = 0.8, column: str = "hashes") -> DataFrame:
    """All pairs at tau or above, exactly: two such sets share one of their size - ceil(tau size) + 1 rarest elements."""
    items = sets.select("doc_id", F.size(column).alias("n"), F.explode(column).alias("x"))
    ranked = items.join(items.groupBy("x").agg(F.count("*").alias("df")), "x")
    w = Window.partitionBy("doc_id").orderBy("df", "x")
    prefix = ranked.withColumn("place", F.row_number().over(w)).filter(F.col("place") <= F.col("n") - F.ceil(F.col("n") * tau - 1e-9) + 1).filter("df > 1")
    left, right = prefix.select(F.col("doc_id").alias("a"), "x", F.col("n").alias("na")), prefix.select(F.col("doc_id").alias("b"), "x", F.col("n").alias("nb"))
    pairs = left.join(right, "x").filter("a < b").filter(F.least("na", "nb") >= tau * F.greatest("na", "nb")).select("a", "b").distinct()
    return verify(pairs, sets, tau, column)


def s_curve(s: Column | float, b: int, r: int) -> Column:
    s = s if isinstance(s, Column) else F.lit(s)
    return 1 - F.pow(1 - F.pow(s, r), b)


def s_curve_value(s: float, b: int, r: int) -> float:
    return 1 - (1 - s**r) ** b


def midpoint(b: int, r: int) -> float:
    return (1 / b) ** (1 / r)


def s_curve_table(spark: SparkSession, settings=((16, 4), (8, 8), (32, 2)), steps: int = 20) -> DataFrame:
    rows = spark.range(steps + 1).select((F.col("id") / steps).alias("s"))
    return reduce(DataFrame.union, (rows.select(F.lit(b).alias("bands"), F.lit(r).alias("rows"), "s", F.round(s_curve(F.col("s"), b, r), 6).alias("probability")) for b, r in settings))


def sweep(sets: DataFrame, tau: float = 0.8, settings=((16, 4), (8, 8), (32, 2)), k: int = 64, seed: int = 0) -> DataFrame:
    """Candidates, true pairs among them, precision and recall against brute force for each way to cut the signature."""
    sigs = staged(signatures(sets, k, seed), "signatures")
    truth = staged(brute_force(sets, tau).select("a", "b"), "true-pairs")
    total, out = truth.agg(F.count("*").alias("all_pairs")), []
    for b, r in settings:
        row = candidates(bands(sigs, b, r), truth).agg(F.count("*").alias("candidates"), F.count_if("marked").alias("true_pairs"))
        out.append(row.crossJoin(total).select(F.lit(b).alias("bands"), F.lit(r).alias("rows"), "candidates", "true_pairs", F.round(F.col("true_pairs") / F.col("candidates"), 6).alias("precision"), F.round(F.col("true_pairs") / F.col("all_pairs"), 6).alias("recall")))
    return reduce(DataFrame.union, out)


class NearDuplicates:
    """The phase as a whole; intermediate tables lie in the shared folder, each computed once."""

    def __init__(self, docs: DataFrame, n: int = 3, k: int = 64, b: int = 16, r: int = 4, tau: float = 0.8, seed: int = 0, base: str = "xx", text: str = "clean"):
        self.docs, self.tau = docs, tau
        keyed = staged(keyed_sets(docs, n, base, text), "shingles")
        firsts = _firsts(keyed)
        #: (doc_id, representative) of the documents that are not the only ones with their set.
        self.members = sized_join(keyed.select("doc_id", "key"), firsts.filter("n > 1"), "key").select("doc_id", "representative")
        self.sets = keyed.select("doc_id", "hashes")
        self.distinct = self.sets.join(firsts.select(F.col("representative").alias("doc_id")), "doc_id", "left_semi")
        self.bands = bands(signatures(self.distinct, k, seed), b, r)
        buckets = staged(self.bands.select(F.xxhash64("band", "key").alias("bucket"), "doc_id"), "buckets")
        #: Verified pairs, as many as connect what is alike; candidates() and verify() give every pair.
        self.pairs = staged(bucket_links(buckets, self.distinct, tau), "pairs")

    def links(self) -> DataFrame:
        """Verified pairs, and each copy linked to its representative."""
        copies = self.members.filter("doc_id != representative").select(F.col("representative").alias("a"), F.col("doc_id").alias("b"))
        return self.pairs.select("a", "b").union(copies)

    def clusters(self) -> DataFrame:
        """(doc_id, component) of documents with a near duplicate."""
        return connected(self.links()).select(F.col("node").alias("doc_id"), F.col("root").alias("component"))


def losers(docs: DataFrame, clusters: DataFrame, unit: str = "chars", text: str = "clean") -> DataFrame:
    """(doc_id) of clustered documents but the longest of each; of equal length the least id as a string stays."""
    length = F.char_length(text) if unit == "chars" else F.size(F.split(F.col(text), " "))
    sized = docs.select("doc_id", length.alias("n")).join(clusters, "doc_id")
    best = sized.groupBy("component").agg(F.min(F.struct((-F.col("n")).alias("n"), F.col("doc_id").cast("string").alias("s"), F.col("doc_id").alias("best"))).alias("x")).select("component", "x.best")
    return sized.join(best, "component").filter("doc_id != best").select("doc_id")


def survivors(docs: DataFrame, clusters: DataFrame, unit: str = "chars", text: str = "clean") -> DataFrame:
    return docs.join(losers(docs, clusters, unit, text), "doc_id", "left_anti")


def cluster_stats(clusters: DataFrame) -> DataFrame:
    return clusters.agg(F.count_distinct("component").alias("n_clusters"), F.count("*").alias("n_covered")).withColumn("n_removed", F.col("n_covered") - F.col("n_clusters"))


def cluster_sizes(clusters: DataFrame) -> DataFrame:
    return clusters.groupBy("component").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n_clusters"))


def tables_for(least: float, planes: int, recall: float) -> int:
    """Hash tables so that a pair of cosine `least` meets in one of them with probability `recall`."""
    agree = (1 - math.acos(least) / math.pi) ** planes
    return math.ceil(math.log(1 - recall) / math.log(1 - agree))


def _unit(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding, norm); null, empty and zero vectors are near none and go."""
    return vectors.select("vec_id", "embedding", F.sqrt(_dot(F.col("embedding"), F.col("embedding"))).alias("norm")).filter("norm > 0")


def _dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, z: s + z)


def plane_pairs(vectors: DataFrame, least: float = 0.9, planes: int = 12, recall: float = 0.999, seed: int = 0) -> DataFrame:
    """(a, b, cosine) of near vectors in vectors(vec_id, embedding), by random hyperplane buckets and exact cosine.

    A pair at the threshold is met with probability `recall`, a nearer one more surely; vector_pairs() meets them all.
    """
    ship(vectors.sparkSession)
    tables = tables_for(least, planes, recall)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        normals = None
        for batch in batches:
            if not batch.num_rows:
                continue
            m = np.stack([np.asarray(x, np.float64) for x in batch.column("embedding").to_pylist()])
            if normals is None:
                normals = np.random.default_rng(seed).normal(size=(tables * planes, m.shape[1]))
            bits = (m @ normals.T > 0).reshape(len(m), tables, planes)
            keys = (bits << np.arange(planes)).sum(axis=2) + (np.arange(tables) << planes)
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(keys.tolist(), pa.list_(pa.int64()))], ["vec_id", "keys"])

    full = _unit(vectors)
    keyed = full.select("vec_id", "embedding").mapInArrow(run, "vec_id long, keys array<long>").select("vec_id", F.explode("keys").alias("key"))
    pairs = keyed.toDF("a", "key").join(keyed.toDF("b", "key"), "key").filter("a < b").select("a", "b").distinct()
    both = pairs.join(full.toDF("a", "ea", "na"), "a").join(full.toDF("b", "eb", "nb"), "b")
    return both.select("a", "b", (_dot(F.col("ea"), F.col("eb")) / (F.col("na") * F.col("nb"))).alias("cosine")).filter(F.col("cosine") >= least)


def vector_pairs(vectors: DataFrame, least: float = 0.9, block: int = VECTOR_BLOCK) -> DataFrame:
    """(a, b, cosine), a < b, of all pairs of vectors(vec_id, embedding) at `least` or above, exactly.

    Vectors are dealt into blocks by hash and every two blocks are multiplied inside one task, a strip at a time: a
    block crosses the network once for each block, pairs never do before they are found.
    """
    ship(vectors.sparkSession)
    full = staged(_unit(vectors), "vectors")
    n = full.count()
    blocks = max(1, math.ceil(n / block), min(8, n // 1024))

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        i, j = (k.as_py() for k in key)
        ids, own, parts = [], [], []
        for batch in batches:
            lists, norms = batch.column("embedding"), batch.column("norm").to_numpy()
            ids.append(batch.column("vec_id").to_numpy())
            own.append(batch.column("own").to_numpy())
            parts.append(lists.flatten().to_numpy(zero_copy_only=False).reshape(len(norms), -1) / norms[:, None])
        ids, own, m = np.concatenate(ids), np.concatenate(own), np.concatenate(parts)
        left, right = np.flatnonzero(own == i), np.flatnonzero(own == j)
        there, columns = ids[right], m[right].T.copy()
        strip = max(1, STRIP_CELLS // max(1, len(right)))
        for s in range(0, len(left), strip):
            rows = left[s : s + strip]
            cosine = m[rows] @ columns
            x, y = np.nonzero(cosine >= least)
            a, b = ids[rows][x], there[y]
            good = a < b if i == j else a != b
            a, b, c = a[good], b[good], cosine[x[good], y[good]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(c)], ["a", "b", "cosine"])

    own = F.pmod(F.xxhash64("vec_id", "embedding"), F.lit(blocks)).cast("int")
    dealt = full.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"), "norm", own.alias("own"))
    units = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    met = units.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    return met.select("i", "j", "vec_id", "embedding", "norm", "own").groupBy("i", "j").applyInArrow(run, "a long, b long, cosine double")


def mllib_candidates(sets: DataFrame, tau: float = 0.8, column: str = "hashes", tables: int = 16, bits: int = 18) -> DataFrame:
    """The library's MinHash join over hashed term vectors, for comparison: pairs that share a hash of its model and are nearer than 1 - tau.

    approxSimilarityJoin carries both vectors through every meeting of two hashes. The same pairs are those of the exact
    join over the hashed terms that meet in a hash.
    """
    from pyspark.ml.feature import HashingTF, MinHashLSH

    text = sets.select("doc_id", F.transform(column, lambda x: x.cast("string")).alias("terms"))
    vectors = HashingTF(inputCol="terms", outputCol="features", numFeatures=1 << bits, binary=True).transform(text)
    model = MinHashLSH(inputCol="features", outputCol="h", numHashTables=tables, seed=0).fit(vectors)
    values = F.transform("h", lambda v: F.element_at(F.unwrap_udt(v)["values"], 1))
    hashed_ = staged(model.transform(vectors).select("doc_id", F.unwrap_udt("features")["indices"].alias("terms"), values.alias("h")), "term-vectors")
    pairs, h = prefix_join(hashed_, tau, "terms"), hashed_.select("doc_id", "h")
    met = pairs.join(h.toDF("a", "ha"), "a").join(h.toDF("b", "hb"), "b").filter(F.exists(F.zip_with("ha", "hb", lambda x, y: x == y), lambda same: same))
    distance = 1 - F.col("jaccard")
    return met.filter(distance < 1 - tau).select("a", "b", (1 - distance).alias("jaccard"))
