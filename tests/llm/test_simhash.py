import itertools
import random
import re

import xxhash

from corpuskit.llm import simhash
from corpuskit.operators.components import connected
from corpuskit.session import staged
from tests.llm.conftest import COLUMNS, ODD, frame


def brute_print(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    parts = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    h = [xxhash.xxh64(p, seed=42).intdigest() for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(prints):
    root = {p: p for p in prints}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(list(root), 2):
        if (a ^ b).bit_count() <= 3:
            root[max(find(a), find(b))] = min(find(a), find(b))
    return {p: find(p) for p in root}


def fixture(prose):
    base = prose(400, 1)
    near = [" ".join(w if i != k * 7 else "changed" for i, w in enumerate(base.split())) for k in range(30)]
    chains = [" ".join(base.split()[:-k]) for k in range(1, 25)]
    return [*ODD, base, base, *near, *chains, *(prose(60, s) for s in range(2, 30)), "A B C d", "a b c D"]


def test_matches_brute_force_at_every_block_size(spark, prose):
    texts = fixture(prose)
    prints = [brute_print(t) for t in texts]
    roots = brute_components(prints)
    least = {}
    for i, p in enumerate(prints):
        least[roots[p]] = min(least.get(roots[p], i), i)
    for block in (3, 2048):
        got = {r["doc_id"]: r for r in simhash.near_duplicates(frame(spark, texts), block).collect()}
        assert len(got) == len(texts)
        for i, p in enumerate(prints):
            assert got[i]["fingerprint"] == f"{p:016x}"
            assert got[i]["component_id"] == least[roots[p]]


def test_index_meets_every_pair_within_three_bits():
    for positions in itertools.combinations(range(8), 5):
        assert any(set(t) <= set(positions) for t in simhash.TRIPLES)


def test_hot_lists_are_cut_and_lose_nothing(spark):
    """Fingerprints that all share three bytes, and a group that shares five, in lists far longer than a block."""
    draw = random.Random(3)
    values = {0xABCDEF << 40 | draw.randrange(1 << 40) for _ in range(300)} | {0xABCDEF1234 << 24 | draw.randrange(1 << 24) for _ in range(150)}
    for v in list(values)[:120]:
        for _ in range(draw.randrange(1, 5)):
            v ^= 1 << draw.randrange(64)
            values.add(v)
    want = brute_components(sorted(values))
    signed = lambda v: v - (1 << 64) if v >> 63 else v
    prints = staged(spark.createDataFrame([(signed(v),) for v in values], "print long"), "prints")
    for block in (20, 2048):
        root = {r["node"] % (1 << 64): r["root"] for r in connected(simhash.links(prints, block)).collect()}
        assert {frozenset(x for x in root if root[x] == k) for k in set(root.values())} == {frozenset(x for x in want if want[x] == k) for k in set(want.values()) if sum(y == k for y in want.values()) > 1}


def test_null_ids_repeated_rows_and_empty_tables(spark):
    docs = spark.createDataFrame([(None, "a b c", "en", "s", 1), (5, "a b c", "en", "s", 1), (5, "a b c", None, None, None), (None, "other", "en", "s", 1)], COLUMNS)
    rows = [(r["doc_id"], r["component_id"]) for r in simhash.near_duplicates(docs).collect()]
    assert sorted(rows, key=str) == sorted([(None, 5), (5, 5), (5, 5), (None, None)], key=str)
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_keep_one_passes_columns_through(spark, prose):
    docs = frame(spark, [prose(90, 1), prose(90, 1), prose(90, 2)]).selectExpr("*", "1 AS component_id", "2 AS root")
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == [0, 2]


def test_keep_one_links_by_fingerprints(spark, prose, monkeypatch):
    """Without the index of resemblance, near copies within three bits still go, and only those that are alike."""
    base = prose(900, 1)
    words = base.split()
    near = [" ".join(words[:-k]) for k in range(1, 6)]
    texts = [base, base, *near, *(prose(80, s) for s in range(50, 70)), "", "..."]
    prints = [brute_print(t) for t in texts]
    close = [i for i in range(2, 7) if (prints[i] ^ prints[0]).bit_count() <= 3]
    assert len(close) > 1
    monkeypatch.setattr(simhash.Resemblance, "links", lambda self: spark.createDataFrame([], "a long, b long"))
    kept = {r["doc_id"] for r in simhash.keep_one(frame(spark, texts)).collect()}
    assert 0 in kept and not kept & {1, *close} and set(range(7, len(texts))) <= kept
