import itertools
import random
import re

import numpy as np

from corpuskit.llm import resemblance, simhash
from tests.conftest import MEDIUM
from tests.llm.conftest import ODD, frame


def brute_sets(texts):
    out = []
    for t in texts:
        words = re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode().lower())
        out.append(frozenset(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else frozenset())
    return out


def brute_kept(texts, ids):
    sets, root = brute_sets(texts), list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(texts)), 2):
        a, b = sets[i], sets[j]
        if a == b or min(len(a), len(b)) * 5 >= 4 * max(len(a), len(b)) and 5 * len(a & b) >= 4 * len(a | b):
            root[max(find(i), find(j))] = min(find(i), find(j))
    least = {}
    for i in range(len(texts)):
        least[find(i)] = min(least.get(find(i), ids[i]), ids[i])
    return sorted(least.values())


def copies(prose):
    draw, texts = random.Random(5), list(ODD)
    for s in range(25):
        words = prose(draw.randrange(6, 200), s).split()
        texts.append(" ".join(words))
        for changes in (1, 2, 3, 4, 6):
            other = list(words)
            for p in draw.sample(range(len(words)), min(changes, len(words))):
                other[p] = f"new{draw.randrange(1000)}"
            texts.append(" ".join(other))
        texts.append(" ".join(words[: -(len(words) // 10) or None]))
    return texts


def test_stage_links_every_pair_at_four_fifths(spark, prose):
    texts = copies(prose)
    want = brute_kept(texts, range(len(texts)))
    for block in (3, 2048):
        assert sorted(r["doc_id"] for r in simhash.keep_one(frame(spark, texts), block).collect()) == want


def test_likeness_at_the_threshold_meets_and_tallies():
    """Pairs of sets at exactly 0.8: share a list and tally enough, but for the stated few."""
    draw, missed = np.random.default_rng(1), 0
    for _ in range(20):
        sets = draw.integers(0, 2**64, (200, 90), dtype=np.uint64)
        left, right = sets[:, :90], np.c_[sets[:, :80], draw.integers(0, 2**64, (200, 10), dtype=np.uint64)]
        (x, p), (y, q) = (resemblance.marks_and_keys(resemblance.minima(np.full(200, 90), s.ravel())) for s in (left, right))
        missed += int((((p == q).sum(axis=1) == 0) | ((x == y).sum(axis=1) < resemblance.SAME)).sum())
    assert missed <= 3  # of 4,000


def test_pairs_across_parts_equal_brute_force():
    draw = np.random.default_rng(2)
    base = draw.integers(0, 256, (6, resemblance.POSITIONS), dtype=np.uint8)
    marks = base[draw.integers(0, 6, 60)].copy()
    other = draw.random(marks.shape) < 0.25
    marks[other] = draw.integers(0, 256, int(other.sum()), dtype=np.uint8)
    node, part = np.arange(60) * 7, draw.integers(0, 9, 60)
    want = {(node[i], node[j]) for i, j in itertools.combinations(range(60), 2) if part[i] != part[j] and (marks[i] == marks[j]).sum() >= resemblance.SAME}
    assert want == set(zip(*resemblance.across(node, part, marks), strict=True)) != set()


def test_links_on_whole_sets_connect_what_brute_force_connects():
    draw = random.Random(7)
    base = list(range(40))
    sets = [sorted(set(base) - set(draw.sample(base, draw.randrange(9))) | {100 * i + k for k in range(draw.randrange(5))}) for i in range(70)]
    part = np.array([draw.randrange(50) for _ in sets])
    links = resemblance.connecting(np.arange(70), part, np.array([len(s) for s in sets]), np.concatenate(sets))
    alike = {(i, j) for i, j in itertools.combinations(range(70), 2) if 5 * len(set(sets[i]) & set(sets[j])) >= 4 * len(set(sets[i]) | set(sets[j]))}
    same = [(i, j) for i, j in itertools.combinations(range(70), 2) if part[i] == part[j]]

    def groups(pairs):
        root = list(range(70))
        for i, j in pairs:
            a, b = root[i], root[j]
            root = [min(a, b) if r in (a, b) else r for r in root]
        return root

    assert set(links) <= alike and len(links) < 70 and groups([*same, *links]) == groups([*same, *alike])


def test_a_family_just_below_the_threshold_stays_linear(spark, prose):
    """900 texts with five of sixty words changed, so that none is alike to most; and a few real copies among them."""
    draw, words, texts = random.Random(2), prose(90, 1).split(), []
    for i in range(900):
        own = list(words)
        for k in draw.sample(range(90), 2):
            own[k] = f"n{i}x{k}"
        texts.append(" ".join(own))
    texts += [t + " more" for t in texts[:5]]
    index = resemblance.Resemblance(frame(spark, texts))
    assert index.links().count() < 30 * len(texts)
    assert sorted(r["doc_id"] for r in simhash.keep_one(frame(spark, texts)).collect()) == brute_kept(texts, range(len(texts)))


def test_a_large_group_of_near_copies_stays_linear(spark, prose):
    """All 5,000 are alike: a link to the least of the group each, and nothing left for the blocks."""
    words = prose(60, 1).split()
    index = resemblance.Resemblance(frame(spark, [" ".join([*words, f"n{i}"]) for i in range(5000)]))
    assert index.links().count() < 3 * 5000


def test_a_chain_of_groups_is_one(spark, prose):
    """A word changed at one of sixty places: alike at the same place or the next, not beyond."""
    words = prose(60, 1).split()
    texts = [" ".join(f"n{i}" if k == i % 60 else w for k, w in enumerate(words)) for i in range(600)]
    assert simhash.keep_one(frame(spark, texts)).count() == 1


def test_stage_on_given_documents(spark):
    docs = spark.read.parquet(f"{MEDIUM}/documents.parquet").select("doc_id", "text").orderBy("doc_id")
    rows = docs.collect()
    want = brute_kept([r["text"] for r in rows], [r["doc_id"] for r in rows])
    assert sorted(r["doc_id"] for r in simhash.keep_one(docs).collect()) == want
