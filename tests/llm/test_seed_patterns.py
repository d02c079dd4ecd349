import itertools
import random

import pyarrow as pa
import pytest

from corpuskit.llm import spaced_seeds as S
from corpuskit.llm.batches import Words


def find(texts, items):
    return {(f[0], f[1]): f for f in S.Seeds(list(enumerate(items))).find(Words(pa.array(texts, pa.large_string())))}


@pytest.mark.parametrize("n", range(1, 18))
def test_every_pattern_the_rule_allows_is_found(n):
    item = [f"w{i}" for i in range(n)]
    texts = []
    for gone in itertools.combinations(range(n), n // 5):
        texts.append(" ".join(["before", *("other" if i in gone else w for i, w in enumerate(item)), "after"]))
    assert {d for d, _ in find(texts, [" ".join(item)])} == set(range(len(texts)))


def test_no_longer_window_escapes_the_masks():
    """Most equal words of any window of 13 to 25 words without a hit, by all states of the last 13 words."""
    masks = [int(m, 2) for m in S.MASKS]
    best = {0: 0}
    for length in range(1, 26):
        new = {}
        for state, n in best.items():
            for bit in (0, 1):
                window = state << 1 | bit
                if not any(window & m == m for m in masks):
                    new[window & 0xFFF] = max(new.get(window & 0xFFF, 0), n + bit)
        best = new
        if length >= S.MIN_WORDS:
            assert max(best.values()) < S.MIN_SHARE * length


def brute(doc, item):
    """Length, without substituted ends, of the longest window on each diagonal that counts; the longest of all."""
    least, best = min(13, len(item)), 0
    for diagonal in range(-len(item) + 1, len(doc)):
        same = [0 <= diagonal + i < len(doc) and doc[diagonal + i] == w for i, w in enumerate(item)]
        low, high = max(0, -diagonal), min(len(item), len(doc) - diagonal)
        good = [(s, e) for s in range(low, high) for e in range(s + least, high + 1) if 5 * sum(same[s:e]) >= 4 * (e - s)]
        if good:
            s, e = max(good, key=lambda w: (w[1] - w[0], -w[0]))
            inside = [i for i in range(s, e) if same[i]]
            best = max(best, inside[-1] + 1 - inside[0])
    return best


def test_windows_equal_brute_force():
    draw = random.Random(3)
    items = [[draw.choice("abcdefgh") + str(draw.randrange(3)) for _ in range(draw.choice([4, 7, 11, 13, 15, 20, 40]))] for _ in range(30)]
    texts = []
    for item in items * 4:
        noisy = [w if draw.random() < draw.choice([0.7, 0.8, 0.9]) else draw.choice("abcdefgh") for w in item]
        texts.append([*draw.choices("abcdefgh", k=5), *noisy, *draw.choices("abcdefgh", k=5)])
    got = find([" ".join(t) for t in texts], [" ".join(x) for x in items])
    want = {(d, k): n for d, t in enumerate(texts) for k, x in enumerate(items) if (n := brute(t, x))}
    assert {x: f[4] for x, f in got.items()} == want and len(want) > 30


def test_verbatim_run_before_weaker_words():
    draw = random.Random(1)
    item = [f"w{i}" for i in range(120)]
    texts = [" ".join(w if i < 20 or draw.random() < 0.7 else "other" for i, w in enumerate(item)) for _ in range(100)]
    assert len(find(texts, [" ".join(item)])) == 100


def test_one_repeated_word_stays_bounded(monkeypatch):
    monkeypatch.setattr(S, "HITS", 1000)
    got = find(["a " * 5000, "b " * 200 + "a " * 20], ["a " * 300])
    assert got[0, 0][4] == 300 and got[1, 0][4] == 20
