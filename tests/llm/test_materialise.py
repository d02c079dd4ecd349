from collections import defaultdict

import numpy as np
import pytest

from corpuskit.llm import materialise as M
from corpuskit.llm.vocab import vocab_path, word_bpe
from corpuskit.session import new_path
from tests.llm.conftest import ODD, frame


@pytest.mark.parametrize("n", [1, 2, 3, 5, 64, 1000, 4097])
def test_slots_are_a_permutation_and_go_back(n):
    p = M.Permutation(n, 7)
    slots = p.slot(np.arange(n))
    assert sorted(slots.tolist()) == list(range(n))
    assert p.index(slots).tolist() == list(range(n))
    if n > 60:
        assert (slots != np.arange(n)).mean() > 0.9
        assert M.Permutation(n, 8).slot(np.arange(n)).tolist() != slots.tolist()


def test_every_token_comes_back_from_its_place(spark, prose):
    texts = [*ODD, *(prose(n, n) for n in (1, 30, 200, 900))] * 2
    path = new_path(spark, "m")
    manifest = M.write(frame(spark, texts).repartition(3), path, length=64, rows=5).collect()
    stored = {r["slot"]: r["ids"] for r in M.read(spark, path, length=64, rows=5).collect()}
    assert sorted(stored) == list(range(len(stored)))
    parts = defaultdict(list)
    for r in manifest:
        assert (r["shard"], r["byte_offset"]) == (r["slot"] // 5, r["slot"] % 5 * 129)
        parts[r["doc_id"]].append((r["start"], stored[r["slot"]][r["offset"] : r["offset"] + r["length"]]))
    want = [[*np.frombuffer(b, "<u4").tolist(), M.END] for b in word_bpe(vocab_path("word_bpe_49k.json")).ids(texts)]
    assert [sum((p for _, p in sorted(parts[i])), []) for i in range(len(texts))] == want


def test_reading_goes_on_from_any_slot(spark, prose):
    path = new_path(spark, "m")
    M.write(frame(spark, [prose(400, i) for i in range(5)]), path, length=64, rows=5)
    every = {r["slot"]: r["ids"] for r in M.read(spark, path, length=64, rows=5).collect()}
    some = {r["slot"]: r["ids"] for r in M.read(spark, path, 7, 13, length=64, rows=5).collect()}
    assert some == {s: every[s] for s in range(7, 13)}


def test_empty_table(spark):
    assert M.training_order(frame(spark, ["x"]).limit(0)).count() == 0
