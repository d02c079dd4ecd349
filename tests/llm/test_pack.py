import zlib
from collections import defaultdict

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from corpuskit.llm import pack
from corpuskit.llm.vocab import vocab_path, word_bpe
from tests.conftest import SMALL
from tests.llm.conftest import ODD, frame


def plain_ids(texts):
    t = Tokenizer.from_file(vocab_path("word_bpe_49k.json"))
    t.encode_special_tokens = True
    return [t.encode(x or "", add_special_tokens=False).ids for x in texts]


def test_word_cache_equals_the_tokenizer(spark):
    texts = [r["text"] for r in spark.read.parquet(f"{SMALL}/documents.parquet").select("text").collect()] + ODD
    texts += ["It's WE'LL 'S ''s x1y2", "ÀÉ ß ÿ ×÷ ª½", "İ ǅ Σς don’t ́a é", "a b c\x85d"]
    model = word_bpe(vocab_path("word_bpe_49k.json"))
    assert [np.frombuffer(b, "<u4").tolist() for b in model.ids(texts)] == plain_ids(texts)


def check(rows, texts, capacity):
    by_doc, by_bin = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r["doc_id"]].append(r)
        by_bin[r["sequence_id"]].append(r)
    for i, ids in enumerate(plain_ids(texts)):
        ids = [*ids, 1]
        own = sorted(by_doc[i], key=lambda r: r["piece"])
        assert [r["piece"] for r in own] == list(range(len(own)))
        assert [r["length"] for r in own[:-1]] == [capacity] * (len(own) - 1)
        at = 0
        for r in own:
            assert r["start"] == at
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[at : at + r["length"]], "<u4").tobytes())
            at += r["length"]
        assert at == len(ids)
    for own in by_bin.values():
        at = 0
        for r in sorted(own, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= capacity
    return len(by_bin)


def test_packs_every_piece_once(spark, prose):
    texts = [*ODD, *(prose(n, n) for n in (3, 50, 700, 1500, 4000)), "same text", "same text"]
    n = check(pack.pack_documents(frame(spark, texts), 512).collect(), texts, 512)
    total = sum(len(x) + 1 for x in plain_ids(texts))
    assert n <= -(-total // 512) + 1


def test_groups_and_few_open_bins_lose_nothing(spark, prose):
    texts = [prose(n % 90 + 1, n) for n in range(200)]
    cuts = pack.cut(frame(spark, texts), 256)
    check(pack.pack(cuts, 256, open_bins=2, group=64).collect(), texts, 256)


def test_empty_table(spark):
    assert pack.pack_documents(frame(spark, ["x"]).limit(0)).count() == 0


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 30), max_size=60), st.integers(1, 8))
def test_bins_are_best_fit(lengths, most):
    """Against a plain version: the tightest open bin, and the fullest closes when there are too many."""
    bins, free, placed = pack.OpenBins(30, most), {}, []
    for x in lengths:
        fitting = [f for f in free.values() if f >= x]
        b, offset = bins.place(x)
        if fitting:
            assert free[b] == min(fitting)
        else:
            assert b not in free
            if len(free) == most:
                fullest = min(free.values())
                gone = [k for k, f in free.items() if f == fullest]
                closed = next(k for k in gone if k not in bins.stacks[fullest])
                del free[closed]
            free[b] = 30
        assert offset == 30 - free[b]
        free[b] -= x
        placed.append(b)
        if not free[b]:
            del free[b]
        assert len(free) == bins.open <= most


def test_words_of_one_part_and_separators_get_the_tokenizers_own_ids():
    texts = ["Plain words, don't 3rd été", "a\x1cb c", "a b\x1d", "\x1e", "one\x1ftwo three", "", "xylophonequartz"]
    own = word_bpe(vocab_path("word_bpe_49k.json")).ids([*texts, None])
    t = Tokenizer.from_file(vocab_path("word_bpe_49k.json"))
    t.encode_special_tokens = True
    assert [np.frombuffer(x, "<u4").tolist() for x in own] == [*(t.encode(x, add_special_tokens=False).ids for x in texts), []]
