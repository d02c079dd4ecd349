"""Public tokenizers with bounded caches of whole words.

word_bpe_49k treats what stands between white space on its own: its normaliser composes and lower-cases character
by character and its patterns never reach over white space. So the ids of a text are those of its words in a row,
and each word needs encoding once. A new word of ASCII and Latin-1 letters is split here by the vocabulary's own
pattern, and its parts, which many words share, go to the merges alone; any other word goes through the whole
tokenizer. Texts with the separators U+001C to U+001F, which Python takes for white space and the tokenizer does
not, are encoded whole.
"""

from __future__ import annotations

import ctypes
import gc
import os
import re
from contextlib import contextmanager
from functools import cache
from itertools import accumulate, chain, islice

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Words kept by a Python worker, and as many parts of words.
CACHED_WORDS = 400_000
_SIMPLE = re.compile("[!-~\xc0-\xd6\xd8-\xf6\xf8-\xff]+")
# fixed values: the split pattern of word_bpe_49k for such characters in lower case
_PARTS = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\xdf-\xf6\xf8-\xff]+|[0-9]|[^a-z\xdf-\xf6\xf8-\xff0-9]+")
_PRINTED = [*range(33, 127), *range(161, 173), *range(174, 256)]


def _odd(text: str) -> bool:
    """Whether a text has one of the separators U+001C to U+001F; four plain searches cost less than a pattern."""
    return "\x1c" in text or "\x1d" in text or "\x1e" in text or "\x1f" in text


def _byte_signs() -> dict[int, str]:
    """The sign that byte-level vocabularies write for each byte: itself if it prints, else the next sign from U+0100."""
    rest = [b for b in range(256) if b not in _PRINTED]
    return {b: chr(b) for b in _PRINTED} | {b: chr(256 + i) for i, b in enumerate(rest)}


@contextmanager
def no_collection():
    """Millions of short-lived strings and tuples without a cycle: the collector would only walk over them."""
    on = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if on:
            gc.enable()


def vocab_path(name: str, folder: str | None = None) -> str:
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


_kept: list[Kept] = []
_trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc's way to give freed memory back; elsewhere there is none


class Kept:
    """A tokenizer that stays with the Python worker. The words it keeps outlive tasks, until the worker turns to another model or operator."""

    def __enter__(self):
        forget_words(self)
        return self

    def __exit__(self, *_):
        pass


def forget_words(but: Kept | None = None) -> None:
    """Give up kept words; operators that need memory for other things begin with this."""
    for model in _kept:
        if model is not but:
            model.forget()
    if _trim is not None:
        _trim(0)


class WordBpe(Kept):
    """ids(texts): for every text the ids of word_bpe_49k as little-endian unsigned 32-bit bytes, no end token."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
        self.merges = Tokenizer(self.tokenizer.model)
        self.merges.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        entries = self.tokenizer.get_vocab()
        self.closes = np.zeros(len(entries), bool)
        self.closes[[i for t, i in entries.items() if t.endswith("</w>")]] = True
        # parts hold letters from U+00DF on; what is written for them lies below that or from U+0100 on, so order is free
        self.signs = {chr(i): "".join(_byte_signs()[b] for b in chr(i).encode()) for i in range(128, 256)}
        self.forget()
        _kept.append(self)

    def forget(self) -> None:
        self.known, self.known_parts = {}, {}

    def _encode(self, texts: list[str]) -> list[bytes]:
        return [np.asarray(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _words(self, new: list[str]) -> dict[str, bytes]:
        """The ids of words that are not kept yet."""
        simple, found = new, {}
        if not _SIMPLE.fullmatch("".join(new)):
            simple = [w for w in new if _SIMPLE.fullmatch(w)]
            rest = [w for w in new if not _SIMPLE.fullmatch(w)]
            found.update(zip(rest, self._encode(rest), strict=True))
        split = [(w,) if w.isalpha() else (w[:-1], w[-1]) if w[-1] in ".,!?" and w[:-1].isalpha() else _PARTS.findall(w) for w in map(str.lower, simple)]
        if len(self.known_parts) > CACHED_WORDS:
            self.known_parts = {}
        known = self.known_parts
        parts = list({p for ps in split for p in ps if p not in known})
        if parts:
            row = " ".join(parts)
            for sign in set(row):
                if sign > "~":
                    row = row.replace(sign, self.signs[sign])
            ids = np.asarray(self.merges.encode_batch_fast([row], add_special_tokens=False)[0].ids, "<u4")
            ends = (4 * (np.flatnonzero(self.closes[ids]) + 1)).tolist()
            data = ids.tobytes()
            known.update(zip(parts, (data[s:e] for s, e in zip([0, *ends], ends, strict=False)), strict=True))
        get = known.__getitem__
        found.update(zip(simple, [get(ps[0]) if len(ps) == 1 else b"".join(map(get, ps)) for ps in split], strict=True))
        return found

    def ids(self, texts: list[str | None]) -> list[bytes]:
        with no_collection():
            return self._ids(texts)

    def _ids(self, texts: list[str | None]) -> list[bytes]:
        split = [() if x is None or _odd(x) else x.split() for x in texts]
        row = list(chain.from_iterable(split))
        found = list(map(self.known.get, row))
        missed = [i for i, x in enumerate(found) if x is None]
        if missed:
            own = self._words(list({row[i] for i in missed}))
            for i in missed:
                found[i] = own[row[i]]
            room = CACHED_WORDS - len(self.known)
            self.known.update(own if len(own) <= room else islice(own.items(), max(0, room)))
        ends = list(accumulate(map(len, split)))
        out = [b"".join(found[s:e]) for s, e in zip([0, *ends], ends, strict=False)]
        for i, x in enumerate(texts):
            if x and not split[i] and _odd(x):
                out[i] = self._encode([x])[0]
        return out


@cache
def word_bpe(path: str) -> WordBpe:
    return WordBpe(path)


class Fertility(Kept):
    """Per-word figures of a public vocabulary with byte fallback: ids, and how many of them are byte pieces."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = self.model.get_piece_size()
        self.is_byte = np.fromiter((self.model.is_byte(i) for i in range(size)), bool, size)
        self.forget()
        _kept.append(self)

    def __exit__(self, *_):
        self.forget()  # a rules stage is followed by others that need the room

    def forget(self) -> None:
        self.number: dict[str, int] = {}
        self.flat, self.at = np.zeros(0, np.int32), np.zeros(1, np.int64)

    def numbers(self, docs: list[list[str]]) -> np.ndarray:
        """A number for every word of the documents, in a row; ids_of() takes such numbers until the next call."""
        if len(self.number) > CACHED_WORDS // 2:
            self.forget()
        number = self.number
        new = list({w for ws in docs for w in ws if w not in number})
        if new:
            rows = self.model.encode(new, num_threads=1)
            for w in new:
                number[w] = len(number)
            lengths = np.fromiter(map(len, rows), np.int64, len(rows))
            self.flat = np.concatenate([self.flat, np.fromiter(chain.from_iterable(rows), np.int32, int(lengths.sum()))])
            self.at = np.concatenate([self.at, self.at[-1] + np.cumsum(lengths)])
        n = sum(map(len, docs))
        return np.fromiter(map(number.__getitem__, chain.from_iterable(docs)), np.int64, n)

    def ids_of(self, numbers: np.ndarray) -> np.ndarray:
        """The ids of these words in a row."""
        start, length = self.at[numbers], self.at[numbers + 1] - self.at[numbers]
        ends = np.cumsum(length)
        if not len(ends) or not ends[-1]:
            return np.zeros(0, np.int32)
        return self.flat[np.arange(ends[-1]) + np.repeat(start - (ends - length), length)]


@cache
def fertility_model(path: str) -> Fertility:
    return Fertility(path)
