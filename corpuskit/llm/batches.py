"""Arrow batches in bounded pieces, and words hashed straight from their UTF-8 bytes."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once; a single longer text makes a piece of its own.
PIECE_BYTES = 500_000
#: Freed blocks of so many bytes go back to the system at once. The C library would else raise the bound with every
#: block freed and keep most of what a piece needed, for as long as the Python worker lives.
GIVEN_BACK, _MMAP_THRESHOLD, _ARENAS = 1 << 18, -3, -8

if (_mallopt := getattr(ctypes.CDLL(None), "mallopt", None)) is not None:
    _mallopt(_MMAP_THRESHOLD, GIVEN_BACK)
    _mallopt(_ARENAS, 1)
    pa.set_memory_pool(pa.system_memory_pool())

_WHITE = np.zeros(256, bool)
_WHITE[[0x20, *range(0x09, 0x0E)]] = True
_PLAIN = np.zeros(256, bool)  # bytes that end a word when punctuation doesn't count
_PLAIN[:128] = True
_PLAIN[[*range(48, 58), *range(65, 91), *range(97, 123)]] = False

_VALUES = np.random.Generator(np.random.PCG64(20240607)).integers(0, 2**64, 256, dtype=np.uint64, endpoint=False)
_FOLDED = _VALUES.copy()
_FOLDED[65:91] = _VALUES[97:123]
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 2**64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit (the public splitmix64 finaliser)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _Powers:
    def __init__(self, base: int):
        self.base, self.table = base, np.ones(1, np.uint64)

    def upto(self, n: int) -> np.ndarray:
        if len(self.table) < n:
            full = np.full(max(n, 2 * len(self.table)), np.uint64(self.base))
            full[0] = 1
            self.table = np.multiply.accumulate(full)
        return self.table[:n]


_up, _down = _Powers(_BASE), _Powers(_INVERSE)
#: The first n powers of an odd number, and of its inverse: a sum over words i to j of word x power, times the inverse
#: power of i, is the same wherever the words stand.
ups, downs = _up.upto, _down.upto


def pieces(batch: pa.RecordBatch, column: str, limit: int = PIECE_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch that hold about `limit` bytes of text each, one row at least."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    if not len(sizes):
        return
    before = np.cumsum(sizes) - sizes
    group = before // limit
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    for s, e in zip(starts, np.r_[starts[1:], len(sizes)], strict=True):
        yield batch.slice(int(s), int(e - s))


class Words:
    """Words of a column of texts: hash, document index, byte place in its text; `first[i]:first[i+1]` are those of text i."""

    def __init__(self, texts: pa.Array, *, fold: bool = True, plain: bool = True):
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        if isinstance(texts, pa.ChunkedArray):
            texts = texts.combine_chunks()
        n = len(texts)
        offsets = np.frombuffer(texts.buffers()[1], np.int64, n + 1, 8 * texts.offset) if n else np.zeros(1, np.int64)
        size = int(offsets[-1] - offsets[0])
        data = np.frombuffer(texts.buffers()[2], np.uint8, size, int(offsets[0])) if size else np.zeros(0, np.uint8)
        offsets = offsets - offsets[0]
        inside = ~(_PLAIN if plain else _WHITE)[data]
        edge = np.zeros(size + 1, bool)
        edge[offsets] = True
        before = np.r_[False, inside[:-1]] if size else inside
        after = np.r_[inside[1:], False] if size else inside
        self.start = np.flatnonzero(inside & (~before | edge[:-1]))
        self.end = np.flatnonzero(inside & (~after | edge[1:])) + 1
        sums = np.zeros(size + 1, np.uint64)
        np.cumsum((_FOLDED if fold else _VALUES)[data] * _up.upto(size), out=sums[1:])
        self.hash = mix((sums[self.end] - sums[self.start]) * _down.upto(size + 1)[self.start] + (self.end - self.start).astype(np.uint64))
        self.first = np.searchsorted(self.start, offsets)
        self.doc = np.repeat(np.arange(n), np.diff(self.first))
        self.offsets, self.n = offsets, n


def windows(words: Words, mask: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """For every place where a window of the mask's span fits in one text: the word index and the hash of the masked words.

    mask: the word positions that count, from 0.
    """
    span = mask[-1] + 1
    m = len(words.hash) - span + 1
    if m <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    total = np.zeros(m, np.uint64)
    for j, p in enumerate(mask):
        total += words.hash[p : p + m] * np.uint64(pow(_BASE, 2 * j + 3, 2**64))
    at = np.flatnonzero(words.doc[:m] == words.doc[span - 1 :])
    return at, mix(total[at])
