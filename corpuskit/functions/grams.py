"""Character n-grams of whole batches as 64-bit hashes, without a Python object for each."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_BASE = 0x9E3779B97F4A7C15


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit (the public splitmix64 finaliser)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def pieces(batch: pa.RecordBatch, column: str, limit: int = 1_000_000):
    """Slices of a batch that hold about `limit` bytes of text each, one row at least."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    group = (np.cumsum(sizes) - sizes) // limit
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]]) if len(sizes) else []
    for s, e in zip(starts, np.r_[starts[1:], len(sizes)] if len(sizes) else [], strict=True):
        yield batch.slice(int(s), int(e - s))


def gram_hashes(texts: list[str], n: int) -> tuple[np.ndarray, np.ndarray]:
    """(text index, hash) of every n-gram in order, repeats included."""
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    doc = np.repeat(np.arange(len(texts)), lengths)
    m = len(points) - n + 1
    if m <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    total = np.full(m, np.uint64(n))
    for j in range(n):
        total = total * np.uint64(_BASE) + points[j : j + m]
    whole = np.flatnonzero(doc[:m] == doc[n - 1 :])
    return doc[whole], mix(total[whole])


def distinct(doc: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each pair once, in order of text, of pairs in that order; sorted a text at a time."""
    hashes = hashes.copy()
    edges = np.flatnonzero(np.r_[True, doc[1:] != doc[:-1], True]) if len(doc) else np.zeros(0, np.int64)
    for s, e in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        hashes[s:e].sort()
    keep = np.ones(len(doc), bool)
    keep[1:] = (doc[1:] != doc[:-1]) | (hashes[1:] != hashes[:-1])
    return doc[keep], hashes[keep]


class Places:
    """Where hashes stand among sorted distinct keys. Their upper bits lead to the first key of a slot; only hashes of
    slots with more keys are searched for."""

    def __init__(self, keys: np.ndarray):
        bits = min(22, max(8, 4 + int(len(keys)).bit_length()))
        self.keys, self.shift = keys, np.uint64(64 - bits)
        self.low = np.searchsorted(keys >> self.shift, np.arange((1 << bits) + 1, dtype=np.uint64)).astype(np.int32)
        self.more = np.diff(self.low) > 1

    def of(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The place of each hash, or some place, and whether it is among the keys; there must be one key at least."""
        slot = (hashes >> self.shift).astype(np.int64)
        at = np.minimum(self.low[slot], len(self.keys) - 1)
        known = self.keys[at] == hashes
        rest = np.flatnonzero(self.more[slot] & ~known)
        if len(rest):
            at[rest] = np.minimum(np.searchsorted(self.keys, hashes[rest]), len(self.keys) - 1)
            known[rest] = self.keys[at[rest]] == hashes[rest]
        return at, known
