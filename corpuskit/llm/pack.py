"""Best-fit packing of token sequences with a bounded number of open bins.

Open bins hang in stacks by their free space; a bitset has a bit for each space in use, so the tightest bin that
takes a piece is the lowest set bit at or above its length. When a new bin would exceed the number that may be open,
the fullest closes. Each group of pieces comes longest first, in a task of its own; only ids and lengths move.

Defined results: a null or empty text is the end token alone; repeated rows are packed as often as they come; a null
doc_id stays null; an empty table gives an empty result. Columns besides doc_id and text are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.batches import pieces
from corpuskit.llm.vocab import vocab_path, word_bpe
from corpuskit.session import ship, staged

END, CAPACITY, OPEN_BINS = 1, 4096, 16_384
#: Pieces that one task packs, about.
GROUP = 65_536
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PACKED = PIECES + ", sequence_id long, offset long"


class OpenBins:
    """Bins that still take pieces."""

    def __init__(self, capacity: int = CAPACITY, most: int = OPEN_BINS):
        self.capacity, self.most = capacity, most
        self.bits, self.open, self.made = 0, 0, 0
        self.stacks: list[list[int]] = [[] for _ in range(capacity + 1)]

    def _take(self, free: int) -> int:
        stack = self.stacks[free]
        found = stack.pop()
        if not stack:
            self.bits ^= 1 << free
        self.open -= 1
        return found

    def place(self, length: int) -> tuple[int, int]:
        """The bin for a piece, and where in it the piece begins."""
        fitting = self.bits >> length
        if fitting:
            free = length + (fitting & -fitting).bit_length() - 1
            found = self._take(free)
        else:
            if self.open == self.most:
                self._take((self.bits & -self.bits).bit_length() - 1)
            found, free = self.made, self.capacity
            self.made += 1
        if left := free - length:
            self.stacks[left].append(found)
            self.bits |= 1 << left
            self.open += 1
        return found, self.capacity - free


def _cut(path: str, capacity: int):
    end = np.array([END], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with word_bpe(path) as model:
            for whole in batches:
                for batch in pieces(whole, "text"):
                    docs, numbers, starts, lengths, sums = [], [], [], [], []
                    for doc, ids in zip(batch.column("doc_id").to_pylist(), model.ids(batch.column("text").to_pylist()), strict=True):
                        ids += end
                        for k, s in enumerate(range(0, len(ids), 4 * capacity)):
                            part = ids[s : s + 4 * capacity]
                            docs.append(doc)
                            numbers.append(k)
                            starts.append(s // 4)
                            lengths.append(len(part) // 4)
                            sums.append(zlib.crc32(part))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(docs, pa.int64()), pa.array(numbers, pa.int32()), *(pa.array(x, pa.int64()) for x in (starts, lengths, sums))],
                        ["doc_id", "piece", "start", "length", "ids_crc32"],
                    )

    return run


def cut(docs: DataFrame, capacity: int = CAPACITY, vocab: str | None = None) -> DataFrame:
    """The pieces of every document, of `capacity` tokens at most; only longer documents are cut."""
    ship(docs.sparkSession)
    path = vocab_path("word_bpe_49k.json", vocab)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_cut(path, capacity), PIECES)


def _pack(capacity: int, open_bins: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bins, base = OpenBins(capacity, open_bins), TaskContext.get().partitionId() << 33
        for batch in batches:
            placed = [bins.place(x) for x in batch.column("length").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [*batch.columns, pa.array([base + b for b, _ in placed], pa.int64()), pa.array([o for _, o in placed], pa.int64())],
                [*batch.schema.names, "sequence_id", "offset"],
            )

    return run


def pack(cuts: DataFrame, capacity: int = CAPACITY, open_bins: int = OPEN_BINS, group: int = GROUP) -> DataFrame:
    """Pieces with sequence_id and offset. `cuts` has the columns of PIECES and is read twice."""
    groups = -(-cuts.count() // group) or 1
    dealt = cuts.repartition(groups, F.xxhash64("doc_id", "piece", "ids_crc32"))
    return dealt.sortWithinPartitions(F.desc("length"), "doc_id", "piece", "ids_crc32").mapInArrow(_pack(capacity, open_bins), PACKED)


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, open_bins: int = OPEN_BINS, vocab: str | None = None) -> DataFrame:
    """Tokenise, cut and pack: one row for each piece."""
    return pack(staged(cut(docs, capacity, vocab), "pieces"), capacity, open_bins)
