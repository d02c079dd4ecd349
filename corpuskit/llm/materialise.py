"""Training-order shards of token ids.

Token ids of an input split, an end token after each document, are laid in a row and cut into sequences of one
length (the last is filled up with `PAD`). Sequences are numbered 0 to n - 1; a keyed Feistel network over the
least even number of bits that holds n, walked along its cycle until the value is below n, gives each its slot. Slot
ranges are shards: shard s holds the slots s * rows to (s + 1) * rows - 1 in order, each a record of fixed stride, so
a reader finds slot x at byte (x mod rows) * stride of shard x div rows and can go on from any slot.

A record is the ids as little-endian unsigned 16-bit numbers and one line feed, which Spark's text writer puts after
each row; that writer's committer makes the shards safe against lost tasks and works on every Hadoop file system.
Beside the shards lies the manifest: which pieces of which documents stand where.

Defined results: a null or empty text is its end token alone; a null doc_id stays null; repeated rows are laid out as
often as they come; an empty table gives no shard and an empty manifest. Which sequence a document falls in follows
the input's splits. Columns besides doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.functions import pandas_udf

from corpuskit.llm.batches import mix, pieces
from corpuskit.llm.vocab import vocab_path, word_bpe
from corpuskit.session import new_path, ship, staged

LENGTH, END, PAD = 4096, 1, 0
ROWS, KEY, ROUNDS = 2048, 20_240_607, 6
STRIDE = 2 * LENGTH + 1
#: Level of the compression in which sequences wait and travel: of 8 kB of ids the fifth makes 1 % less in nearly three times the time.
LEVEL = 2
#: Input splits whose first numbers are broadcast at most (12 bytes each); those of more splits are joined by a shuffle.
BROADCAST_PARTS = 1_000_000
_SPAN = "doc_id long, start long, length int, offset int, ids_crc32 long"
MANIFEST = "slot long, shard int, byte_offset long, doc_id long, start long, length int, offset int, ids_crc32 long"


class Permutation:
    """A keyed permutation of 0 to n - 1."""

    def __init__(self, n: int, key: int = KEY, rounds: int = ROUNDS):
        self.n, self.half = n, max(1, (max(n - 1, 1).bit_length() + 1) // 2)
        self.keys = [int.from_bytes(hashlib.sha256(f"{key}:{i}".encode()).digest()[:8], "little") for i in range(rounds)]

    def _once(self, x: np.ndarray, keys: list[int], back: bool) -> np.ndarray:
        half, low = np.uint64(self.half), np.uint64((1 << self.half) - 1)
        a, b = x >> half, x & low
        for k in keys:
            if back:
                a, b = b ^ (mix(a + np.uint64(k)) & low), a
            else:
                a, b = b, a ^ (mix(b + np.uint64(k)) & low)
        return (a << half) | b

    def _walk(self, x: np.ndarray, keys: list[int], back: bool) -> np.ndarray:
        out = self._once(np.asarray(x, np.uint64), keys, back)
        while len(far := np.flatnonzero(out >= self.n)):
            out[far] = self._once(out[far], keys, back)
        return out.astype(np.int64)

    def slot(self, index: np.ndarray) -> np.ndarray:
        return self._walk(index, self.keys, False)

    def index(self, slot: np.ndarray) -> np.ndarray:
        return self._walk(slot, self.keys[::-1], True)


def _lay(path: str, length: int):
    end = np.array([END], "<u2").tobytes()
    pad = np.array([PAD], "<u2").tobytes()
    kinds = {"doc_id": pa.int64(), "start": pa.int64(), "length": pa.int32(), "offset": pa.int32(), "ids_crc32": pa.int64()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(LEVEL)
        part, local = TaskContext.get().partitionId(), 0
        held, filled = [], 0
        rows: list[tuple] = []
        spans, ends = tuple([] for _ in kinds), [0]

        def close() -> None:
            nonlocal filled, local
            record = b"".join(held) + pad * (length - filled)
            rows.append((local, press.compress(record)))
            held.clear()
            ends.append(len(spans[0]))
            filled, local = 0, local + 1

        def out() -> pa.RecordBatch:
            whole = pa.StructArray.from_arrays([pa.array(x[: ends[-1]], t) for x, t in zip(spans, kinds.values(), strict=True)], list(kinds))
            batch = pa.RecordBatch.from_arrays(
                [pa.array([part] * len(rows), pa.int32()), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), whole)],
                ["part", "local", "packed", "spans"],
            )
            rows.clear()
            for x in spans:  # those of the sequence that is not full yet stay
                del x[: ends[-1]]
            ends[:] = [0]
            return batch

        with word_bpe(path) as model:
            if len(model.closes) > 1 << 16:
                raise ValueError(f"ids of {path} don't fit in 16 bits")
            for whole in batches:
                for batch in pieces(whole, "text"):
                    for doc, ids in zip(batch.column("doc_id").to_pylist(), model.ids(batch.column("text").to_pylist()), strict=True):
                        ids = np.frombuffer(ids, "<u4").astype("<u2").tobytes() + end
                        at, n = 0, len(ids) // 2
                        while at < n:
                            take = min(n - at, length - filled)
                            own = ids[2 * at : 2 * (at + take)]
                            for x, value in zip(spans, (doc, at, take, filled, zlib.crc32(own)), strict=True):
                                x.append(value)
                            held.append(own)
                            at, filled = at + take, filled + take
                            if filled == length:
                                close()
                    if rows:
                        yield out()
        if filled:
            close()
        if rows:
            yield out()

    return run


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    opened = zstandard.ZstdDecompressor()
    for batch in batches:
        yield pa.RecordBatch.from_arrays([pa.array([opened.decompress(x) for x in batch.column("packed").to_pylist()], pa.binary())], ["record"])


def write(docs: DataFrame, path: str, length: int = LENGTH, rows: int = ROWS, key: int = KEY, vocab: str | None = None) -> DataFrame:
    """Write shards and manifest under `path`; return the manifest."""
    spark = docs.sparkSession
    ship(spark)
    lay = _lay(vocab_path("word_bpe_49k.json", vocab), length)
    laid = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lay, f"part int, local long, packed binary, spans array<struct<{_SPAN.replace(' ', ': ').replace(',:', ',')}>>")
    laid = staged(laid, "sequences")
    # a row for each input split, so its size follows the number of files read and not their rows
    parts = sorted((r[0], r[1]) for r in laid.groupBy("part").count().collect())
    begins, n = [], 0
    for part, count in parts:
        begins.append((part, n))
        n += count
    order, stride = Permutation(n, key), 2 * length + 1

    @pandas_udf("long")
    def slot_of(index):
        import pandas as pd

        return pd.Series(order.slot(index.to_numpy()))

    begin = spark.createDataFrame(begins, "part int, begin long")
    begin = F.broadcast(begin) if len(begins) <= BROADCAST_PARTS else begin
    placed = laid.join(begin, "part").withColumn("slot", slot_of(F.col("begin") + F.col("local"))).withColumn("shard", F.floor(F.col("slot") / F.lit(rows)).cast("int"))
    shards = max(1, -(-n // rows))
    dealt = placed.select("shard", "slot", "packed").repartitionById(shards, F.col("shard")).sortWithinPartitions("slot")
    dealt.select("packed").mapInArrow(_unpack, "record binary").select(F.col("record").cast("string").alias("value")).write.text(f"{path}/shards")
    named = placed.select("slot", "shard", (F.pmod("slot", F.lit(rows)) * stride).cast("long").alias("byte_offset"), F.explode("spans").alias("s")).select("slot", "shard", "byte_offset", "s.*")
    named.write.parquet(f"{path}/manifest")
    return spark.read.schema(MANIFEST).parquet(f"{path}/manifest")


def _records(length: int, rows: int, first: int, last: int):
    stride = 2 * length + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data in zip(batch.column("path").to_pylist(), batch.column("content").to_pylist(), strict=True):
                base = int(name.rsplit("/part-", 1)[1].split("-", 1)[0]) * rows
                table = np.frombuffer(data, np.uint8).reshape(-1, stride)
                low, high = max(0, first - base), min(len(table), last - base)
                if low < high:
                    ids = np.ascontiguousarray(table[low:high, :-1]).view("<u2").astype(np.int32)
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(base + low, base + high)), pa.array(list(ids), pa.list_(pa.int32()))], ["slot", "ids"])

    return run


def read(spark: SparkSession, path: str, first: int = 0, last: int = 2**62, length: int = LENGTH, rows: int = ROWS) -> DataFrame:
    """(slot, ids) of the slots from `first` to below `last`; only the shards that hold them are opened."""
    ship(spark)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(f"{path}/shards")
    shard = F.regexp_extract("path", "/part-(\\d+)-[^/]*$", 1).cast("long")
    wanted = files.filter((shard >= first // rows) & (shard <= (last - 1) // rows))
    return wanted.select("path", "content").mapInArrow(_records(length, rows, first, last), "slot long, ids array<int>")


def training_order(docs: DataFrame, path: str | None = None) -> DataFrame:
    return write(docs, path or new_path(docs.sparkSession, "training-order"))
