"""Token counts kept by signed deltas.

A change inserts, revises or deletes the count of one document under one tokenizer version. Against the live row of
that document the change becomes signed ledger rows: minus what was live, plus what now is. A batch's ledger rows are
summed by source, language and tokenizer into a small table of deltas; totals are the sum of the committed deltas, so
they never need the documents again.

Commits: a batch writes its ledger, then its deltas, each through Spark's committer, and counts once its deltas have
the success mark. A committed batch is skipped when it comes again; one that broke off is written anew.

Ledgers lie in buckets of doc_id, and a batch reads the buckets of its own documents alone. compact() sums what is
committed into a snapshot of live rows and totals; later batches read that and what came after it, so a batch's cost
follows its documents and not the history. Compacting comes due by itself after `COMPACT_AFTER` batches.

Defined results: inserting a live document revises it, revising one that is not live inserts it, deleting one that is
not live does nothing; of several changes of one document in a batch the greatest `turn` counts (ties: the greatest
operation, then count); a document without an id can be inserted, every time anew, and is never revised or deleted:
such a change, or one without a tokenizer, is refused with an error; null sources and languages are groups of their
own; an empty batch commits and changes nothing.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpuskit.llm.batches import pieces
from corpuskit.llm.vocab import fertility_model, vocab_path, word_bpe
from corpuskit.operators.relational import sized_join
from corpuskit.session import new_path, ship, staged

KEY = ["doc_id", "tokenizer"]
GROUP = ["source", "lang", "tokenizer"]
MEASURES = ["n_docs", "n_tokens", "n_chars"]
#: Folders that a ledger is dealt into by doc_id, and batches after which they are summed.
BUCKETS, COMPACT_AFTER = 32, 16
LEDGER = "doc_id long, tokenizer string, source string, lang string, n_docs long, n_tokens long, n_chars long, bucket int"
CHANGES = "doc_id long, tokenizer string, source string, lang string, op string, turn long, n_tokens long, n_chars long"
DELTAS = "source string, lang string, tokenizer string, n_docs long, n_tokens long, n_chars long"


class Rollup:
    """Totals in a folder that all executors share."""

    def __init__(self, spark: SparkSession, path: str, buckets: int = BUCKETS, compact_after: int = COMPACT_AFTER):
        self.spark, self.path, self.buckets, self.compact_after = spark, path.rstrip("/"), buckets, compact_after

    def _exists(self, path: str) -> bool:
        place = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return place.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(place)

    def _done(self, kind: str) -> list[str]:
        """Names under a folder that have the success mark."""
        root = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}")
        system = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not system.exists(root):
            return []
        return sorted(s.getPath().getName() for s in system.listStatus(root) if self._exists(f"{s.getPath().toString()}/_SUCCESS"))

    def committed(self) -> list[str]:
        return self._done("deltas")

    def _snapshot(self) -> tuple[str | None, set[str]]:
        """The last snapshot and the batches in it. Its list of batches is written last."""
        done = self._done("snapshots")
        if not done:
            return None, set()
        return done[-1], {r[0] for r in self.spark.read.schema("batch string").parquet(f"{self.path}/snapshots/{done[-1]}").collect()}

    def _read(self, kind: str, schema: str) -> DataFrame:
        """Committed rows: those of the last snapshot and of the batches after it."""
        last, within = self._snapshot()
        paths = [f"{self.path}/{kind}/{b}" for b in self.committed() if b not in within]
        paths += [f"{self.path}/snapshot-{kind}/{last}"] if last else []
        parts = [self.spark.read.schema(schema).parquet(p) for p in paths]
        return reduce(DataFrame.unionByName, parts) if parts else self.spark.createDataFrame([], schema)

    def live(self) -> DataFrame:
        """The live row of each document and tokenizer: what the signed ledger sums to."""
        rows = self._read("ledger", LEDGER).groupBy(*KEY, "bucket", "source", "lang").agg(*(F.sum(c).alias(c) for c in MEASURES))
        return rows.filter("n_docs > 0")

    def _write_ledger(self, rows: DataFrame, path: str) -> None:
        placed = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id"), F.lit(self.buckets)).cast("int"))
        # documents without an id would else all lie in one bucket's one task
        spread = F.when(F.col("doc_id").isNull(), F.pmod(F.xxhash64("source", "lang", "n_tokens", "n_chars"), F.lit(self.buckets))).otherwise(0)
        placed.repartition("bucket", spread).write.mode("overwrite").partitionBy("bucket").parquet(path)

    def apply(self, batch: str, changes: DataFrame) -> bool:
        """Commit a batch of changes; False if it is committed already."""
        if self._exists(f"{self.path}/deltas/{batch}/_SUCCESS"):
            return False
        refused = F.raise_error(F.lit("a change needs a tokenizer, and a doc_id unless it inserts"))
        wrong = F.col("tokenizer").isNull() | (F.col("doc_id").isNull() & ~F.col("op").eqNullSafe(F.lit("insert")))
        checked = changes.withColumn("tokenizer", F.when(wrong, refused).otherwise(F.col("tokenizer")))
        order = Window.partitionBy(*KEY).orderBy(F.desc("turn"), F.desc("op"), F.desc("n_tokens"), F.desc("n_chars"), F.desc("source"), F.desc("lang"))
        last = checked.filter("doc_id is not null").withColumn("rank", F.row_number().over(order)).filter("rank = 1")
        plus = last.filter("op != 'delete'").drop("rank").unionByName(checked.filter("doc_id is null"))
        ledger = plus.select(*KEY, "source", "lang", F.lit(1).cast("long").alias("n_docs"), "n_tokens", "n_chars")
        if self.committed():
            touched = last.select(F.pmod(F.xxhash64("doc_id"), F.lit(self.buckets)).cast("int").alias("b")).distinct().collect()  # BUCKETS rows at most
            was = self.live().filter(F.col("bucket").isin([r[0] for r in touched])).join(last.select(*KEY), KEY, "left_semi")
            ledger = ledger.unionByName(was.select(*KEY, "source", "lang", *((-F.col(c)).alias(c) for c in MEASURES)))
        self._write_ledger(ledger, f"{self.path}/ledger/{batch}")
        rows = self.spark.read.schema(LEDGER).parquet(f"{self.path}/ledger/{batch}")
        deltas = rows.groupBy(*GROUP).agg(*(F.sum(c).alias(c) for c in MEASURES)).filter("n_docs != 0 or n_tokens != 0 or n_chars != 0")
        deltas.write.mode("overwrite").parquet(f"{self.path}/deltas/{batch}")
        if len(set(self.committed()) - self._snapshot()[1]) >= self.compact_after:
            self.compact()
        return True

    def compact(self) -> None:
        """Sum all committed batches into a snapshot. It counts once its list of batches has the success mark."""
        batches = self.committed()
        name = f"{len(self._done('snapshots')):08d}"
        self._write_ledger(self.live().drop("bucket"), f"{self.path}/snapshot-ledger/{name}")
        self.totals().select(*GROUP, *MEASURES).write.mode("overwrite").parquet(f"{self.path}/snapshot-deltas/{name}")
        self.spark.createDataFrame([(b,) for b in batches], "batch string").write.mode("overwrite").parquet(f"{self.path}/snapshots/{name}")

    def totals(self) -> DataFrame:
        """(source, lang, tokenizer, n_docs, n_tokens, n_chars) over all committed batches; groups that came to nothing are left out."""
        rows = self._read("deltas", DELTAS).groupBy(*GROUP).agg(*(F.sum(c).alias(c) for c in MEASURES))
        return rows.filter("n_docs != 0 or n_tokens != 0 or n_chars != 0")

    def rollup(self) -> DataFrame:
        """Totals by source, language and tokenizer with their subtotals; level 0 is a single group, 3 a whole tokenizer."""
        return (
            self.totals()
            .groupingSets([["tokenizer", "source", "lang"], ["tokenizer", "source"], ["tokenizer"]], "tokenizer", "source", "lang")
            .agg(F.grouping_id().cast("int").alias("level"), *(F.sum(c).alias(c) for c in MEASURES))
            .select("tokenizer", "source", "lang", "level", *MEASURES)
        )


#: Tokenizer versions that count() knows.
VERSIONS = ("word_bpe_49k", "piece_bpe_32k")


def _count(paths: dict[str, str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = {v: (word_bpe if v == "word_bpe_49k" else fertility_model)(path) for v, path in paths.items()}
        for whole in batches:
            for batch in pieces(whole, "text"):
                text = pc.fill_null(batch.column("text").cast(pa.large_string()), "")
                texts, chars = text.to_pylist(), pc.utf8_length(text).cast(pa.int64())
                for version, model in models.items():
                    if version == "word_bpe_49k":
                        counts = [len(x) // 4 for x in model.ids(texts)]
                    else:
                        words = [x.split() for x in texts]
                        numbers = model.numbers(words)
                        upto = np.r_[0, np.cumsum(model.at[numbers + 1] - model.at[numbers])]
                        counts = np.diff(upto[np.r_[0, np.cumsum([len(ws) for ws in words])]])
                    n = batch.num_rows
                    yield pa.RecordBatch.from_arrays(
                        [batch.column("doc_id"), pa.array([version] * n, pa.string()), batch.column("source"), batch.column("lang"), batch.column("copy"), pa.array(counts, pa.int64()), chars],
                        ["doc_id", "tokenizer", "source", "lang", "copy", "n_tokens", "n_chars"],
                    )

    return run


def count(docs: DataFrame, versions: tuple[str, ...] = VERSIONS, vocab: str | None = None) -> DataFrame:
    """A row for each document and tokenizer version; copy is a 128-bit mark that equal texts share."""
    ship(docs.sparkSession)
    files = {"word_bpe_49k": "word_bpe_49k.json", "piece_bpe_32k": "piece_bpe_32k.model"}
    paths = {v: vocab_path(files[v], vocab) for v in versions}
    rows = docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), F.col("lang").cast("string"), F.col("text").cast("string"), F.md5(F.encode(F.coalesce("text", F.lit("")), "UTF-8")).alias("copy"))
    return rows.mapInArrow(_count(paths), "doc_id long, tokenizer string, source string, lang string, copy string, n_tokens long, n_chars long")


def maintained(docs: DataFrame, path: str | None = None, vocab: str | None = None) -> DataFrame:
    """The rollup after three batches: all documents inserted under the first tokenizer version; revised counts, each
    document's end token included; exact repeats deleted and every document inserted under the second version. Each
    batch comes twice, as it does after a retry; the second time it changes nothing. Rows that share a doc_id are one
    document; rows without one are counted under both versions, without an end token, and never taken for repeats."""
    spark = docs.sparkSession
    path = path or new_path(spark, "rollup")
    counted = count(docs, vocab=vocab)
    counted.write.parquet(f"{path}/counted")
    counted = spark.read.schema(counted.schema).parquet(f"{path}/counted")
    first, second = (counted.filter(F.col("tokenizer") == v) for v in VERSIONS)
    known = first.filter("doc_id is not null")
    change = lambda rows, op, extra=0: rows.select(*KEY, "source", "lang", F.lit(op).alias("op"), F.lit(0).cast("long").alias("turn"), (F.col("n_tokens") + extra).alias("n_tokens"), "n_chars")
    originals = staged(known.groupBy("copy").agg(F.min("doc_id").alias("original"), F.count("*").alias("n")).filter("n > 1"), "originals")
    repeats = sized_join(known, originals, "copy").filter("doc_id != original")
    state = Rollup(spark, path)
    steps = (("0", change(first, "insert")), ("1", change(known, "revise", 1)), ("2", change(repeats, "delete").unionByName(change(second, "insert"))))
    for batch, changes in steps:
        for _ in range(2):
            state.apply(batch, changes)
    return state.rollup()
