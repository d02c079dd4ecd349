"""Order, split, release files, and removal of evaluation passages."""

from __future__ import annotations

import datetime as dt
import json

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.config import DEFAULT, Config
from corpuskit.functions.text import word_grams


def shuffle_key(doc_id: Column, seed: int = 0) -> Column:
    """A key that orders documents at random and doesn't depend on how they are partitioned."""
    return F.md5(F.concat(F.lit(f"{seed}|"), doc_id.cast("string")))


def shuffle(docs: DataFrame, seed: int = 0) -> DataFrame:
    return docs.withColumn("shuffle_key", shuffle_key(F.col("doc_id"), seed)).orderBy("shuffle_key", "doc_id")


def places(docs: DataFrame, seed: int = 0, digits: int = 3) -> DataFrame:
    """(doc_id, place): the 1-based place of each document in the shuffled order, without ordering all in one task.

    Prefixes of the key are counted and numbered first, then each document within its prefix.
    """
    keyed = docs.select("doc_id", shuffle_key(F.col("doc_id"), seed).alias("k")).withColumn("p", F.substring("k", 1, digits))
    before = Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)
    # 16**digits rows at most
    begins = keyed.groupBy("p").agg(F.count("*").alias("n")).select("p", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("begin"))
    within = F.row_number().over(Window.partitionBy("p").orderBy("k", "doc_id"))
    return keyed.join(F.broadcast(begins), "p").select("doc_id", (F.col("begin") + within).alias("place"))


def _number(key: Column, digits: int) -> Column:
    return F.conv(F.substring(key, 1, digits), 16, 10).cast("long")


def split(docs: DataFrame, percent: int = DEFAULT.split_percent, how: str = "exact", seed: int = 0) -> DataFrame:
    """docs with `split`. exact: the first floor(percent N / 100) of the shuffled order train; hash: by threshold, without order."""
    keyed = docs.withColumn("shuffle_key", shuffle_key(F.col("doc_id"), seed))
    if how == "hash":
        train = _number(F.col("shuffle_key"), 8) < F.lit((1 << 32) * percent // 100)
        return keyed.withColumn("split", F.when(train, "train").otherwise("val")).drop("shuffle_key")
    if how != "exact":
        raise ValueError(f"how is exact or hash, not {how}")
    n = keyed.count()
    cut = n * percent // 100
    if cut >= n:
        return keyed.withColumn("split", F.lit("train")).drop("shuffle_key")
    last = _key_at(keyed.select("shuffle_key"), cut)
    return keyed.withColumn("split", F.when(F.col("shuffle_key") < last, "train").otherwise("val")).drop("shuffle_key")


def _key_at(keys: DataFrame, k: int, digits: int = 4, most: int = 100_000) -> str:
    """The key at 0-based place k, by counting prefixes: the driver sees 16**digits rows or `most` keys at a time."""
    prefix, depth = "", digits
    while True:
        inside = keys.filter(F.col("shuffle_key").startswith(prefix)) if prefix else keys
        for p, n in inside.groupBy(F.substring("shuffle_key", 1, depth).alias("p")).count().orderBy("p").collect():
            if k < n:
                break
            k -= n
        if n <= most or depth >= 32:
            return sorted(r[0] for r in keys.filter(F.col("shuffle_key").startswith(p)).collect())[k]
        prefix, depth = p, depth + digits


def decontaminate(docs: DataFrame, evaluation: DataFrame, n: int = 8, text: str = "clean") -> DataFrame:
    """docs without those that share a word n-gram with the evaluation texts (column `text`)."""
    return docs.join(contaminated(docs, evaluation, n, text), "doc_id", "left_anti")


def contaminated(docs: DataFrame, evaluation: DataFrame, n: int = 8, text: str = "clean") -> DataFrame:
    from corpuskit.functions.text import collapse_ws

    known = evaluation.select(F.explode(word_grams(collapse_ws(F.col("text")), n)).alias("gram")).distinct()
    return docs.select("doc_id", F.explode(word_grams(F.col(text), n)).alias("gram")).join(known, "gram", "left_semi").select("doc_id").distinct()


def write(docs: DataFrame, path: str, config: Config = DEFAULT, form: str = "parquet", files: int = 8) -> dict:
    """Write docs(doc_id, split, ...) in shuffled order by split, with a manifest; return the manifest."""
    spark = docs.sparkSession
    laid = docs.withColumn("shuffle_key", shuffle_key(F.col("doc_id"), config.seed)).repartitionByRange(files, "split", "shuffle_key").sortWithinPartitions("split", "shuffle_key").drop("shuffle_key")
    writer = laid.write.mode("overwrite").partitionBy("split")
    (writer.parquet(f"{path}/data") if form == "parquet" else writer.option("compression", "gzip").json(f"{path}/data"))
    counts = {r["split"]: r["count"] for r in docs.groupBy("split").count().collect()}
    manifest = {"config": config.digest(), "seed": config.seed, "form": form, "counts": counts, "spark": spark.version}
    spark.createDataFrame([(json.dumps(manifest, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")
    return manifest


def card(title: str, config: Config, tables: dict[str, DataFrame], rows: int = 200) -> str:
    """A dataset card in Markdown. Report tables are small by nature; `rows` is how many of each are printed."""
    out = [f"# {title}", "", f"Config {config.digest()}, seeds {config.seed}, written {dt.date.today().isoformat()}.", ""]
    for name, table in tables.items():
        out += [f"## {name}", "", "| " + " | ".join(table.columns) + " |", "|" + "---|" * len(table.columns)]
        out += ["| " + " | ".join("" if v is None else str(v) for v in r) + " |" for r in table.limit(rows).collect()] + [""]
    return "\n".join(out)
