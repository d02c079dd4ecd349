"""Documents from several upstream forms, with provenance and order."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from corpuskit.config import DEFAULT, Config
from corpuskit.functions import text as T

DOCUMENT = "doc_id long, source string, text string"


def read_jsonl(spark: SparkSession, path: str, schema: str = DOCUMENT, parts: int | None = None) -> DataFrame:
    """JSON lines, zipped or not. Zipped files aren't splittable: `parts` deals their rows out after reading."""
    rows = spark.read.schema(schema).json(path)
    return rows.repartition(parts) if parts else rows


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pages_as_documents(pages: DataFrame, source: str = "pages") -> DataFrame:
    return pages.select(F.col("page_id").alias("doc_id"), F.lit(source).alias("source"), T.page_text(F.col("html")).alias("text"))


def source_rank(source: Column, order: tuple[str, ...]) -> Column:
    """The place of a source in the configured order; unknown sources come last."""
    ranks = F.create_map(*[F.lit(x) for i, s in enumerate(order) for x in (s, i)])
    return F.coalesce(ranks[source], F.lit(len(order))).cast("int")


def with_roles(docs: DataFrame, config: Config = DEFAULT) -> DataFrame:
    roles = F.create_map(*[F.lit(x) for pair in config.roles for x in pair])
    return docs.withColumns({"source_rank": source_rank(F.col("source"), config.source_order), "role": F.coalesce(roles[F.col("source")], F.lit("other"))})


def aggregate(parts: list[DataFrame], config: Config = DEFAULT) -> DataFrame:
    """The bag union of documents, whatever columns each part has, with rank and role of the source."""
    return with_roles(reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts), config)
