"""SQL names of the library's functions: register(spark) makes them callable in spark.sql."""

from __future__ import annotations


from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from corpuskit.operators.neardup import PRIME, hash_family
from corpuskit.session import ship

# pure expressions, inlined by the optimizer
_EXPRESSIONS = {
    "ck_collapse_ws": ("t STRING", "STRING", "trim(regexp_replace(t, '[ \\\\t\\\\n\\\\r\\\\f\\\\x0B]+', ' '))"),
    "ck_content_key": ("t STRING", "STRING", "sha2(trim(regexp_replace(lower(t), '[ \\\\t\\\\n\\\\r\\\\f\\\\x0B]+', ' ')), 256)"),
    "ck_clean": ("t STRING", "STRING", "regexp_replace(trim(regexp_replace(t, '[ \\\\t\\\\n\\\\r\\\\f\\\\x0B]+', ' ')), '(?s)(.)\\\\1{3,}', '$1$1$1')"),
    "ck_shingles": ("t STRING", "ARRAY<STRING>", "array_distinct(get(transform(array(split(t, ' ')), ws -> CASE WHEN size(ws) >= 3 THEN transform(sequence(1, greatest(size(ws) - 2, 1)), i -> concat_ws(' ', slice(ws, i, 3))) ELSE CAST(array() AS ARRAY<STRING>) END), 0))"),
    "ck_jaccard": ("a ARRAY<STRING>, b ARRAY<STRING>", "DOUBLE", "size(array_intersect(a, b)) / (size(array_distinct(a)) + size(array_distinct(b)) - size(array_intersect(a, b)))"),
    "ck_char_grams": ("t STRING", "ARRAY<STRING>", "array_distinct(get(transform(array(split(t, '')), cs -> CASE WHEN size(cs) >= 5 THEN transform(sequence(0, greatest(size(cs) - 5, 0)), i -> concat(get(cs, i), get(cs, i + 1), get(cs, i + 2), get(cs, i + 3), get(cs, i + 4))) ELSE CAST(array() AS ARRAY<STRING>) END), 0))"),
}


def _signature() -> tuple[str, str, str]:
    minima = ", ".join(f"array_min(transform(h, x -> (x * {a}L + {c}L) % {PRIME}L))" for a, c in hash_family())
    return "h ARRAY<BIGINT>", "ARRAY<BIGINT>", f"CASE WHEN size(h) > 0 THEN array({minima}) END"


def register(spark: SparkSession, tokenizer=None, profile=None) -> None:
    """Register ck_* functions. ck_token_count and ck_lid exist if a trained tokenizer and a profile are given."""
    from pyspark.sql.functions import udtf
    from pyspark.sql.pandas.functions import pandas_udf

    ship(spark)
    for name, (args, kind, body) in (_EXPRESSIONS | {"ck_signature": _signature()}).items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")

    @udtf(returnType="place int, shingle string")
    class ShingleRows:
        def eval(self, text: str, n: int):
            words = (text or "").split()
            for i in range(len(words) - n + 1):
                yield i, " ".join(words[i : i + n])

    spark.udtf.register("ck_shingle_rows", ShingleRows)
    if tokenizer is not None:
        tokens = spark.sparkContext.broadcast(tokenizer)

        @pandas_udf("long")
        def token_count(texts):
            return texts.map(lambda t: len(tokens.value.encode(t or "")))

        spark.udf.register("ck_token_count", token_count)

        @udtf(returnType="place int, token string")
        class Tokens:
            def eval(self, text: str):
                yield from enumerate(tokens.value.encode(text or ""))

        spark.udtf.register("ck_tokens", Tokens)
    if profile is not None:
        model = spark.sparkContext.broadcast(profile)

        @pandas_udf("string")
        def identify(texts):
            import pandas as pd

            score, size = model.value.scores([f" {' '.join((t or '').lower().split())} " for t in texts])
            return pd.Series([model.value.labels[b] if n else None for b, n in zip(score.argmax(axis=1), size, strict=True)])

        spark.udf.register("ck_lid", identify)
