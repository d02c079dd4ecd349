"""Relational forms that a corpus audit needs and Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, take: list[str], suffix: str = "_before") -> DataFrame:
    """Each left row with the last right row of the same `by` strictly before it. One shuffle on `by`: the sides are
    laid in one row of events and the last right value is carried forward. Of right rows at one time the greatest counts."""
    marked = F.struct(on, *take)
    both = left.withColumns({"__left": F.lit(1), "__r": F.lit(None).cast(right.select(marked.alias("s")).schema["s"].dataType)}).unionByName(
        right.select(by, on, marked.alias("__r"), F.lit(0).alias("__left")), allowMissingColumns=True
    )
    w = Window.partitionBy(by).orderBy(F.col(on), F.desc("__left"), "__r").rowsBetween(Window.unboundedPreceding, -1)
    seen = both.withColumn("__seen", F.last("__r", ignorenulls=True).over(w)).filter("__left = 1")
    return seen.select(*left.columns, *(F.col(f"__seen.{c}").alias(c + suffix) for c in [on, *take]))


def interval_join(left: DataFrame, right: DataFrame, by: str, on: str, seconds: int) -> DataFrame:
    """Pairs of the same `by` with right within `seconds` after left: an equi join on time buckets, then the exact condition.

    left and right carry distinct column names but for `by` and `on`; the right time comes out as `{on}_right`.
    """
    micros = lambda c: F.unix_micros(c.cast("timestamp"))  # noqa: E731  with or without a zone
    bucket = lambda c: F.floor(micros(c) / (seconds * 1_000_000))
    a = left.withColumn("__b", F.explode(F.array(bucket(F.col(on)), bucket(F.col(on)) + 1)))
    b = right.withColumnRenamed(on, f"{on}_right").withColumn("__b", bucket(F.col(f"{on}_right")))
    inside = (F.col(f"{on}_right") > F.col(on)) & (micros(F.col(f"{on}_right")) <= micros(F.col(on)) + seconds * 1_000_000)
    return a.join(b, [by, "__b"]).filter(inside).drop("__b")


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Points with the half-open ranges that hold them, by an equi join on cells of `width`."""
    cell = lambda c: F.floor(c / width)
    last = F.greatest(cell(F.col(high) - 1e-9), cell(F.col(low)))
    cells = ranges.withColumn("__c", F.explode(F.sequence(cell(F.col(low)), last)))
    return points.withColumn("__c", cell(F.col(value))).join(cells, "__c").filter((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__c")


def salted_join(big: DataFrame, small: DataFrame, on: str, salts: int = 16, spread: Column | None = None) -> DataFrame:
    """An inner join whose hot keys are dealt over `salts` tasks; the small side is repeated that often."""
    salt = F.pmod(spread if spread is not None else F.xxhash64(*big.columns), F.lit(salts)).cast("int")
    repeated = small.withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return big.withColumn("__s", salt).join(repeated, [on, "__s"]).drop("__s")


#: Keys with more than one part in so many of all rows are hot; there can't be as many of them.
HOT_PARTS = 500


def sized_join(big: DataFrame, small: DataFrame, on: str, n: str = "n", parts: int = HOT_PARTS, sizes: DataFrame | None = None) -> DataFrame:
    """An inner join of big with small on a column of which small has few rows for each value, big any number.

    small[n], or sizes(on, n), says how many rows of big have a value. Rows of hot values stay where they are and meet
    the hot rows of small in a broadcast: of fewer than `parts` values, which go through the driver; the rest is
    shuffled. Nulls meet nulls.
    """
    slim, sizes = (small.drop(n), small) if sizes is None else (small, sizes)
    total, most = sizes.agg(F.sum(n), F.max(n)).first()
    if not total or most * parts <= total:
        return _null_safe(big, slim, on)
    values = [r[0] for r in sizes.filter(F.col(n) * parts > total).select(on).collect()]
    hot = F.coalesce(F.col(on).isin([v for v in values if v is not None]), F.lit(None in values))
    return _null_safe(big.filter(hot), F.broadcast(slim.filter(hot)), on).unionByName(_null_safe(big.filter(~hot), slim.filter(~hot), on))


def _null_safe(big: DataFrame, small: DataFrame, on: str) -> DataFrame:
    return big.join(small.withColumnRenamed(on, "__k"), F.col(on).eqNullSafe(F.col("__k"))).drop("__k")


def share(df: DataFrame, value: str, *by: str) -> DataFrame:
    total = F.sum(value).over(Window.partitionBy(*(by or [F.lit(0)])))
    return df.withColumn("share", F.round(F.col(value) / total, 6))
