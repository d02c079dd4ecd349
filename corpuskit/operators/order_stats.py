"""Exact order statistics without a global sort."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BINS = 10_000


def value_at(rows: DataFrame, column: str, k: int, low: float = 0.0, high: float = 1.0, most: int = 100_000) -> float | None:
    """The value at 0-based ascending place k of a column of doubles in [low, high].

    Each pass counts values in `BINS` bins and goes on inside the bin that holds the place, until that bin has
    `most` distinct values at most; the driver sees one row for each bin or value.
    """
    while True:
        inside = rows.filter(F.col(column).between(low, high))
        width = (high - low) / BINS
        if width == 0:
            return low
        bin_of = F.least(F.floor((F.col(column) - low) / width), F.lit(BINS - 1)).cast("int")
        found = inside.groupBy(bin_of.alias("bin")).agg(F.count("*").alias("n"), F.min(column).alias("least"), F.max(column).alias("most")).orderBy("bin").collect()
        for row in found:
            if k < row["n"]:
                break
            k -= row["n"]
        else:
            return None
        low, high = row["least"], row["most"]
        if low == high:
            return low
        if row["n"] <= most:
            for value, n in rows.filter(F.col(column).between(low, high)).groupBy(column).count().orderBy(column).collect():
                if k < n:
                    return value
                k -= n
