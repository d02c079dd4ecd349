"""Connected components over an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.session import discard, staged


def _larger_to_least(edges: DataFrame) -> DataFrame:
    """Each node hands its larger neighbours to the least of its closed neighbourhood."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.join(least, "u").filter("v > u and v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _smaller_to_least(edges: DataFrame) -> DataFrame:
    """Each node hands itself and its smaller neighbours to the least of these."""
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").filter("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _counted(edges: DataFrame) -> tuple[DataFrame, tuple]:
    """The edges, staged, and their number and an order-free hash sum."""
    out = staged(edges, "edges")
    return out, tuple(out.select(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def connected(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node on an edge; root is the least node reachable.

    Every round is two shuffles of the remaining edges, written to the shared folder so that lineage stays
    short. It ends when a round changes nothing, told by a count and a hash sum of the edge set.
    Self loops, reversed and repeated edges are allowed; an edge with a null end is ignored. No edges: no rows.
    """
    now, mark = _counted(edges.select(F.col(a).alias("u"), F.col(b).alias("v")).filter("u is not null and v is not null and u != v").distinct())
    for _ in range(max_rounds):
        if mark[0] == 0:
            break
        before, known = now, mark
        now, mark = _counted(_smaller_to_least(_larger_to_least(before)))
        discard(before)
        if mark == known:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    nodes = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return nodes.union(nodes.select(F.col("root").alias("node"), "root")).groupBy("node").agg(F.min("root").alias("root"))
