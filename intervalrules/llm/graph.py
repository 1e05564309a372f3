"""Connected components of an edge table by alternating large and small stars.

Each round rewires edges towards the smallest neighbour; rounds are logarithmic in practice. Rounds are written to the
shared folder, so a lost executor costs one round. The joins are plain equi-joins on a node, which adaptive execution can split for hubs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    return tuple(row)


def _large(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small(edges: DataFrame) -> DataFrame:
    """edges: a > b."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    rest = edges.join(least, "a").filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return least.select("a", F.col("m").alias("b")).unionByName(rest)


def components(edges: DataFrame, scratch: Scratch, name: str = "component") -> DataFrame:
    """(id, component) of every node of edges (a, b); component is the smallest id reachable.

    Rounds go on until the edges stay the same: every other round moves an edge to a smaller node, so they end.
    """
    pairs = edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    now = scratch.table(f"{name}-0", pairs)
    mark, at = _signature(now), 0
    while mark[0]:
        at += 1
        new = scratch.table(f"{name}-{at}", _small(_large(now).filter("a <> b").distinct()).distinct())
        seen = _signature(new)
        scratch.drop(f"{name}-{at - 1}")
        now, mark, before = new, seen, mark
        if seen == before:
            break
    roots = now.select(F.col("b").alias("id")).distinct()
    return now.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(roots.select("id", F.col("id").alias("component")))
