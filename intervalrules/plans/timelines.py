"""Timelines: position, utility behind (tail), the first position with the same start (tie) and the utility from there on (head)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ORDER = ("st", "ft", "code")
COLUMNS = ("pos", "code", "st", "ft", "u", "tail", "tie", "head")


def items(coded: DataFrame, parts: int) -> DataFrame:
    """sid and COLUMNS of each interval, hash-partitioned and sorted by sid: the layout that all later levels keep."""
    own = Window.partitionBy("sid").orderBy(*ORDER)
    upto, behind = own.rowsBetween(Window.unboundedPreceding, 0), own.rowsBetween(1, Window.unboundedFollowing)
    out = coded.select("sid", "code", "st", "ft", "u").repartition(parts, "sid")
    out = out.withColumns({"pos": F.row_number().over(own), "tail": F.coalesce(F.sum("u").over(behind), F.lit(0)), "new": F.coalesce(F.col("st") != F.lag("st").over(own), F.lit(True))})
    first = lambda c: F.last(F.when(F.col("new"), c), ignorenulls=True).over(upto)
    return out.withColumns({"tie": first(F.col("pos")), "head": first(F.col("tail") + F.col("u"))}).select("sid", *COLUMNS)


def arrays(coded: DataFrame, parts: int) -> DataFrame:
    """sid and iv, the array of its intervals in order, hash-partitioned by sid."""
    return items(coded, parts).groupBy("sid").agg(F.array_sort(F.collect_list(F.struct(*COLUMNS))).alias("iv"))
