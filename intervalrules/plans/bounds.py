"""Utility bounds: symbol weights, reserves, left, right and open bounds, symbol budgets and class bounds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scratch import Tables


def symbol_weight(coded: DataFrame, literal: bool = False) -> DataFrame:
    """(code, weight). A rule with the symbol can earn no more than the timelines that hold it; `literal` sums the symbol's own utility only."""
    if literal:
        return coded.groupBy("code").agg(F.sum("u").alias("weight"))
    own = coded.groupBy("sid", "code").agg(F.sum("u").alias("u"))
    total = own.withColumn("total", F.sum("u").over(Window.partitionBy("sid")))
    return total.groupBy("code").agg(F.sum("total").alias("weight"))


def symbol_utility(coded: DataFrame) -> DataFrame:
    """u of each symbol in each timeline, written."""
    return Tables(coded.sparkSession, "symbols").put("own", coded.groupBy("sid", "code").agg(F.sum("u").alias("u")))


def prune_symbols(coded: DataFrame, minutil: int, own: DataFrame | None = None) -> tuple[DataFrame, list[dict[str, int]]]:
    """Drops intervals of symbols whose weight is below minutil until none is left, with the numbers of symbols of each round.

    Works on one row for each timeline and symbol (own: symbol_utility(coded), if it is there already). The symbols that stay are a table; only their number reaches the driver.
    """
    tables = Tables(coded.sparkSession, "symbols")
    own = symbol_utility(coded) if own is None else own
    trace: list[dict[str, int]] = []
    kept = None
    while True:
        weights = tables.put(f"weights-{len(trace)}", symbol_weight(own))
        count = weights.agg(F.count(F.lit(1)).alias("symbols"), F.count_if(F.col("weight") < minutil).alias("removed")).first().asDict()
        trace.append(count)
        if not count["removed"]:
            return (coded if kept is None else coded.join(kept, "code", "left_semi")), trace
        kept = weights.filter(F.col("weight") >= minutil).select("code")
        own = own.join(kept, "code", "left_semi")


# tails are the utility behind a position; tail_before_tie: behind the position before the consequent's tie head


def left_reserve(tail_last: Column, tail_before_tie: Column) -> Column:
    """Utility of the intervals that may still join the antecedent."""
    return F.greatest(tail_last - tail_before_tie, F.lit(0))


def right_reserve(tail_last: Column) -> Column:
    """Utility of the intervals that may still join the consequent."""
    return tail_last


def left_bound(u: Column, left: Column) -> Column:
    return u + left


def right_bound(u: Column, right: Column) -> Column:
    return u + right


def open_bound(u: Column, left: Column, right: Column) -> Column:
    """For rules that may grow to either side; the utility counts once."""
    return u + left + right


def per_timeline(rows: DataFrame, keys: list[str], bound: str) -> DataFrame:
    """The best bound of each key in each timeline; no exchange if rows are partitioned by sid."""
    return rows.groupBy("sid", *keys).agg(F.max(bound).alias(bound))


def class_bound(rows: DataFrame, rule: list[str]) -> DataFrame:
    """Bound of each (rule, side, code, digit)."""
    keys = [*rule, "side", "code", "digit"]
    return per_timeline(rows, keys, "bound").groupBy(*keys).agg(F.sum("bound").alias("bound"))


def symbol_budget(rows: DataFrame, rule: list[str]) -> DataFrame:
    """Bound of each (rule, side, code), its relation unknown."""
    keys = [*rule, "side", "code"]
    return per_timeline(rows, keys, "bound").groupBy(*keys).agg(F.sum("bound").alias("bound"))


def class_budget(classes: DataFrame, rule: list[str], minutil: int, trace: bool = False) -> DataFrame:
    """Classes that may hold a profitable rule: those whose own bound suffices.

    The budget of a symbol is the sum of its class bounds; what is left after a class is the sum of the later ones. The trace shows
    each class with the rest before it, whether it is kept and whether it is evaluated before the rest is too small.
    """
    if not trace:
        return classes.filter(F.col("bound") >= minutil)
    later = Window.partitionBy(*rule, "side", "code").orderBy("digit").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    return classes.withColumn("rest", F.sum("bound").over(later)).withColumns({"kept": F.col("bound") >= minutil, "visited": F.col("rest") >= minutil})
