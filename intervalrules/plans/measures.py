"""Support, confidence and utility of rules."""

from __future__ import annotations

from decimal import Decimal
from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def enough_confidence(n_rule: Column, n_ante: Column, minconf: float | str | Fraction) -> Column:
    """n_rule / n_ante >= minconf, exactly: minconf is the decimal (or fraction) as written, and whole numbers are compared."""
    bar = Fraction(str(minconf))
    whole = lambda c: c.cast("decimal(19,0)")
    if bar.denominator <= 1_000_000:
        return n_rule * F.lit(bar.denominator) >= n_ante * F.lit(bar.numerator)
    return whole(n_rule) * F.lit(Decimal(bar.denominator)).cast("decimal(19,0)") >= whole(n_ante) * F.lit(Decimal(bar.numerator)).cast("decimal(19,0)")


def confidence(n_rule: Column, n_ante: Column) -> Column:
    return n_rule / n_ante


def support(n_rule: Column, n_timelines: int) -> Column:
    return n_rule / F.lit(n_timelines)


def utility_in(occ: DataFrame, keys: list[str], policy: str = "max") -> DataFrame:
    """u of each key in each timeline: of the best occurrence, of the first by positions, or of all."""
    if policy == "max":
        value = F.max("u")
    elif policy == "first":
        value = F.min(F.struct("at", "u"))["u"]
    elif policy == "sum":
        value = F.sum("u")
    else:
        raise ValueError(policy)
    return occ.groupBy("sid", *keys).agg(value.alias("u"))


def utility(per: DataFrame, keys: list[str]) -> DataFrame:
    return per.groupBy(*keys).agg(F.sum("u").alias("utility"), F.count(F.lit(1)).alias("n_rule"))


def antecedent_count(occ: DataFrame, keys: list[str]) -> DataFrame:
    """Timelines with the pattern, whether or not a consequent follows."""
    return occ.select("sid", *keys).distinct().groupBy(*keys).agg(F.count(F.lit(1)).alias("n_ante"))
