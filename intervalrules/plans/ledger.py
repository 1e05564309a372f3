"""Ledgers of a rule: which timelines hold it and what it may still earn there."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def left(rule_occ: DataFrame, ante_occ: DataFrame) -> DataFrame:
    """(sid, occurs, ub) for every timeline with the antecedent; ub is the open bound, 0 where the rule does not occur."""
    best = rule_occ.groupBy("sid").agg(F.max("open").alias("ub"))
    return ante_occ.select("sid").distinct().join(best, "sid", "left").select("sid", F.col("ub").isNotNull().alias("occurs"), F.coalesce("ub", F.lit(0)).alias("ub"))


def right(rule_occ: DataFrame) -> DataFrame:
    """(sid, ub) for the rule's timelines; ub is the right bound."""
    return rule_occ.groupBy("sid").agg(F.max("right").alias("ub"))
