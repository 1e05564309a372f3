"""SQL functions, an aggregate and a table function over timelines."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from . import relations as R


@pandas_udf(T.LongType())
def peak_concurrency(st: pd.Series, ft: pd.Series) -> int:
    """Most intervals open at once in a group; ends come before starts at the same time."""
    marks = sorted([(t, 1) for t in st] + [(t, -1) for t in ft], key=lambda m: (m[0], m[1]))
    now = best = 0
    for _, v in marks:
        now += v
        best = max(best, now)
    return best


@udtf(returnType=T.StructType([T.StructField("first_pos", T.IntegerType()), T.StructField("second_pos", T.IntegerType())]))
class RuleOccurrences:
    """Pairs of a timeline (JSON array of intervals) with a given relation digit."""

    def eval(self, timeline: str, digit: int):
        items = json.loads(timeline)
        for i, a in enumerate(items):
            for b in items[i + 1 :]:
                if relation(a["st"], a["ft"], b["st"], b["ft"]) == digit:
                    yield a["pos"], b["pos"]


def relation(a_st: int, a_ft: int, b_st: int, b_ft: int) -> int:
    """The digit for plain numbers; an independent check of the column form."""
    if b_st >= a_ft:
        return int(b_st == a_ft)
    if a_st == b_st:
        return 6 if a_ft == b_ft else 5
    return 4 if a_ft == b_ft else 2 if a_ft < b_ft else 3


def register(spark: SparkSession) -> None:
    """relation_digit and relation_letters as SQL expressions, rule_occurrences as a table function."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION relation_digit(a_st BIGINT, a_ft BIGINT, b_st BIGINT, b_ft BIGINT) RETURNS INT RETURN " + R.digit_sql("a_st", "a_ft", "b_st", "b_ft"))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION relation_letters(num BIGINT, k INT) RETURNS STRING RETURN translate(lpad(conv(CAST(num AS STRING), 10, 7), k, '0'), '0123456', '{R.LETTERS}')")
    spark.udtf.register("rule_occurrences", RuleOccurrences)
    spark.udf.register("peak_concurrency", peak_concurrency)


def mine_rules(spark: SparkSession, view: str, **options):
    """Rules of a log that is registered as a view."""
    from ..plans import search

    return search.mine(spark.table(view), **options).rules

