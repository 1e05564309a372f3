"""The interval log: sid LONG, sym STRING, st LONG, ft LONG, u LONG."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .scratch import Tables

LOG = T.StructType([T.StructField("sid", T.LongType()), T.StructField("sym", T.StringType()), T.StructField("st", T.LongType()), T.StructField("ft", T.LongType()), T.StructField("u", T.LongType())])
TIMELINE = "sid long, iv array<struct<st:long,ft:long,code:int,u:long>>"


class Clean(NamedTuple):
    good: DataFrame
    bad: DataFrame


def assert_schema(df: DataFrame) -> DataFrame:
    """The log's columns with their types; other columns are dropped."""
    kinds = dict(df.dtypes)
    for f in LOG.fields:
        if kinds.get(f.name) != f.dataType.simpleString():
            raise TypeError(f"column {f.name} should be {f.dataType.simpleString()}, not {kinds.get(f.name)}")
    return df.select(*LOG.fieldNames())


def clean(df: DataFrame, duplicates: str = "merge") -> Clean:
    """Intervals of positive length and non-negative utility, repeats merged by sum (or sent to `bad`); the rest is quarantined."""
    df = assert_schema(df)
    sound = F.coalesce((F.col("st") < F.col("ft")) & (F.col("u") >= 0) & F.col("sid").isNotNull() & F.col("sym").isNotNull(), F.lit(False))
    good, bad = df.filter(sound), df.filter(~sound)
    if duplicates == "merge":
        return Clean(good.groupBy("sid", "sym", "st", "ft").agg(F.sum("u").alias("u")), bad)
    if duplicates != "error":
        raise ValueError(duplicates)
    counted = good.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("sid", "sym", "st", "ft")))
    return Clean(counted.filter("n = 1").drop("n"), bad.unionByName(counted.filter("n > 1").drop("n")))


LOCAL_BITS = 33  # monotonically_increasing_id keeps the row number of a partition in so many low bits


def encode_symbols(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(log with code, dictionary of code and sym); codes are ranks in the lexicographic order.

    The alphabet is range-sorted and numbered by partition, so it is never in one task.
    """
    tables = Tables(df.sparkSession, "alphabet")
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranked = df.select("sym").distinct().repartitionByRange(parts, "sym").sortWithinPartitions("sym").withColumn("at", F.monotonically_increasing_id())
    ranked = tables.put("sorted", ranked).withColumn("part", F.shiftright("at", LOCAL_BITS))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = ranked.groupBy("part").count().withColumn("before", F.coalesce(F.sum("count").over(before), F.lit(0)))  # one row a partition
    code = F.col("before") + F.col("at").bitwiseAND(F.lit((1 << LOCAL_BITS) - 1)) + 1
    codes = tables.put("codes", ranked.join(F.broadcast(starts), "part").select(code.cast("int").alias("code"), "sym"))
    return df.join(codes, "sym"), codes


def named(df: DataFrame, codes: DataFrame, *cols: str) -> DataFrame:
    """df with the codes in its array columns `cols` (none of them empty) turned into symbols, by a join with the dictionary; rows of df are distinct."""
    rest = df.columns
    each = df.select(*rest, F.posexplode(F.concat(*cols)).alias("at", "code")).join(codes, "code")
    whole = each.groupBy(*rest).agg(F.array_sort(F.collect_list(F.struct("at", "sym")))["sym"].alias("names"))
    begin, out = F.lit(1), {}
    for c in cols:
        out[c] = F.slice("names", begin, F.size(c))
        begin = begin + F.size(c)
    return whole.withColumns(out).select(*rest)


def to_timelines(coded: DataFrame) -> DataFrame:
    """One row for each timeline, its intervals in the order start, finish, symbol."""
    iv = F.array_sort(F.collect_list(F.struct("st", "ft", "code", "u")))
    return coded.groupBy("sid").agg(iv.alias("iv"))
