"""Test tables and the interval logs built from them.

Days count from 1995-01-01, cents are floor(x * 100 + 0.5), times are LONG before anything is compared.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans import model

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EPOCH = "DATE'1995-01-01'"
QUARTER = "(year({0}) * 4 + quarter({0}))"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names=TABLES) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def cents(x: str) -> Column:
    return F.expr(f"CAST(FLOOR(({x}) * 100 + 0.5) AS BIGINT)")


def day(x: str) -> Column:
    return F.expr(f"CAST(datediff(CAST({x} AS DATE), {EPOCH}) AS BIGINT)")


def micros(x: str) -> Column:
    return F.expr(f"unix_micros(CAST({x} AS TIMESTAMP))")


def from_table(df: DataFrame, sid: Column | str, sym: Column | str, start: Column | str, finish: Column | str, utility: Column | str) -> DataFrame:
    """Any table as a log; expressions give the five columns."""
    as_col = lambda c: F.expr(c) if isinstance(c, str) else c
    return df.select(as_col(sid).cast("long").alias("sid"), as_col(sym).cast("string").alias("sym"), as_col(start).cast("long").alias("st"), as_col(finish).cast("long").alias("ft"), as_col(utility).cast("long").alias("u"))


def _shipped(spark: SparkSession, sf_dir: str, within: int | None) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderdate", "o_totalprice")
    items = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_shipdate")
    late = items.join(orders, "o_orderkey").filter("l_shipdate > o_orderdate")
    if within is not None:
        late = late.filter(F.expr(f"l_shipdate < o_orderdate + INTERVAL '{within}' DAY"))
    return late.groupBy("o_orderkey", "o_custkey", "o_orderpriority", "o_orderdate", "o_totalprice").agg(F.max("l_shipdate").alias("last"))


def order_spans(spark: SparkSession, sf_dir: str, within: int | None = None) -> DataFrame:
    """Orders of a customer by priority, from order to last later shipment."""
    return from_table(_shipped(spark, sf_dir, within), "o_custkey", "o_orderpriority", day("o_orderdate"), day("last"), cents("o_totalprice"))


def short_order_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_spans(spark, sf_dir, 121)


def quarter_spans_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As order_spans with both ends in quarters, repeats not merged."""
    return from_table(_shipped(spark, sf_dir, None), "o_custkey", "o_orderpriority", QUARTER.format("o_orderdate"), QUARTER.format("last") + " + 1", cents("o_totalprice"))


def quarter_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return model.clean(quarter_spans_raw(spark, sf_dir)).good


def _items(spark: SparkSession, sf_dir: str, sym: str, days: int) -> DataFrame:
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("p_partkey"), "l_shipdate", "l_quantity", "l_extendedprice", "l_discount")
    parts = table(spark, sf_dir, "part").select("p_partkey", sym)
    start = day("l_shipdate")
    log = from_table(items.join(parts, "p_partkey"), "l_orderkey", sym, start, start + F.expr(f"CAST({days} * l_quantity AS BIGINT)"), cents("l_extendedprice * (1 - l_discount)"))
    return model.clean(log).good


def items_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items of an order by part type, 20 days for each unit."""
    return _items(spark, sf_dir, "p_type", 20)


def items_by_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _items(spark, sf_dir, "p_brand", 1)


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The customers' keys as timelines (sid)."""
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("sid")).filter("sid IS NOT NULL").distinct()


def _usage(spark: SparkSession, sf_dir: str, sid: str, sym: str, scale: int) -> DataFrame:
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_type", "value", "props")
    u = cents("value")
    return from_table(events, sid, sym, micros("ts"), micros("ts") + u * scale, u)


def user_weeks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of a user and week of the month; duration follows the value."""
    return _usage(spark, sf_dir, "user_id * 100 + (day(ts) - 1) DIV 7", "event_type", 36_000_000)


def user_weeks_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _usage(spark, sf_dir, "user_id * 100 + (day(ts) - 1) DIV 7", "concat(event_type, '-', CAST(get_json_object(props, '$.k') AS INT) DIV 20)", 36_000_000)


def user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _usage(spark, sf_dir, "user_id * 100 + day(ts)", "event_type", 3_600_000)


def talk_turns_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of a conversation by role on a clock of characters; an empty turn has no length."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.length("text").alias("n"))
    clock = F.sum(F.col("n") + 1).over(Window.partitionBy("conv_id").orderBy("turn"))
    turns = turns.withColumn("ft", clock)
    return from_table(turns, "conv_id", "role", F.col("ft") - F.col("n") - 1, "ft", "n")


def talk_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return model.clean(talk_turns_raw(spark, sf_dir)).good


LOGS = {
    "order_spans": order_spans,
    "short_order_spans": short_order_spans,
    "quarter_spans": quarter_spans,
    "items_by_type": items_by_type,
    "items_by_brand": items_by_brand,
    "user_weeks": user_weeks,
    "user_weeks_k": user_weeks_k,
    "user_days": user_days,
    "talk_turns": talk_turns,
}
