"""Where logs, levels and rules go."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def parquet(df: DataFrame, path: str, partition_by: str | None = None) -> None:
    writer = df.write.mode("overwrite")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)


def bucketed(df: DataFrame, name: str, path: str, buckets: int, key: str = "sid") -> None:
    """A table whose later joins and groupings on the key need no exchange."""
    df.write.mode("overwrite").option("path", path).bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def csv(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").option("header", True).csv(path)


def json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def orc(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").orc(path)


def text(log: DataFrame, path: str) -> None:
    """One timeline a line, as formats.read_text reads it."""
    item = F.concat_ws(":", "sym", "st", "ft", "u")
    rows = log.groupBy("sid").agg(F.array_join(F.array_sort(F.collect_list(item)), " ").alias("items"))
    rows.select(F.concat_ws("\t", F.col("sid").cast("string"), "items").alias("value")).write.mode("overwrite").text(path)


def noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()
