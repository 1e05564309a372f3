"""Logs from files and from point events."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.model import LOG
from ..plans.scratch import Tables


def read_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(LOG).option("header", True).csv(path)


def read_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(LOG).json(path)


def read_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(LOG).orc(path)


def read_parquet(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(LOG).parquet(path)


def read_text(spark: SparkSession, path: str) -> DataFrame:
    """One timeline a line: 'sid<TAB>sym:st:ft:u sym:st:ft:u ...'."""
    rows = spark.read.text(path).select(F.split("value", "\t").alias("p"))
    items = rows.select(F.col("p")[0].cast("long").alias("sid"), F.explode(F.split(F.col("p")[1], " ")).alias("i")).select("sid", F.split("i", ":").alias("i"))
    return items.select("sid", F.col("i")[0].alias("sym"), *[F.col("i")[k].cast("long").alias(c) for k, c in ((1, "st"), (2, "ft"), (3, "u"))])


def pair_starts_stops(events: DataFrame) -> DataFrame:
    """Columns sid, sym, at, kind ('start'/'stop'), u: each start with the next stop of the same symbol; others are left out."""
    own = Window.partitionBy("sid", "sym").orderBy("at")
    rows = events.withColumns({"ft": F.lead("at").over(own), "next": F.lead("kind").over(own)})
    return rows.filter("kind = 'start' AND next = 'stop'").select("sid", "sym", F.col("at").alias("st"), "ft", "u")


def until_next(events: DataFrame, by=("sid",)) -> DataFrame:
    """Each event lasts until the next one; the last of each group is left out."""
    own = Window.partitionBy(*by).orderBy("at", "sym")
    return events.withColumn("ft", F.lead("at").over(own)).filter("ft IS NOT NULL").select("sid", "sym", F.col("at").alias("st"), "ft", "u")


def sessions(events: DataFrame, gap: int) -> DataFrame:
    """Events of one symbol less than `gap` apart become one interval."""
    own = Window.partitionBy("sid", "sym").orderBy("at")
    new = F.coalesce((F.col("at") - F.lag("at").over(own) > gap).cast("int"), F.lit(0))
    rows = events.withColumn("new", new).withColumn("n", F.sum("new").over(own))
    return rows.groupBy("sid", "sym", "n").agg(F.min("at").alias("st"), (F.max("at") + 1).alias("ft"), F.sum("u").alias("u")).drop("n")


def state_runs(rows: DataFrame) -> DataFrame:
    """Columns sid, at, sym: stretches of equal symbol become intervals, the utility is their number of rows.

    One series may hold all rows: it is cut into ranges of time, whose first and last runs are joined with their neighbours'.
    """
    tables = Tables(rows.sparkSession, "runs")
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.select("sid", "at", "sym").repartitionByRange(parts, "sid", "at").sortWithinPartitions("sid", "at").withColumn("part", F.spark_partition_id())
    own = Window.partitionBy("part", "sid").orderBy("at")
    change = F.coalesce((F.col("sym") != F.lag("sym").over(own)).cast("int"), F.lit(1))
    runs = tables.put("rows", dealt).withColumn("change", change).withColumn("n", F.sum("change").over(own))
    runs = runs.groupBy("part", "sid", "n", "sym").agg(F.min("at").alias("st"), (F.max("at") + 1).alias("ft"), F.count(F.lit(1)).alias("u"))
    ends = Window.partitionBy("part", "sid")
    runs = tables.put("runs", runs.withColumn("border", (F.col("n") == F.min("n").over(ends)) | (F.col("n") == F.max("n").over(ends))))
    # at most two rows a range and series
    along = Window.partitionBy("sid").orderBy("part", "n")
    fresh = F.coalesce(((F.lag("sym").over(along) != F.col("sym")) | (F.lag("part").over(along) == F.col("part"))).cast("int"), F.lit(1))
    border = runs.filter("border").withColumn("fresh", fresh).withColumn("k", F.sum("fresh").over(along))
    joined = border.groupBy("sid", "k", "sym").agg(F.min("st").alias("st"), F.max("ft").alias("ft"), F.sum("u").alias("u"))
    cols = ["sid", "sym", "st", "ft", "u"]
    return runs.filter("NOT border").select(*cols).unionByName(joined.select(*cols))
