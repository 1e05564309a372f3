"""Structured Streaming: logs from event streams, windowed utility, rule matching with state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..operators import oracles as O
from ..plans.scratch import Tables
from ..sources import tables as T

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
DAY_US = 86_400_000_000


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


def events_of(plain: DataFrame) -> DataFrame:
    return plain.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", T.cents("value").alias("u"))


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream, times as TIMESTAMP."""
    plain = T.table(spark, sf_dir, "events")
    # a file source reads a folder; the glob names the one table in it
    return events_of(spark.readStream.schema(plain.schema).option("pathGlobFilter", "events*").option("recursiveFileLookup", "true").parquet(sf_dir))


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream over all that is there and returns what it wrote."""
    spark = df.sparkSession
    tables = Tables(spark, "stream")
    if mode == "append":
        run = df.writeStream.format("parquet").option("path", f"{tables.root}/out").option("checkpointLocation", f"{tables.root}/state").outputMode("append").trigger(availableNow=True).start()
        run.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{tables.root}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{tables.root}/out")

    run = df.writeStream.foreachBatch(keep).option("checkpointLocation", f"{tables.root}/state").outputMode(mode).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{tables.root}/out")


@query("stream_tumbling", "SELECT epoch_us(date_trunc('day', ts)) AS day, event_type, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS u FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    rows = event_stream(spark, d).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("u").alias("u"))
    return drain(rows, "complete").select(F.unix_micros("window.start").alias("day"), "event_type", "n", "u")


@query("stream_sliding", f"SELECT day - k * {DAY_US} AS start, event_type, CAST(sum(u) AS BIGINT) AS u FROM (SELECT epoch_us(date_trunc('day', ts)) AS day, event_type, CAST(floor(value * 100 + 0.5) AS BIGINT) AS u FROM events), (VALUES (0), (1)) t(k) GROUP BY ALL")
def stream_sliding(spark, d):
    """Utility in windows of two days that start every day, all windows of the stream."""
    rows = event_stream(spark, d).groupBy(F.window("ts", "2 days", "1 day"), "event_type").agg(F.sum("u").alias("u"))
    return drain(rows, "complete").select(F.unix_micros("window.start").alias("start"), "event_type", "u")


@query("stream_sessions", f"SELECT user_id, min(t) AS st, max(t) + {DAY_US // 4} AS ft, CAST(count(*) AS BIGINT) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS k FROM (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) >= {DAY_US // 4} THEN 1 ELSE 0 END AS new FROM events)) GROUP BY user_id, k")
def stream_sessions(spark, d):
    rows = event_stream(spark, d).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return drain(rows, "complete").select("user_id", F.unix_micros("session_window.start").alias("st"), F.unix_micros("session_window.end").alias("ft"), "n")


# Delivery of the late-data stream: an event comes with the file of its four days, every tenth one file later, every other tenth four
# files later; every fifth event comes again with the next file.
FILE_DAYS, DELAY_DAYS = 4, 3
DELIVERED = "CASE event_id % 10 WHEN 3 THEN 1 WHEN 7 THEN 4 ELSE 0 END"


def delivered_files(spark: SparkSession, sf_dir: str) -> str:
    """Folder of the files, written one after the other so that their order is that of their numbers."""
    tables = Tables(spark, "delivered")
    plain = T.table(spark, sf_dir, "events")
    first = plain.agg(F.min(F.date_trunc("day", "ts"))).first()[0]
    own = F.floor(F.datediff(F.to_date("ts"), F.lit(first).cast("date")) / FILE_DAYS) + F.expr(DELIVERED)
    rows = plain.withColumn("file", own.cast("int"))
    rows = tables.put("rows", rows.unionByName(rows.filter("event_id % 5 = 0").withColumn("file", F.col("file") + 1)))
    for number in [r["file"] for r in rows.select("file").distinct().orderBy("file").collect()]:  # one for each delivery
        rows.filter(F.col("file") == number).drop("file").coalesce(1).write.mode("append").parquet(f"{tables.root}/files")
    return f"{tables.root}/files"


# A batch drops what is not later than the watermark of the batch before it, which is the newest time of the batches before that one less the delay.
LATE = f"""
WITH e AS (SELECT event_id, user_id, epoch_us(ts) AS t, CAST(floor(value * 100 + 0.5) AS BIGINT) AS u, datediff('day', (SELECT min(CAST(ts AS DATE)) FROM events), CAST(ts AS DATE)) // {FILE_DAYS} + {DELIVERED} AS file FROM events),
d AS (SELECT file, t FROM e UNION ALL SELECT file + 1, t FROM e WHERE event_id % 5 = 0),
b AS (SELECT file, row_number() OVER (ORDER BY file) AS n, max(t) AS t FROM d GROUP BY file),
w AS (SELECT x.file, max(y.t) // 1000 * 1000 - {DELAY_DAYS * DAY_US} AS mark FROM b x LEFT JOIN b y ON y.n <= x.n - 2 GROUP BY x.file)
SELECT user_id, CAST(count(*) AS BIGINT) AS n, CAST(sum(u) AS BIGINT) AS u FROM e JOIN w USING (file) WHERE mark IS NULL OR t > mark GROUP BY user_id
"""


@query("stream_late_data", LATE)
def stream_late_data(spark, d):
    """Files in several batches: events behind the watermark are dropped, and so are repeats within it."""
    plain = T.table(spark, d, "events")
    rows = events_of(spark.readStream.schema(plain.schema).option("maxFilesPerTrigger", 1).parquet(delivered_files(spark, d)))
    rows = rows.withWatermark("ts", f"{DELAY_DAYS} days").dropDuplicatesWithinWatermark(["event_id"])
    return drain(rows.select("event_id", "user_id", "u"), "append").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.sum("u").alias("u"))


@query("stream_static_join", "SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events WHERE event_type IN (SELECT event_type FROM events GROUP BY event_type ORDER BY count(*) DESC, event_type LIMIT 3) GROUP BY event_type")
def stream_static_join(spark, d):
    """Events of the three most frequent symbols, which come from a batch table."""
    top = T.table(spark, d, "events").groupBy("event_type").count().orderBy(F.desc("count"), "event_type").limit(3).select("event_type")
    rows = event_stream(spark, d).join(F.broadcast(top), "event_type").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return drain(rows, "complete")


@query("stream_interval_join", "SELECT a.event_id AS view_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def stream_interval_join(spark, d):
    """Each view with the purchases of the same user within a day: two watermarked streams."""
    rows = event_stream(spark, d)
    a = rows.filter("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", "40 days")
    b = rows.filter("event_type = 'purchase'").select(F.col("event_id").alias("buy_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", "40 days")
    return drain(a.join(b, F.expr("a_user = b_user AND b_ts > a_ts AND b_ts <= a_ts + INTERVAL 1 DAY")).select("view_id", "buy_id"), "append")


STATE = "at array<long>, sym array<string>, id array<long>, open_at array<long>, open_sym array<string>"
MATCHED = "event_id long, predicted string, confidence_ppm long, was_predicted boolean"


def matcher(pairs: dict[str, tuple[str, int]], keep_us: int):
    """For rules a -> b: emits the predicted b when a arrives, and whether a itself was predicted.

    A user's events wait in the state until the watermark has passed them, so they are judged in order over all batches; the open predictions stay for
    keep_us. The timeout is that of the first event that waits, in event time.
    """

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        at, sym, number, open_at, open_sym = map(list, state.get) if state.exists else ([], [], [], [], [])
        if not state.hasTimedOut:
            for pdf in batches:
                at += pdf["at"].tolist()
                sym += pdf["event_type"].tolist()
                number += pdf["event_id"].tolist()
        mark = state.getCurrentWatermarkMs() * 1000
        waiting, out = sorted(zip(at, sym, number)), []
        open_ = list(zip(open_at, open_sym))
        while waiting and waiting[0][0] <= mark:
            now, symbol, event = waiting.pop(0)
            open_ = [(t, s) for t, s in open_ if now - t <= keep_us]
            if symbol in pairs:
                expected, ppm = pairs[symbol]
                out.append((int(event), expected, ppm, any(s == symbol and t < now for t, s in open_)))
                open_.append((int(now), expected))
        if waiting:
            state.update(tuple(list(v) for v in (*zip(*waiting), *(zip(*open_) if open_ else ((), ())))))
            state.setTimeoutTimestamp(max(waiting[0][0] // 1000 + 1, mark // 1000 + 1))
        elif open_ and open_[-1][0] + keep_us > mark:
            state.update(([], [], [], *(list(v) for v in zip(*open_))))
            state.setTimeoutTimestamp(max((open_[-1][0] + keep_us) // 1000 + 1, mark // 1000 + 1))
        elif state.exists:
            state.remove()
        yield pd.DataFrame(out, columns=["event_id", "predicted", "confidence_ppm", "was_predicted"])

    return step


KEEP_US = 7 * DAY_US
MATCH = O.on(
    "user_weeks",
    f"SELECT predicted, CAST(count(*) AS BIGINT) AS n, CAST(count(*) FILTER (was) AS BIGINT) AS n_predicted, max(ppm) AS confidence_ppm FROM (SELECT b.b AS predicted, b.ppm, EXISTS (SELECT 1 FROM ev p JOIN best q ON q.a = p.sym WHERE p.user_id = e.user_id AND q.b = e.sym AND p.t < e.t AND e.t - p.t <= {KEEP_US}) AS was FROM ev e JOIN best b ON b.a = e.sym) GROUP BY predicted",
    O.PAIRS,
    O.ROOTS,
    "conf AS (SELECT sa AS a, sb AS b, CAST(n_rule * 1000000 // n_ante AS BIGINT) AS ppm FROM (SELECT sa, sb, d, count(DISTINCT sid) AS n_rule FROM roots GROUP BY sa, sb, d) JOIN (SELECT sym AS sa, count(DISTINCT sid) AS n_ante FROM log GROUP BY sym) USING (sa))",
    "best AS (SELECT a, b, ppm FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY ppm DESC, b DESC) AS r FROM conf) WHERE r = 1)",
    "ev AS (SELECT user_id, event_type AS sym, epoch_us(ts) AS t FROM events)",
)


@query("stream_match", MATCH)
def stream_match(spark, d):
    """Antecedents met in the stream with the consequent that mined one-to-one rules predict, and how many of those were predicted themselves."""
    from ..plans import search

    rules = search.mine(T.user_weeks(spark, d), minutil=0, minconf=0, max_size=2).rules
    ppm = F.expr("n_rule * 1000000 DIV n_ante")
    best = rules.groupBy(F.col("x")[0].alias("a")).agg(F.max(F.struct(ppm.alias("ppm"), F.col("y")[0].alias("b"))).alias("v"))
    pairs = {r["a"]: (r["v"]["b"], r["v"]["ppm"]) for r in best.collect()}  # one row for each symbol
    # a last row far ahead ends the stream: the watermark passes every event
    tables = Tables(spark, "end")
    plain = T.table(spark, d, "events")
    last = plain.agg(F.lit(-1).cast("long").alias("event_id"), (F.max("ts") + F.expr("INTERVAL 400 DAYS")).alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    tables.put("rows", last.select(*[F.col(f.name).cast(f.dataType) for f in plain.schema.fields]))
    end = events_of(spark.readStream.schema(plain.schema).parquet(f"{tables.root}/rows"))
    rows = event_stream(spark, d).unionByName(end).withWatermark("ts", "1 day").withColumn("at", F.unix_micros("ts"))
    out = rows.groupBy("user_id").applyInPandasWithState(matcher(pairs, KEEP_US), MATCHED, STATE, "append", GroupStateTimeout.EventTimeTimeout)
    found = drain(out, "append").groupBy("predicted")
    return found.agg(F.count(F.lit(1)).alias("n"), F.count_if("was_predicted").alias("n_predicted"), F.max("confidence_ppm").alias("confidence_ppm"))


@query("stream_root_refresh", "SELECT event_type, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS u FROM events GROUP BY 1")
def stream_root_refresh(spark, d):
    """Symbol statistics kept up to date batch by batch."""
    rows = event_stream(spark, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("u").alias("u"))
    return drain(rows, "complete")
