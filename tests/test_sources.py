"""Sources, sinks and streams."""

import random

from pyspark.sql import functions as F

from intervalrules.functions import sqlfuncs
from intervalrules.operators import experiments, rules
from intervalrules.operators.rules import EXAMPLE_ROWS, example
from intervalrules.plans import model, report, search
from intervalrules.sources import formats, sinks, synth, tables


def rows_of(df):
    return sorted(tuple(r) for r in df.select(*model.LOG.fieldNames()).collect())


def test_files_round_trip(spark, tmp_path):
    log = example(spark)
    for name, read in (("csv", formats.read_csv), ("json", formats.read_json), ("orc", formats.read_orc), ("parquet", formats.read_parquet), ("text", formats.read_text)):
        getattr(sinks, name)(log, f"{tmp_path}/{name}")
        assert rows_of(read(spark, f"{tmp_path}/{name}")) == sorted(EXAMPLE_ROWS), name
    sinks.parquet(log, f"{tmp_path}/by", "sym")
    assert rows_of(spark.read.parquet(f"{tmp_path}/by").select("sid", F.col("sym").cast("string").alias("sym"), "st", "ft", "u")) == sorted(EXAMPLE_ROWS)
    sinks.bucketed(log, "example_bucketed", f"{tmp_path}/bucketed", 3)
    try:
        plan = spark.table("example_bucketed").groupBy("sid").count()._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and rows_of(spark.table("example_bucketed")) == sorted(EXAMPLE_ROWS)
    finally:
        spark.sql("DROP TABLE example_bucketed")
    sinks.noop(log)


def test_rule_files(spark, tmp_path):
    rules = search.mine(example(spark), minutil=35, minconf=0.6).rules
    report.write_rules(rules, f"{tmp_path}/rules", "matrix")
    lines = {r["value"] for r in spark.read.text(f"{tmp_path}/rules").collect()}
    assert "A,C ==> D #util: 47 #conf: 1.0000 0,0,0" in lines and "A ==> B,D #util: 36 #conf: 0.6667 0,0,2" in lines and len(lines) == 5
    assert report.output_bytes(rules, "matrix") == sum(len(v) + 1 for v in lines)


def test_point_events_to_intervals(spark):
    events = spark.createDataFrame([(1, "a", 1, "start", 5), (1, "a", 4, "stop", 0), (1, "b", 2, "start", 7), (1, "b", 3, "start", 8), (1, "b", 9, "stop", 0), (2, "a", 5, "stop", 1)], "sid long, sym string, at long, kind string, u long")
    assert sorted(tuple(r) for r in formats.pair_starts_stops(events).collect()) == [(1, "a", 1, 4, 5), (1, "b", 3, 9, 8)]


def test_state_runs_over_range_borders(spark):
    rng = random.Random(2)
    for weights in ((1, 1), (60, 1)):
        rows, now = [], "a"
        for sid in (1, 2):
            for at in range(400):
                now = now if rng.choices((True, False), weights)[0] else rng.choice("abc")
                rows.append((sid, at, now))
        want, start = [], 0
        for k in range(1, len(rows) + 1):
            if k == len(rows) or rows[k][0] != rows[start][0] or rows[k][2] != rows[start][2]:
                want.append((rows[start][0], rows[start][2], rows[start][1], rows[k - 1][1] + 1, k - start))
                start = k
        got = formats.state_runs(spark.createDataFrame(rows, "sid long, at long, sym string"))
        assert sorted(tuple(r) for r in got.select("sid", "sym", "st", "ft", "u").collect()) == sorted(want)


def test_views_and_table_functions(spark):
    tables.register_views(spark, "/root/testdata/sf0.001", ["region", "events"])
    assert spark.sql("SELECT count(*) AS n FROM region").first()["n"] == 5
    example(spark).createOrReplaceTempView("example_log")
    assert sqlfuncs.mine_rules(spark, "example_log", minutil=35, minconf=0.6).count() == 5


def test_generated_logs_do_not_depend_on_partitions(spark):
    a = rows_of(synth.interval_log(spark, 50, 20, 6))
    spark.conf.set("spark.sql.leafNodeDefaultParallelism", "3")
    try:
        assert rows_of(synth.interval_log(spark, 50, 20, 6)) == a
    finally:
        spark.conf.unset("spark.sql.leafNodeDefaultParallelism")
    drawn = synth.gaussian_duration(example(spark), 10.0, 3.0, 42)
    assert rows_of(drawn) == rows_of(synth.gaussian_duration(example(spark).repartition(5), 10.0, 3.0, 42)) and min(r[4] for r in rows_of(drawn)) >= 1


def test_generated_features_follow_the_customers(spark, tmp_path):
    spark.createDataFrame([(3,), (70,), (70,), (None,)], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    got = rules.QUERIES["synthetic_log_features"](spark, str(tmp_path)).first()
    log = synth.interval_log(spark, spark.createDataFrame([(3,), (70,)], "sid long"), 200, 32)
    assert got["timelines"] == 2 and got["utility"] == log.agg(F.sum("u")).first()[0]


def test_the_synthetic_sweep_follows_the_customers(spark, tmp_path, monkeypatch):
    keys = [3, 70, 70, 901, None]
    spark.createDataFrame([(k,) for k in keys], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    seen = []
    monkeypatch.setattr(experiments, "sweep", lambda spark, name, log, *rest: seen.append(rows_of(log)) or log)
    experiments.QUERIES["sweep_cost_synthetic"](spark, str(tmp_path))
    assert seen == [rows_of(synth.interval_log(spark, spark.createDataFrame([(3,), (70,), (901,)], "sid long"), 200, 32))]
