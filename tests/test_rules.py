"""Worked examples and invariants of the search."""

import random

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from intervalrules.functions import relations as R
from intervalrules.functions.sqlfuncs import relation
from intervalrules.operators.rules import example
from intervalrules.plans import baselines, bounds, ledger, match, measures, metrics, model, packed, prefix, report, scratch, search, timelines
from intervalrules.plans.prefix import number
from intervalrules.plans.variants import VARIANTS

TABLE_1 = {("A>B,D|0,2", 36, 2, 3), ("A>C,D|0,0", 47, 3, 3), ("A,B>D|0,2", 36, 2, 3), ("A,C>D|0,0", 47, 3, 3), ("C>D|0", 35, 3, 3)}


def keyed(rules):
    return {(r["k"], r["utility"], r["n_rule"], r["n_ante"]) for r in rules.select(report.key_text().alias("k"), "utility", "n_rule", "n_ante").collect()}


def random_log(spark, seed, lines=4, size=6, symbols="ABCD"):
    rng = random.Random(seed)
    rows = []
    for sid in range(lines):
        for _ in range(size):
            st = rng.randint(0, 8)
            rows.append((sid, rng.choice(symbols), st, st + rng.randint(1, 5), rng.randint(1, 9)))
    return spark.createDataFrame(rows, model.LOG)


def brute(rows, minutil, minconf, cap=6):
    """All rules of small logs by plain enumeration."""
    merged = {}
    for sid, sym, st, ft, u in rows:
        merged[sid, sym, st, ft] = merged.get((sid, sym, st, ft), 0) + u
    lines = {}
    for (sid, sym, st, ft), u in merged.items():
        lines.setdefault(sid, []).append((st, ft, sym, u))
    best, ante = {}, {}
    for sid, line in lines.items():
        line.sort()
        todo = [()]
        while todo:
            at = todo.pop()
            for j in range(at[-1] + 1 if at else 0, len(line)):
                new = (*at, j)
                if len(new) < cap:
                    todo.append(new)
                iv = [line[p] for p in new]
                nums = tuple(number(iv[:k], iv[k]) for k in range(1, len(iv)))
                syms = tuple(e[2] for e in iv)
                ante.setdefault((syms, nums), set()).add(sid)
                for k in range(1, len(new)):
                    if iv[k - 1][0] < iv[k][0] and not set(syms[:k]) & set(syms[k:]):
                        key = (syms[:k], syms[k:], nums)
                        own = best.setdefault(key, {})
                        own[sid] = max(own.get(sid, 0), sum(e[3] for e in iv))
    out = set()
    for (x, y, nums), per in best.items():
        n = len(ante[x, nums[: len(x) - 1]])
        if sum(per.values()) >= minutil and len(per) >= minconf * n:
            out.add((",".join(x) + ">" + ",".join(y) + "|" + ",".join(map(str, nums)), sum(per.values()), len(per), n))
    return out


def test_running_example(spark):
    got = search.mine(example(spark), minutil=35, minconf=0.6)
    assert keyed(got.rules) == TABLE_1 and got.metrics.candidates == 16


def test_no_budget_counts_more_candidates(spark):
    got = search.mine(example(spark), minutil=35, minconf=0.6, **VARIANTS["no_budget"])
    assert keyed(got.rules) == TABLE_1 and got.metrics.candidates == 23


@pytest.mark.parametrize("seed", [1, 2])
def test_engines_equal_brute_force(spark, seed):
    log = random_log(spark, seed)
    rows = [tuple(r) for r in log.collect()]
    for engine in ("frontier", "prefix", "subtrees"):
        got = search.mine(log, minutil=30, minconf=0.5, engine=engine, max_size=5, batch_timelines=30)
        assert keyed(got.rules) == brute(rows, 30, 0.5, 5), engine


def test_top_k_is_the_head_of_the_full_result(spark):
    log = random_log(spark, 5, size=4)
    every = sorted((-u for _, u, _, _ in keyed(search.mine(log, minutil=1, minconf=0.5, max_size=3).rules)))
    top = sorted(-r["utility"] for r in search.mine_top_k(log, 7, 0.5, max_size=3).rules.collect())
    assert top == every[:7]


def test_relation_truth_table(spark):
    grid = [(a, b, c, d) for a in range(6) for b in range(a + 1, 6) for c in range(6) for d in range(c + 1, 6) if (a, b) <= (c, d)]
    df = spark.createDataFrame(grid, "a int, b int, c int, d int")
    rows = df.select("*", R.digit(F.col("a"), F.col("b"), F.col("c"), F.col("d")).alias("r")).collect()
    assert all(r["r"] == relation(r["a"], r["b"], r["c"], r["d"]) for r in rows)
    assert {r["r"] for r in rows} == set(range(7))


def test_numbers_round_trip(spark):
    rng = random.Random(3)
    rows = [([rng.randint(0, 6) for _ in range(k)],) for k in (*range(1, 26), 40, 44, 45, 100)]
    df = spark.createDataFrame(rows, "d array<int>").withColumn("n", R.limbs(F.col("d")))
    for r in df.select("d", "n", R.limb_digits(F.col("n"), F.size("d")).alias("b"), R.tail_digits(F.col("d")).alias("t")).collect():
        value = int("".join(map(str, r["d"])), 7)
        assert list(r["d"]) == list(r["b"]) and list(r["n"]) == prefix.limbs(value, len(r["d"]))
        assert r["t"] == len("".join(map(str, r["d"])).lstrip("0"))
    one = spark.range(1).select(R.insert_digit(F.lit(15).cast("long"), 1, F.lit(3)).alias("v")).first()["v"]
    assert one == 2 * 49 + 3 * 7 + 1  # 21 in base 7 becomes 231


def test_numbers_of_long_timelines(spark):
    # 60 intervals that overlap, contain and follow one another
    iv = sorted((k // 2, k // 2 + 1 + (k * 7) % 40) for k in range(60))
    digits = [[relation(*iv[i], *iv[j]) for i in range(j)] for j in range(1, 60)]
    df = spark.createDataFrame([([{"st": a, "ft": b} for a, b in iv],)], "iv array<struct<st:long,ft:long>>")
    rel = R.matrix_numbers(R.matrix(F.col("iv")))
    row = df.select(rel.alias("rel"), R.triangle(rel, F.lit(60)).alias("t"), R.letters(rel, F.lit(60)).alias("l")).first()
    assert [list(t) for t in row["t"]] == digits
    assert row["rel"] == [v for k, own in enumerate(digits, 1) for v in prefix.limbs(int("".join(map(str, own)), 7), k)]
    assert row["l"] == ";".join("".join(R.LETTERS[d] for d in own) for own in digits)
    for n in (1, 2, 23, 24, 40, 60):
        assert spark.range(1).select(R.limbs_before(F.lit(n)).alias("v")).first()["v"] == sum(-(-k // 22) for k in range(1, n))


def numbers(iv):
    """Relation list of intervals in order."""
    return [v for k in range(1, len(iv)) for v in prefix.limbs(number(iv[:k], iv[k]), k)]


def test_rules_of_more_than_23_intervals(spark):
    # one timeline that only the rules of all its 25 intervals can pay for
    rows = [(1, f"s{k:02d}", k, k + 3, 1) for k in range(1, 27)]
    log = spark.createDataFrame(rows[:25], model.LOG)
    got = search.mine(log, minutil=25, minconf=0.5, engine="prefix").rules
    assert got.count() == 24  # every place of the arrow
    texts = {r["rel_text"] for r in got.select("rel_text").collect()}
    assert texts == {";".join("b" * max(0, k - 3) + "m" * (k >= 3) + "o" * min(k, 2) for k in range(1, 25))}
    # a rule of 23 intervals, s01 .. s12 -> s14 .. s24, grown by s13 on the left and by s25 or s26 on the right
    coded, _ = search.prepare(spark.createDataFrame(rows, model.LOG))
    items, opt = timelines.items(coded, 2), search.Options(1, 0.0)
    points = lambda codes: [(k, k + 3) for k in codes]
    x, y = list(range(1, 13)), list(range(14, 25))
    kind = "sid long, x array<int>, y array<int>, rel array<bigint>, xi array<struct<st:long,ft:long>>, yi array<struct<st:long,ft:long>>, last_x int, tie_y int, last_y int, tail_x long, tail_tie long, tail_y long, u long, open long, right long"
    occ = spark.createDataFrame([(1, x, y, numbers(points(x + y)), points(x), points(y), 12, 14, 24, 14, 13, 2, 23, 24, 25)], kind)
    for side, want in (("left", [(x + [13], y)]), ("right", [(x, y + [25]), (x, y + [26])])):
        grown = search.materialise(search.extensions(occ, items, side, opt), side, opt, 24).select("x", "y", "rel", "u").collect()
        assert sorted((r["x"], r["y"], r["rel"], r["u"]) for r in grown) == [(a, b, numbers(points(a + b)), 24) for a, b in want]
    ante = spark.createDataFrame([(1, x + y, numbers(points(x + y)), points(x + y), 24)], "sid long, x array<int>, xrel array<bigint>, xi array<struct<st:long,ft:long>>, last_x int")
    longer = x + y + [26]
    wanted = spark.createDataFrame([(longer, numbers(points(longer)))], "x array<int>, xrel array<bigint>")
    assert [r["last_x"] for r in search.grow_antecedents(ante, items, wanted, 25, opt).collect()] == [26]
    rule = spark.createDataFrame([(longer, [99], numbers(points(longer)) + [0, 0])], "x array<int>, y array<int>, rel array<bigint>")
    assert rule.select(search.antecedent_of(F.col("rel"), F.col("x")).alias("r")).first()["r"] == numbers(points(longer))


def test_minconf_is_exact(spark):
    df = spark.createDataFrame([(333333, 1000000), (333334, 1000000), (1, 3), (1, 10_000_000)], "n long, a long")
    held = lambda c: [r["v"] for r in df.select(measures.enough_confidence(F.col("n"), F.col("a"), c).alias("v")).collect()]
    assert held("1/3") == [False, True, True, False]
    assert held(1 / 3) == [False, True, True, False]
    assert held(1e-7) == [True] * 4 and held(2e-7) == [True, True, True, False]
    assert held(0.3333335) == [False, True, False, False]


def test_ledger_and_bounds_of_the_example(spark):
    coded, codes = search.prepare(example(spark))
    own = timelines.items(coded, 4)
    opt = search.Options(1, 0.0)
    occ = search.materialise(search.extensions(search.roots(own, opt), own, "right", opt), "right", opt, 3)
    rule = occ.filter((F.col("x") == F.array(F.lit(1))) & (F.col("y") == F.array(F.lit(2), F.lit(4))) & (F.col("rel") == F.array(F.lit(0), F.lit(2)).cast("array<bigint>")))
    got = sorted(tuple(r) for r in ledger.left(rule, coded.filter("sym = 'A'")).collect())
    assert got == [(1, True, 34), (2, True, 14), (3, False, 0)]
    assert {r["weight"] for r in bounds.symbol_weight(coded).collect()} == {62}
    literal = {r["sym"]: r["weight"] for r in bounds.symbol_weight(coded, True).join(codes, "code").collect()}
    assert literal == {"A": 12, "B": 15, "C": 14, "D": 21}


def test_timeline_array(spark):
    rows = [(4, "A", 2, 8, 8), (4, "B", 9, 15, 10), (4, "C", 14, 20, 7), (4, "D", 14, 22, 9)]
    coded, _ = search.prepare(spark.createDataFrame(rows, model.LOG))
    got = [(r["tail"], r["tie"], r["head"]) for r in timelines.items(coded, 2).orderBy("pos").collect()]
    assert got == [(26, 1, 34), (16, 2, 26), (9, 3, 16), (0, 3, 16)]
    assert got == [(e["tail"], e["tie"], e["head"]) for e in timelines.arrays(coded, 2).first()["iv"]]


def test_clean_and_empty(spark):
    rows = [(1, "A", 3, 3, 1), (1, "A", 1, 2, 1), (1, "A", 1, 2, 4), (None, "B", 1, 2, 1), (1, "C", 1, 2, -1)]
    got = model.clean(spark.createDataFrame(rows, model.LOG))
    assert [tuple(r) for r in got.good.collect()] == [(1, "A", 1, 2, 5)] and got.bad.count() == 3
    assert search.mine(spark.createDataFrame([], model.LOG), minutil=1).rules.count() == 0


def test_level_growth_has_no_exchange_on_occurrences(spark):
    coded, _ = search.prepare(example(spark))
    own = scratch.partitioned_checkpoint(timelines.items(coded, 4))
    opt = search.Options(1, 0.0)
    rows = scratch.in_session(search.extensions(search.roots(own, opt), own, "right", opt), scratch.fixed_plans(spark))
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Cartesian" not in plan and "Python" not in plan and "NestedLoop" not in plan


def test_the_session_keeps_its_settings(spark):
    before = spark.conf.get("spark.sql.adaptive.enabled")
    df = scratch.partitioned_checkpoint(spark.range(10).repartition(3, "id"))
    assert df.sparkSession is spark and df.count() == 10 and spark.conf.get("spark.sql.adaptive.enabled") == before


def test_shared_folder_is_demanded_on_a_cluster():
    class Context:
        master = "spark://host:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

        class conf:
            get = staticmethod(lambda name, default: default)

    with pytest.raises(RuntimeError):
        scratch.shared_dir(Session())


def test_baselines_agree(spark):
    log = random_log(spark, 9, size=4)
    assert keyed(baselines.two_stage(log, 20, 0.5, 4)) == keyed(search.mine(log, minutil=20, minconf=0.5, max_size=4).rules)
    a, b = (keyed(baselines.frequent_rules(log, 2, 0.5, 3, s)) for s in ("growth", "levelwise"))
    assert a == b
    every = {tuple(r) for r in baselines.frequent_patterns(log, 2, 3).collect() for r in [(tuple(r["x"]), tuple(r["rel"]), r["support"])]}
    assert every == {(tuple(r["x"]), tuple(r["rel"]), r["support"]) for r in baselines.frequent_patterns(log, 2, 3, "levelwise").collect()}


def test_symbols_leave_in_rounds(spark):
    # D leaves with A and B; without D's utility C is not worth enough
    rows = [(1, "A", 1, 2, 9), (1, "B", 3, 4, 2), (2, "C", 1, 2, 20), (2, "D", 3, 4, 20), (3, "C", 1, 2, 20), (4, "E", 1, 2, 60)]
    coded, _ = search.prepare(spark.createDataFrame(rows, model.LOG))
    kept, trace = bounds.prune_symbols(coded, 50)
    assert [(t["symbols"], t["removed"]) for t in trace] == [(5, 3), (2, 1), (1, 0)]
    assert [r["sym"] for r in kept.collect()] == ["E"]


def test_occurrences_of_rules(spark):
    log = random_log(spark, 4, size=5)
    coded, codes = search.prepare(log)
    rules = search.mine(log, minutil=25, minconf=0.3, max_size=4).rules.withColumn("rule_id", report.key_text()).collect()
    number_of = {r["sym"]: r["code"] for r in codes.collect()}
    own = spark.createDataFrame([(r["rule_id"], [number_of[s] for s in r["x"]], [number_of[s] for s in r["y"]], r["rel"]) for r in rules], "rule_id string, x array<int>, y array<int>, rel array<bigint>")
    arrays = timelines.arrays(coded, 3)
    got = match.occurrences(own, arrays).groupBy("rule_id").agg(F.count_distinct("sid").alias("n"), F.max("u").alias("u")).collect()
    assert {r["rule_id"]: r["n"] for r in got} == {r["rule_id"]: r["n_rule"] for r in rules}
    ante = match.occurrences(own, arrays, "ante").groupBy("rule_id").agg(F.count_distinct("sid").alias("n")).collect()
    assert {r["rule_id"]: r["n"] for r in ante} == {r["rule_id"]: r["n_ante"] for r in rules}
    one = rules[0]
    w = [number_of[s] for s in (*one["x"], *one["y"])]
    assert match.pattern_occurrences(arrays, w, list(one["rel"]), len(one["x"])).select("sid").distinct().count() == one["n_rule"]


def test_cost_of_a_run(spark):
    got = metrics.run(example(spark), minutil=35, minconf=0.6)
    assert (got["candidates"], got["rules"]) == (16, 5) and got["seconds"] > 0 and got["task_ms"] > 0 and got["bytes_base7"] <= got["bytes_matrix"]
    assert [level["size"] for level in got["levels"]][0] == 2


def test_a_run_leaves_no_files(spark):
    def files():
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(scratch.shared_dir(spark))
        found = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).listFiles(path, True)
        out = set()
        while found.hasNext():
            out.add(found.next().getPath().toString())
        return out

    metrics.run(example(spark), minutil=35, minconf=0.6)  # makes the folders
    before = files()
    assert metrics.run(random_log(spark, 1), minutil=10, minconf=0.1)["rules"] > 0
    assert files() <= before


def test_prefix_engine_scans_each_antecedent_once(monkeypatch):
    rng, scanned, plain = random.Random(3), [], prefix.DepthFirst._scan
    lines = []
    for _ in range(30):
        rows = sorted((st := rng.randint(0, 9), st + rng.randint(1, 5), rng.randint(1, 4), rng.randint(1, 9)) for _ in range(6))
        tie = [next(k for k, e in enumerate(rows, 1) if e[0] == r[0]) for r in rows]
        lines.append([(*r, sum(e[3] for e in rows[k + 1 :]), tie[k]) for k, r in enumerate(rows)])
    monkeypatch.setattr(prefix.DepthFirst, "_scan", lambda self, x, xrel: scanned.append((x, xrel)) or plain(self, x, xrel))
    run = prefix.DepthFirst(1, lines, search.Options(1, 0, max_size=4)).run()
    assert len(scanned) == len(set(scanned)) > 0
    for x, _, rel, _, n, _ in run.found:
        assert n == plain(run, tuple(x), tuple(rel[: len(x) - 1]))


@pytest.mark.parametrize("variant", ["full", "matrix", "no_budget", "no_zero_carry", "no_right_bound"])
def test_packed_search_equals_stored_levels(spark, variant, monkeypatch):
    monkeypatch.setattr(packed, "CHUNK", 25)  # several chunks and parts of rows
    monkeypatch.setattr(packed, "GROWN", 40)
    options = dict(minutil=25, minconf=0.3, max_size=5, disjoint="interval" if variant == "no_right_bound" else "symbol", **VARIANTS[variant])
    made, plain = [], packed.PackedSearch.__init__
    monkeypatch.setattr(packed.PackedSearch, "__init__", lambda self, *a: made.append(1) or plain(self, *a))
    new = search.mine(random_log(spark, 3), **options)
    assert made
    monkeypatch.setattr(search, "packable", lambda items, opt: None)
    old = search.mine(random_log(spark, 3), **options)
    assert keyed(new.rules) == keyed(old.rules) and keyed(new.rules)
    assert new.metrics.candidates == old.metrics.candidates and new.metrics.levels == old.metrics.levels


def test_wide_levels_are_stored(spark, monkeypatch):
    whole = search.mine(random_log(spark, 3), minutil=25, minconf=0.3, max_size=4)
    top = search.mine_top_k(random_log(spark, 3), 9, 0.3, max_size=4)
    monkeypatch.setattr(packed, "BROADCAST_ROWS", 3)
    assert keyed(search.mine(random_log(spark, 3), minutil=25, minconf=0.3, max_size=4).rules) == keyed(whole.rules)
    assert keyed(search.mine_top_k(random_log(spark, 3), 9, 0.3, max_size=4).rules) == keyed(top.rules)


def test_top_k_of_a_coded_log(spark):
    log = random_log(spark, 5, size=4)
    coded = search.ready(log)
    for variant in ("full", "matrix"):
        got = search.mine_top_k(coded, 7, 0.5, max_size=3, **VARIANTS[variant])
        assert keyed(got.rules) == keyed(search.mine_top_k(log, 7, 0.5, max_size=3).rules)


@pytest.mark.parametrize("disable", [frozenset(), frozenset({"confidence", "open_bound"})])
def test_prefix_task_of_column_arrays_equals_lists(disable, monkeypatch):
    monkeypatch.setattr(packed, "GROWN", 50)  # several parts of rows
    rng = random.Random(5)
    lines = [sorted((st := rng.randint(0, 9), st + rng.randint(1, 5), rng.randint(1, 4), rng.randint(1, 9)) for _ in range(6)) for _ in range(40)]
    for first in (1, 2):
        own = [rows[next(k for k, r in enumerate(rows) if r[2] == first) :] for rows in lines if first in [r[2] for r in rows]]
        full = [[(*r, sum(e[3] for e in rows[k + 1 :]), next(j for j, e in enumerate(rows, 1) if e[0] == r[0])) for k, r in enumerate(rows)] for rows in own]
        opt = search.Options(60, 0.1, max_size=4, disable=disable)
        column = pa.chunked_array([pa.array([[dict(zip(("st", "ft", "code", "u"), r)) for r in rows] for rows in part]) for part in (own[:7], own[7:])])
        a, b = prefix.DepthFirst(first, full, opt).run(), prefix.Subtree(first, prefix.chunk_of(column, opt, 4), opt).run()
        assert sorted(a.found) == sorted(b.found) and a.found and a.candidates == b.candidates
