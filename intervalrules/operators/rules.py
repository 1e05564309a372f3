"""Registered queries over the methods of rule mining; columns are LONG, INT or STRING."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import relations as R
from ..plans import baselines, bounds, ledger, match, measures, model, report, search, timelines
from ..plans.scratch import Tables
from ..plans.search import KEY
from ..plans.variants import VARIANTS
from ..sources import synth
from ..sources import tables as T
from . import oracles as O

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

EXAMPLE_ROWS = [(1, "A", 1, 3, 8), (1, "C", 5, 8, 10), (1, "B", 7, 11, 7), (1, "D", 10, 14, 9), (2, "A", 1, 3, 2), (2, "C", 4, 6, 2), (2, "B", 7, 11, 4), (2, "D", 10, 14, 6), (3, "A", 1, 2, 2), (3, "B", 3, 4, 4), (3, "C", 5, 6, 2), (3, "D", 7, 9, 6)]


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


def example(spark) -> DataFrame:
    return spark.createDataFrame(EXAMPLE_ROWS, model.LOG)


def coded(spark, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    return search.prepare(T.LOGS[name](spark, sf_dir))


def flat(spark, sf_dir: str, name: str) -> DataFrame:
    """Intervals with position, tail, tie and symbol."""
    log, codes = coded(spark, sf_dir, name)
    return timelines.items(log, search.partitions(log)).join(codes, "code")


def arrays(spark, sf_dir: str, name: str) -> DataFrame:
    log, _ = coded(spark, sf_dir, name)
    return timelines.arrays(log, search.partitions(log))


def pairs(spark, sf_dir: str, name: str) -> DataFrame:
    """Ordered pairs of each timeline, by a merge join on the timeline."""
    items = flat(spark, sf_dir, name).select("sid", "pos", "sym", "st", "ft")
    a, b = (items.select("sid", *[F.col(c).alias(f"{p}_{c}") for c in items.columns[1:]]) for p in "ab")
    rows = a.join(b, "sid").filter("a_pos < b_pos")
    return rows.select("sid", F.col("a_pos").alias("pa"), F.col("b_pos").alias("pb"), F.col("a_sym").alias("sa"), F.col("b_sym").alias("sb"), R.digit(F.col("a_st"), F.col("a_ft"), F.col("b_st"), F.col("b_ft")).alias("d"))


def sorted_points(spark, sf_dir: str, name: str) -> DataFrame:
    """sid and p, the ends of its intervals in order (intervals with equal ends have the same relations, in whatever order)."""
    log = model.clean(T.LOGS[name](spark, sf_dir)).good
    return log.groupBy("sid").agg(F.array_sort(F.collect_list(F.struct("st", "ft"))).alias("p"))


def log_columns(df: DataFrame) -> DataFrame:
    return df.select("sid", "sym", "st", "ft", "u")


for _name in T.LOGS:
    query(f"log_{_name}", f"WITH {O.log(_name)} SELECT sid, sym, st, ft, u FROM log")(lambda spark, d, n=_name: log_columns(model.clean(T.LOGS[n](spark, d)).good))


@query("log_features", " UNION ALL ".join(f"SELECT '{n}' AS log, CAST(count(DISTINCT sid) AS BIGINT) AS timelines, CAST(count(DISTINCT sym) AS BIGINT) AS symbols, CAST(count(*) AS BIGINT) AS intervals, CAST(sum(u) AS BIGINT) AS utility FROM (WITH {O.log(n)} SELECT * FROM log)" for n in T.LOGS))
def log_features(spark, d):
    out = None
    for name, make in T.LOGS.items():
        own = model.clean(make(spark, d)).good.agg(F.lit(name).alias("log"), F.count_distinct("sid").alias("timelines"), F.count_distinct("sym").alias("symbols"), F.count(F.lit(1)).alias("intervals"), F.sum("u").alias("utility"))
        out = own if out is None else out.unionByName(own)
    return out


@query("symbol_codes", f"WITH {O.log('items_by_brand')} SELECT sym, CAST(row_number() OVER (ORDER BY sym) AS INT) AS code FROM (SELECT DISTINCT sym FROM log)")
def symbol_codes(spark, d):
    return coded(spark, d, "items_by_brand")[1].select("sym", "code")


@query("quarantine_zero_length", f"SELECT sid, sym, st, st AS ft, CAST(0 AS BIGINT) AS u FROM ({O.RAW['talk_turns']})")
def quarantine_zero_length(spark, d):
    """Every turn also as an empty interval, which belongs to the quarantine."""
    turns = T.talk_turns_raw(spark, d)
    empty = turns.withColumns({"ft": F.col("st"), "u": F.lit(0).cast("long")})
    return model.clean(turns.filter("st < ft").unionByName(empty)).bad


@query("merged_duplicates", f"SELECT sid, sym, CAST(st AS BIGINT) AS st, CAST(ft AS BIGINT) AS ft, CAST(count(*) AS BIGINT) AS n, CAST(sum(u) AS BIGINT) AS u FROM ({O.RAW['quarter_spans']}) GROUP BY ALL HAVING count(*) > 1")
def merged_duplicates(spark, d):
    return T.quarter_spans_raw(spark, d).groupBy("sid", "sym", "st", "ft").agg(F.count(F.lit(1)).alias("n"), F.sum("u").alias("u")).filter("n > 1")


@query("timeline_arrays", O.on("items_by_type", "SELECT sid, CAST(p AS INT) AS pos, sym, st, ft, u, tail, CAST(tie AS INT) AS tie FROM iv"))
def timeline_arrays(spark, d):
    return flat(spark, d, "items_by_type").select("sid", "pos", "sym", "st", "ft", "u", "tail", "tie")


@query("timeline_size_histogram", f"WITH {O.log('user_weeks')} SELECT n AS size, CAST(count(*) AS BIGINT) AS timelines FROM (SELECT CAST(count(*) AS BIGINT) AS n FROM log GROUP BY sid) GROUP BY n")
def timeline_size_histogram(spark, d):
    return model.clean(T.user_weeks(spark, d)).good.groupBy("sid").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("timelines"))


@query("relation_pairs", O.on("quarter_spans", "SELECT sid, CAST(pa AS INT) AS pa, CAST(pb AS INT) AS pb, sa, sb, d FROM pairs", O.PAIRS))
def relation_pairs(spark, d):
    return pairs(spark, d, "quarter_spans").select("sid", "pa", "pb", "sa", "sb", "d")


MIX_LOGS = ("order_spans", "short_order_spans", "quarter_spans", "items_by_type", "items_by_brand", "user_weeks", "user_days", "talk_turns")


@query("relation_mix", " UNION ALL ".join(f"SELECT '{n}' AS log, d, CAST(count(*) AS BIGINT) AS n FROM ({O.on(n, 'SELECT d FROM pairs', O.PAIRS)}) GROUP BY d" for n in MIX_LOGS))
def relation_mix(spark, d):
    """Digit counts of all ordered pairs; a timeline's digits are counted where its intervals are."""
    out = None
    for name in MIX_LOGS:
        of = lambda j, b: F.transform(F.slice("p", 1, j), lambda a: R.digit(a["st"], a["ft"], b["st"], b["ft"]))
        digits = sorted_points(spark, d, name).select(F.explode(F.flatten(F.transform("p", lambda b, j: of(j, b)))).alias("d"))
        own = digits.groupBy("d").agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("log"), "d", "n")
        out = own if out is None else out.unionByName(own)
    return out


ALLEN = "CASE WHEN b.st < a.st OR (b.st = a.st AND b.ft < a.ft) THEN {inv} || '-i' ELSE {fwd} END".format(
    fwd="['before','meets','overlaps','contains','finished-by','starts','equals'][" + O.digit("a.st", "a.ft", "b.st", "b.ft") + " + 1]",
    inv="['before','meets','overlaps','contains','finished-by','starts','equals'][" + O.digit("b.st", "b.ft", "a.st", "a.ft") + " + 1]",
)


@query("relation13_pairs", O.on("quarter_spans", f"SELECT a.sid, CAST(a.p AS INT) AS pa, CAST(b.p AS INT) AS pb, {ALLEN} AS rel FROM iv a JOIN iv b ON a.sid = b.sid AND a.p <> b.p"))
def relation13_pairs(spark, d):
    rows = arrays(spark, d, "quarter_spans").select("sid", "iv", F.explode("iv").alias("a")).select("sid", "a", F.explode("iv").alias("b")).filter("a.pos <> b.pos")
    a, b = F.col("a"), F.col("b")
    return rows.select("sid", a["pos"].alias("pa"), b["pos"].alias("pb"), R.allen13(a["st"], a["ft"], b["st"], b["ft"]).alias("rel"))


def numbered(spark, d, name="quarter_spans"):
    """sid, pos, num (limbs), digits: the number of every interval against all earlier ones of its timeline, however long."""
    rows = arrays(spark, d, name).select("sid", "iv", F.explode("iv").alias("e")).filter("e.pos > 1")
    own = R.digits_against(F.expr("slice(iv, 1, e.pos - 1)"), F.col("e.st"), F.col("e.ft"))
    return rows.select("sid", F.col("e.pos").alias("pos"), R.limbs(own).alias("num"))


def back(k):
    """The digits of num, decoded."""
    return R.limb_digits(F.col("num"), k)


# num: limbs of 22 digits, the highest first
_POWER = "CAST([" + ", ".join(str(7**k) for k in range(22)) + "][(pb - 1 - pa) % 22 + 1] AS HUGEINT)"
NUMBERS = (
    O.PAIRS
    + f",\nlimbs AS (SELECT sid, pb, (pb - 1 - pa) // 22 AS place, CAST(sum(d * {_POWER}) AS BIGINT) AS v, string_agg(CAST(d AS VARCHAR), '' ORDER BY pa) AS part FROM pairs GROUP BY ALL)"
    + ",\nnums AS (SELECT sid, CAST(pb AS INT) AS pos, string_agg(CAST(v AS VARCHAR), ',' ORDER BY place DESC) AS num, string_agg(part, '' ORDER BY place DESC) AS text FROM limbs GROUP BY sid, pb)"
)


@query("relation_numbers", O.on("quarter_spans", "SELECT sid, pos, num FROM nums", NUMBERS))
def relation_numbers(spark, d):
    return numbered(spark, d).withColumn("num", F.array_join(F.col("num").cast("array<string>"), ","))


@query("relation_digits_back", O.on("quarter_spans", "SELECT sid, pos, text FROM nums", NUMBERS))
def relation_digits_back(spark, d):
    return numbered(spark, d).select("sid", "pos", F.array_join(back(F.col("pos") - 1), "").alias("text"))


@query("relation_letters", O.on("quarter_spans", "SELECT sid, pos, translate(text, '0123456', 'bmocfse') AS text FROM nums", NUMBERS))
def relation_letters(spark, d):
    return numbered(spark, d).select("sid", "pos", F.array_join(F.transform(back(F.col("pos") - 1), R.letter), "").alias("text"))


def carried(spark, d):
    """sid, pos, compared pairs of each interval with and without zero carry."""
    rows = numbered(spark, d, "items_by_type")
    own = Window.partitionBy("sid").orderBy("pos")
    before = F.coalesce(F.lag(R.tail_digits(back(F.col("pos") - 1))).over(own), F.lit(0))
    return rows.withColumns({"compared": before + 1, "pairs": F.col("pos") - 1})


@query("zero_carry_pairs_saved", O.on("items_by_type", "SELECT CAST(sum(pos - 1) AS BIGINT) AS pairs, CAST(sum(1 + coalesce(length(ltrim(prev, '0')), 0)) AS BIGINT) AS compared FROM (SELECT sid, pos, lag(text) OVER (PARTITION BY sid ORDER BY pos) AS prev FROM nums)", NUMBERS))
def zero_carry_pairs_saved(spark, d):
    return carried(spark, d).agg(F.sum("pairs").cast("long").alias("pairs"), F.sum("compared").cast("long").alias("compared"))


@query("checking_area", O.on("items_by_type", "SELECT sid, pos, CAST(length(text) - length(ltrim(text, '0')) AS INT) AS n_earlier, CAST(pos - (length(text) - length(ltrim(text, '0'))) AS INT) AS n_checking FROM nums", NUMBERS))
def checking_area(spark, d):
    """For the interval after position pos: how many earlier ones are surely before it, how many are to be compared."""
    area = R.split_area(F.col("num"), F.col("pos"))
    return numbered(spark, d, "items_by_type").withColumn("a", area).select("sid", "pos", F.size("a.earlier").alias("n_earlier"), F.size("a.checking").alias("n_checking"))


INSERTED = O.on("short_order_spans", "SELECT sid, CAST(a AS INT) AS a, CAST(b AS INT) AS b, CAST(c AS INT) AS c, CAST(" + O.digit("st1", "ft1", "st3", "ft3") + " * 7 + " + O.digit("st2", "ft2", "st3", "ft3") + " AS BIGINT) AS num FROM (SELECT x.sid, x.p AS a, y.p AS b, z.p AS c, x.st AS st1, x.ft AS ft1, y.st AS st2, y.ft AS ft2, z.st AS st3, z.ft AS ft3 FROM iv x JOIN iv y ON x.sid = y.sid AND x.p < y.p JOIN iv z ON y.sid = z.sid AND y.p < z.p)")


@query("inserted_numbers", INSERTED)
def inserted_numbers(spark, d):
    """Triples a, b, c: the number of c against a alone gains b's digit."""
    rows = arrays(spark, d, "short_order_spans").select("sid", "iv", F.explode("iv").alias("a")).select("sid", "iv", "a", F.explode(F.expr("slice(iv, a.pos + 1, size(iv))")).alias("b")).select("sid", "a", "b", F.explode(F.expr("slice(iv, b.pos + 1, size(iv))")).alias("c"))
    a, b, c = F.col("a"), F.col("b"), F.col("c")
    num = R.insert_digit(R.digit(a["st"], a["ft"], c["st"], c["ft"]).cast("long"), 0, R.digit(b["st"], b["ft"], c["st"], c["ft"]))
    return rows.select("sid", a["pos"].alias("a"), b["pos"].alias("b"), c["pos"].alias("c"), num.alias("num"))


ROWS = "rws AS (SELECT sid, pb, string_agg(CAST(d AS VARCHAR), ',' ORDER BY pa) AS r, sum(d * CAST(8 ** (pb - 1 - pa) AS BIGINT)) AS o FROM pairs GROUP BY sid, pb)"


@query("matrix_layout", O.on("short_order_spans", "SELECT sid, string_agg(r, ';' ORDER BY pb) AS text FROM rws GROUP BY sid", O.PAIRS, ROWS))
def matrix_layout(spark, d):
    rows = arrays(spark, d, "short_order_spans").filter("size(iv) > 1")
    return rows.select("sid", F.array_join(F.transform(R.matrix(F.col("iv")), lambda r: F.array_join(r, ",")), ";").alias("text"))


@query("sparse_layout", O.on("short_order_spans", "SELECT sid, coalesce(string_agg(CASE WHEN d <> 0 THEN pa || ':' || pb || ':' || d END, ';' ORDER BY pb, pa), '') AS text FROM pairs GROUP BY sid", O.PAIRS))
def sparse_layout(spark, d):
    rows = arrays(spark, d, "short_order_spans").filter("size(iv) > 1")
    return rows.select("sid", F.array_join(F.transform(R.sparse(R.matrix(F.col("iv"))), lambda e: F.concat_ws(":", e["i"].cast("string"), e["j"].cast("string"), e["d"].cast("string"))), ";").alias("text"))


@query("octal_layout", O.on("short_order_spans", "SELECT sid, string_agg(CAST(CAST(o AS BIGINT) AS VARCHAR), ',' ORDER BY pb) AS text FROM rws GROUP BY sid", O.PAIRS, ROWS))
def octal_layout(spark, d):
    rows = arrays(spark, d, "short_order_spans").filter("size(iv) > 1")
    return rows.select("sid", F.array_join(F.transform(R.matrix(F.col("iv")), lambda r: R.pack8(r).cast("string")), ",").alias("text"))


@query("layout_bytes", O.on("quarter_spans", "SELECT CAST(sum(length(m)) AS BIGINT) AS matrix_bytes, CAST(sum(length(num)) AS BIGINT) AS base7_bytes FROM (SELECT num, array_to_string(string_split(text, ''), ',') AS m FROM nums)", NUMBERS))
def layout_bytes(spark, d):
    rows = numbered(spark, d)
    return rows.agg(F.sum(F.octet_length(F.array_join(back(F.col("pos") - 1), ","))).cast("long").alias("matrix_bytes"), F.sum(F.octet_length(F.array_join(F.col("num").cast("array<string>"), ","))).cast("long").alias("base7_bytes"))


# ---- weights and bounds ----

WEIGHT = f"WITH {O.log('items_by_brand')}, t AS (SELECT sid, sum(u) AS total FROM log GROUP BY sid)"


@query("symbol_weight", WEIGHT + " SELECT sym, CAST(sum(total) AS BIGINT) AS weight FROM (SELECT DISTINCT sid, sym FROM log) JOIN t USING (sid) GROUP BY sym")
def symbol_weight(spark, d, literal=False):
    log, codes = coded(spark, d, "items_by_brand")
    return bounds.symbol_weight(log, literal).join(codes, "code").select("sym", "weight")


@query("symbol_own_utility", f"WITH {O.log('items_by_brand')} SELECT sym, CAST(sum(u) AS BIGINT) AS weight FROM log GROUP BY sym")
def symbol_own_utility(spark, d):
    return symbol_weight(spark, d, True)


def _rounds(n: int) -> str:
    """Unrolled removal: each round drops symbols whose weight is below 14.687 % of the total utility (two rounds at sf0.01)."""
    out = [O.log("items_by_brand").replace("log AS", "r0 AS", 1)]
    for k in range(n):
        out.append(f"w{k} AS (SELECT sym, sum(total) AS w FROM (SELECT DISTINCT sid, sym FROM r{k}) JOIN (SELECT sid, sum(u) AS total FROM r{k} GROUP BY sid) USING (sid) GROUP BY sym), r{k + 1} AS (SELECT * FROM r{k} WHERE sym IN (SELECT sym FROM w{k} WHERE w >= (SELECT ceil(0.14687 * sum(u)) FROM r0)))")
    return "WITH " + ", ".join(out) + f" SELECT sym, CAST(count(*) AS BIGINT) AS intervals FROM r{n} GROUP BY sym"


@query("prune_symbols", _rounds(12))
def prune_symbols(spark, d):
    log, codes = coded(spark, d, "items_by_brand")
    kept, _ = bounds.prune_symbols(log, search.resolve_threshold(log, None, 0.14687))
    return kept.groupBy("sym").agg(F.count(F.lit(1)).alias("intervals"))


def root_rows(spark, d, name="items_by_type", occurrence="max"):
    log, codes = coded(spark, d, name)
    opt = search.Options(0, 0.0, occurrence=occurrence)
    rows = search.roots(timelines.items(log, search.partitions(log)), opt)
    of = lambda c: codes.select(F.col("code").alias(f"code_{c}"), F.col("sym").alias(c))
    rows = rows.withColumns({"code_sa": F.col("x")[0], "code_sb": F.col("y")[0], "d": F.col("rel")[0].cast("int")})
    return log, rows.join(of("sa"), "code_sa").join(of("sb"), "code_sb")


ROOT = ["sa", "sb", "d"]
PER = "per AS (SELECT sid, sa, sb, d, max(u) AS u, max(u + lr) AS lb, max(u + rr) AS rb, max(u + lr + rr) AS ob FROM roots GROUP BY sid, sa, sb, d)"


@query("roots", O.on("items_by_type", "SELECT sa, sb, d, CAST(count(*) AS BIGINT) AS n_rule, CAST(sum(per.u) AS BIGINT) AS utility, any_value(n_ante) AS n_ante FROM per JOIN (SELECT sym AS sa, count(DISTINCT sid) AS n_ante FROM log GROUP BY sym) USING (sa) GROUP BY sa, sb, d", O.PAIRS, O.ROOTS, PER))
def roots(spark, d):
    log, rows = root_rows(spark, d)
    best = measures.utility_in(rows, ROOT)
    ante = log.select("sid", F.col("sym").alias("sa")).distinct().groupBy("sa").agg(F.count(F.lit(1)).alias("n_ante"))
    return measures.utility(best, ROOT).join(ante, "sa").select(*ROOT, "n_rule", "utility", "n_ante")


@query("root_support", O.on("items_by_type", "SELECT sa, sb, d, CAST(count(DISTINCT sid) AS BIGINT) AS n_rule, CAST((SELECT count(DISTINCT sid) FROM log) AS BIGINT) AS n_timelines FROM roots GROUP BY sa, sb, d", O.PAIRS, O.ROOTS))
def root_support(spark, d):
    log, rows = root_rows(spark, d)
    total = log.agg(F.count_distinct("sid").alias("n_timelines"))
    return rows.groupBy(*ROOT).agg(F.count_distinct("sid").alias("n_rule")).crossJoin(total)  # one row


@query("root_confidence", O.on("user_weeks", "SELECT sa, sb, d, CAST(n_rule * 1000000 // n_ante AS BIGINT) AS confidence_ppm FROM (SELECT sa, sb, d, count(DISTINCT sid) AS n_rule FROM roots GROUP BY sa, sb, d) JOIN (SELECT sym AS sa, count(DISTINCT sid) AS n_ante FROM log GROUP BY sym) USING (sa)", O.PAIRS, O.ROOTS))
def root_confidence(spark, d):
    log, rows = root_rows(spark, d, "user_weeks")
    ante = log.groupBy(F.col("sym").alias("sa")).agg(F.count_distinct("sid").alias("n_ante"))
    return rows.groupBy(*ROOT).agg(F.count_distinct("sid").alias("n_rule")).join(ante, "sa").select(*ROOT, F.expr("n_rule * 1000000 DIV n_ante").alias("confidence_ppm"))


@query("root_utility_first", O.on("items_by_type", "SELECT sa, sb, d, CAST(sum(u) AS BIGINT) AS utility FROM (SELECT sid, sa, sb, d, arg_min(u, [pa, pb]) AS u FROM roots GROUP BY sid, sa, sb, d) GROUP BY sa, sb, d", O.PAIRS, O.ROOTS))
def root_utility_first(spark, d):
    _, rows = root_rows(spark, d, occurrence="first")
    return measures.utility_in(rows, ROOT, "first").groupBy(*ROOT).agg(F.sum("u").alias("utility"))


@query("reserves", O.on("items_by_type", "SELECT sid, CAST(pa AS INT) AS pa, CAST(pb AS INT) AS pb, lr AS left_reserve, rr AS right_reserve FROM roots", O.PAIRS, O.ROOTS))
def reserves(spark, d):
    _, rows = root_rows(spark, d)
    return rows.select("sid", F.col("last_x").alias("pa"), F.col("last_y").alias("pb"), bounds.left_reserve(F.col("tail_x"), F.col("tail_tie")).alias("left_reserve"), bounds.right_reserve(F.col("tail_y")).alias("right_reserve"))


def _bound_query(name: str, column: str, expr):
    sql = {"left": "lb", "right": "rb", "open": "ob"}[column]

    @query(name, O.on("items_by_type", f"SELECT sa, sb, d, CAST(sum({sql}) AS BIGINT) AS bound FROM per GROUP BY sa, sb, d", O.PAIRS, O.ROOTS, PER))
    def run(spark, d):
        _, rows = root_rows(spark, d)
        return bounds.per_timeline(rows.withColumn("bound", expr()), ROOT, "bound").groupBy(*ROOT).agg(F.sum("bound").alias("bound"))


_bound_query("root_left_bound", "left", lambda: bounds.left_bound(F.col("u"), bounds.left_reserve(F.col("tail_x"), F.col("tail_tie"))))
_bound_query("root_right_bound", "right", lambda: F.col("right"))
_bound_query("root_open_bound", "open", lambda: F.col("open"))

FIXED = "sa = (SELECT min(sym) FROM log) AND sb = (SELECT max(sym) FROM log) AND d = 0"


def fixed_root(spark, d):
    """The rule from the first symbol to the last one with relation before."""
    log, rows = root_rows(spark, d)
    ends = log.agg(F.min("sym").alias("lo"), F.max("sym").alias("hi")).first()
    return log, ends, rows.filter((F.col("sa") == ends["lo"]) & (F.col("sb") == ends["hi"]) & (F.col("d") == 0))


@query("left_ledger", O.on("items_by_type", f"SELECT a.sid, b.ub IS NOT NULL AS occurs, CAST(coalesce(b.ub, 0) AS BIGINT) AS ub FROM (SELECT DISTINCT sid FROM log WHERE sym = (SELECT min(sym) FROM log)) a LEFT JOIN (SELECT sid, max(u + lr + rr) AS ub FROM roots WHERE {FIXED} GROUP BY sid) b USING (sid)", O.PAIRS, O.ROOTS))
def left_ledger(spark, d):
    log, ends, rows = fixed_root(spark, d)
    return ledger.left(rows, log.filter(F.col("sym") == ends["lo"]))


@query("right_ledger", O.on("items_by_type", f"SELECT sid, CAST(max(u + rr) AS BIGINT) AS ub FROM roots WHERE {FIXED} GROUP BY sid", O.PAIRS, O.ROOTS))
def right_ledger(spark, d):
    return ledger.right(fixed_root(spark, d)[2])


def grown(spark, d, side: str):
    log, codes = coded(spark, d, "items_by_type")
    opt = search.Options(0, 0.0)
    own = timelines.items(log, search.partitions(log))
    return opt, codes, search.extensions(search.roots(own, opt), own, side, opt)


def growth(spark, d, side):
    opt, codes, rows = grown(spark, d, side)
    occ = search.materialise(rows, side, opt, 3)
    stats = measures.utility(measures.utility_in(occ, KEY), KEY)
    return model.named(stats, codes, "x", "y").select(report.key_text().alias("rule"), "n_rule", "utility")


for _side, _name, _x, _y in (("left", "left_growth_2x1", 2, 1), ("right", "right_growth_1x2", 1, 2)):
    _sql = O.on("items_by_type", f"SELECT rule, n_rule, utility FROM rated WHERE len(string_split(split_part(rule, '>', 1), ',')) = {_x} AND len(string_split(split_part(split_part(rule, '>', 2), '|', 1), ',')) = {_y}", O.levels(3), O.rated(3))
    query(_name, _sql)(lambda spark, d, s=_side: growth(spark, d, s))

# left extensions of roots: e between the antecedent and the consequent's tie head
LEFT = "ext AS (SELECT r.sid, r.sa, r.sb, r.d, e.sym AS code, " + O.digit("a.st", "a.ft", "e.st", "e.ft") + " AS digit, r.u + e.u + greatest(e.tail - (t.tail + t.u), 0) + r.tb AS bound FROM roots r JOIN iv a ON a.sid = r.sid AND a.p = r.pa JOIN iv t ON t.sid = r.sid AND t.p = r.tie JOIN iv e ON e.sid = r.sid AND e.p > r.pa AND e.p < r.tie AND e.sym <> r.sb)"
CLASSES = "cls AS (SELECT sa, sb, d, code, digit, CAST(sum(b) AS BIGINT) AS bound FROM (SELECT sid, sa, sb, d, code, digit, max(bound) AS b FROM ext GROUP BY ALL) GROUP BY ALL)"


def class_rows(spark, d, by_digit=True):
    _, codes, rows = grown(spark, d, "left")
    found = bounds.class_bound(rows, KEY) if by_digit else bounds.symbol_budget(rows, KEY)
    for name, code in (("sa", F.col("x")[0]), ("sb", F.col("y")[0]), ("sym", F.col("code"))):
        found = found.withColumn("at", code).join(codes.select(F.col("code").alias("at"), F.col("sym").alias(f"{name}_")), "at").drop("at")
    return found.select(F.col("sa_").alias("sa"), F.col("sb_").alias("sb"), F.col("rel")[0].cast("int").alias("d"), F.col("sym_").alias("code"), *(["digit"] if by_digit else []), "bound", *(["side"] if by_digit else []))


@query("symbol_budget", O.on("items_by_type", "SELECT sa, sb, d, code, CAST(sum(b) AS BIGINT) AS bound FROM (SELECT sid, sa, sb, d, code, max(bound) AS b FROM ext GROUP BY ALL) GROUP BY ALL", O.PAIRS, O.ROOTS, LEFT))
def symbol_budget(spark, d):
    return class_rows(spark, d, False)


@query("class_bounds", O.on("items_by_type", "SELECT sa, sb, d, code, digit, bound FROM cls", O.PAIRS, O.ROOTS, LEFT, CLASSES))
def class_bounds(spark, d):
    return class_rows(spark, d).drop("side")


@query("class_budget_trace", O.on("items_by_type", "SELECT sa, sb, d, code, digit, bound, CAST(sum(bound) OVER (PARTITION BY sa, sb, d, code ORDER BY digit DESC) AS BIGINT) AS rest, bound >= bar AS kept, sum(bound) OVER (PARTITION BY sa, sb, d, code ORDER BY digit DESC) >= bar AS visited FROM cls, (SELECT ceil(0.002 * sum(u)) AS bar FROM log)", O.PAIRS, O.ROOTS, LEFT, CLASSES))
def class_budget_trace(spark, d):
    bar = search.resolve_threshold(coded(spark, d, "items_by_type")[0], None, 0.002)
    return bounds.class_budget(class_rows(spark, d), ["sa", "sb", "d"], bar, trace=True).drop("side")


@query("confidence_gate", O.on("user_weeks", "SELECT sa, sb, d, CAST(n_rule AS BIGINT) AS n_rule, n_ante FROM (SELECT sa, sb, d, count(DISTINCT sid) AS n_rule FROM roots GROUP BY sa, sb, d) JOIN (SELECT sym AS sa, count(DISTINCT sid) AS n_ante FROM log GROUP BY sym) USING (sa) WHERE n_rule * 4 >= n_ante", O.PAIRS, O.ROOTS))
def confidence_gate(spark, d):
    log, rows = root_rows(spark, d, "user_weeks")
    ante = log.groupBy(F.col("sym").alias("sa")).agg(F.count_distinct("sid").alias("n_ante"))
    stats = rows.groupBy(*ROOT).agg(F.count_distinct("sid").alias("n_rule")).join(ante, "sa")
    return stats.filter(measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), 0.25)).select(*ROOT, "n_rule", "n_ante")


# ---- mining ----


def rule_rows(rules: DataFrame) -> DataFrame:
    return rules.select(report.key_text().alias("rule"), "n_rule", "n_ante", "utility")


def mined(spark, d, log: str, **options) -> DataFrame:
    return rule_rows(search.mine(T.LOGS[log](spark, d), **options).rules)


# name: (log, ratio, minconf, cap of the search, cap of the enumeration)
MINES = {
    "mine_short_order_spans": ("short_order_spans", 0.001, 0.02, None, 7),
    "mine_order_spans": ("order_spans", 0.02, 0.1, 4, 4),
    "mine_quarter_spans": ("quarter_spans", 0.01, 0.1, 4, 4),
    "mine_items_by_type": ("items_by_type", 0.002, 0.03, 4, 4),
    "mine_items_by_brand": ("items_by_brand", 0.004, 0.05, 4, 4),
    "mine_user_weeks": ("user_weeks", 0.05, 0.25, 3, 3),
    "mine_user_days": ("user_days", 0.002, 0.05, 4, 4),
    "mine_talk_turns": ("talk_turns", 0.1, 0.6, None, 8),
}
for _name, (_log, _ratio, _conf, _cap, _all) in MINES.items():
    query(_name, O.mine(_log, _ratio, _conf, _all))(lambda spark, d, a=(_log, _ratio, _conf, _cap): mined(spark, d, a[0], minutil_ratio=a[1], minconf=a[2], max_size=a[3]))

query("mine_interval_disjoint", O.mine("talk_turns", 0.1, 0.6, 8, disjoint="interval"))(lambda spark, d: mined(spark, d, "talk_turns", minutil_ratio=0.1, minconf=0.6, disjoint="interval"))
query("mine_first_occurrence", O.mine("short_order_spans", 0.001, 0.02, 7, occurrence="first"))(lambda spark, d: mined(spark, d, "short_order_spans", minutil_ratio=0.001, minconf=0.02, occurrence="first"))
query("mine_side_caps", O.mine("talk_turns", 0.05, 0.6, 5, max_x=3, max_y=2))(lambda spark, d: mined(spark, d, "talk_turns", minutil_ratio=0.05, minconf=0.6, max_x=3, max_y=2))
for _variant, _options in VARIANTS.items():
    if _variant in ("matrix", "no_budget", "neither", "no_zero_carry"):
        query(f"mine_items_{_variant}", ORACLES["mine_items_by_type"])(lambda spark, d, o=_options: mined(spark, d, "items_by_type", minutil_ratio=0.002, minconf=0.03, max_size=4, **o))
    elif _variant != "full":
        query(f"mine_short_{_variant}", O.mine("short_order_spans", 0.002, 0.05, 7))(lambda spark, d, o=_options: mined(spark, d, "short_order_spans", minutil_ratio=0.002, minconf=0.05, **o))
query("mine_subtrees_engine", ORACLES["mine_items_by_type"])(lambda spark, d: mined(spark, d, "items_by_type", minutil_ratio=0.002, minconf=0.03, max_size=4, engine="subtrees", batch_timelines=50_000))
query("mine_prefix_engine", ORACLES["mine_items_by_type"])(lambda spark, d: mined(spark, d, "items_by_type", minutil_ratio=0.002, minconf=0.03, max_size=4, engine="prefix"))

# ties are broken by the rule's arrays of codes, as in the search
TOP = "ORDER BY utility DESC, n_rule / n_ante DESC, rule LIMIT 200"


@query("top_k_items", O.mine("items_by_type", None, 0.03, 4, minutil=1, tail=TOP))
def top_k_items(spark, d):
    return rule_rows(search.mine_top_k(T.items_by_type(spark, d), 200, 0.03, max_size=4).rules)


query("running_example", O.mine("example", None, 0.6, 4, minutil=35))(lambda spark, d: rule_rows(search.mine(example(spark), minutil=35, minconf=0.6).rules))


@query("running_example_candidates", "SELECT * FROM (VALUES (35, 'full', CAST(16 AS BIGINT), CAST(5 AS BIGINT)), (35, 'matrix', 16, 5), (35, 'no_budget', 23, 5), (20, 'full', 19, 11)) t(minutil, variant, candidates, rules)")
def running_example_candidates(spark, d):
    rows = []
    for minutil, name in ((35, "full"), (35, "matrix"), (35, "no_budget"), (20, "full")):
        got = search.mine(example(spark), minutil=minutil, minconf=0.6, **VARIANTS[name])
        rows.append((minutil, name, got.metrics.candidates, got.rules.count()))
    return spark.createDataFrame(rows, "minutil int, variant string, candidates long, rules long")


LINE = "length(rule) + length(CAST(utility AS VARCHAR)) + 27"


@query("output_bytes_by_layout", O.mine("quarter_spans", 0.01, 0.1, 4).replace("SELECT rule, n_rule, n_ante, utility FROM rated", f"SELECT CAST(sum({LINE}) AS BIGINT) AS bytes_base7, CAST(sum({LINE} - length(split_part(rule, '|', 2)) + k * (k - 1) - 1) AS BIGINT) AS bytes_matrix FROM (SELECT *, len(string_split(translate(split_part(rule, '|', 1), '>', ','), ',')) AS k FROM rated)"))
def output_bytes_by_layout(spark, d):
    """Bytes of the written rule files; a line holds the rule, '==>', two labelled measures and the relations."""
    rules = search.mine(T.quarter_spans(spark, d), minutil_ratio=0.01, minconf=0.1, max_size=4).rules
    tables, out = Tables(spark, "report"), None
    for layout in ("base7", "matrix"):
        report.write_rules(rules, f"{tables.root}/{layout}", layout)
        own = spark.read.text(f"{tables.root}/{layout}").agg(F.sum(F.octet_length("value") + 1).alias(f"bytes_{layout}"))
        out = own if out is None else out.crossJoin(own)  # one row each
    return out


# ---- baselines ----


def short(spark, d):
    return T.short_order_spans(spark, d)


@query("two_stage", O.mine("short_order_spans", 0.001, 0.02, 5))
def two_stage(spark, d):
    bar = search.resolve_threshold(model.clean(short(spark, d)).good, None, 0.001)
    return rule_rows(baselines.two_stage(short(spark, d), bar, 0.02, 5))


query("brute_force", O.mine("short_order_spans", None, 0.0, 4, minutil=0))(lambda spark, d: rule_rows(baselines.brute_force(short(spark, d), 4)))
for _style in ("levelwise", "growth"):
    query(f"frequent_rules_{_style}", O.frequent("short_order_spans", 5, 0.02, 5))(lambda spark, d, s=_style: rule_rows(baselines.frequent_rules(short(spark, d), 5, 0.02, 5, s)))


def pattern_rows(df: DataFrame, *cols: str) -> DataFrame:
    text = F.concat(F.array_join("x", ","), F.lit("|"), F.array_join(F.transform("rel", lambda v: v.cast("string")), ","))
    return df.select(text.alias("pattern"), *cols)


query("frequent_patterns", "SELECT pattern, support FROM (" + O.patterns("short_order_spans", 5, "count(*) >= 5") + ")")(lambda spark, d: pattern_rows(baselines.frequent_patterns(short(spark, d), 5, 5), "support"))


@query("profitable_patterns", O.patterns("items_by_type", 3, "sum(u) >= (SELECT ceil(0.01 * sum(u)) FROM log)"))
def profitable_patterns(spark, d):
    log = T.items_by_type(spark, d)
    return pattern_rows(baselines.profitable_patterns(log, search.resolve_threshold(log, None, 0.01), 3), "support", "utility")


query("point_rules", O.frequent("user_days", 20, 0.05, 3, points=True))(lambda spark, d: rule_rows(baselines.point_rules(T.user_days(spark, d), 20, 0.05, 3)))


@query("point_utility_rules", O.mine("user_days", 0.002, 0.05, 3, points=True))
def point_utility_rules(spark, d):
    log = T.user_days(spark, d)
    return rule_rows(baselines.point_utility_rules(log, search.resolve_threshold(baselines.as_points(log), None, 0.002), 0.05, 3))


# ---- use of rules ----

DAYS = {"minutil_ratio": 0.002, "minconf": 0.05, "max_size": 3}


def day_rules(spark, d):
    """Rules of user_days with codes and an id by their text."""
    log, codes = coded(spark, d, "user_days")
    rules = search.mine(T.user_days(spark, d), **DAYS).rules.withColumn("rule_id", report.key_text())
    each = rules.select("rule_id", F.size("x").alias("nx"), F.posexplode(F.concat("x", "y")).alias("at", "sym")).join(codes, "sym")
    w = each.groupBy("rule_id", "nx").agg(F.array_sort(F.collect_list(F.struct("at", "code")))["code"].alias("w"))
    w = w.select("rule_id", F.slice("w", F.lit(1), F.col("nx")).alias("x"), F.slice("w", F.col("nx") + 1, F.size("w")).alias("y"))
    return rules.drop("x", "y").join(w, "rule_id"), timelines.arrays(log, search.partitions(log))


OCC = O.on("user_days", "SELECT rule, CAST(count(*) AS BIGINT) AS occurrences, CAST(count(DISTINCT sid) AS BIGINT) AS timelines FROM occ WHERE rule IN (SELECT rule FROM rated WHERE utility >= (SELECT ceil(0.002 * sum(u)) FROM log) AND n_rule * 20 >= n_ante) GROUP BY rule", O.levels(3), O.rated(3))


@query("rule_occurrences", OCC)
def rule_occurrences(spark, d):
    rules, own = day_rules(spark, d)
    return match.occurrences(rules, own).groupBy(F.col("rule_id").alias("rule")).agg(F.count(F.lit(1)).alias("occurrences"), F.count_distinct("sid").alias("timelines"))


PREDICT = O.on(
    "user_days",
    "SELECT sid, rule, score, CAST(rank AS INT) AS rank FROM (SELECT h.sid, g.rule, g.score, row_number() OVER (PARTITION BY h.sid ORDER BY g.score DESC, g.rule) AS rank FROM (SELECT DISTINCT sid, ante FROM held) h JOIN good g USING (ante)) WHERE rank <= 3",
    O.levels(3),
    O.rated(3),
    "good AS (SELECT DISTINCT rated.rule, occ.ante, CAST(utility * 1000000 // n_ante AS BIGINT) AS score FROM rated JOIN (SELECT DISTINCT rule, ante FROM occ) occ USING (rule) WHERE utility >= (SELECT ceil(0.002 * sum(u)) FROM log) AND n_rule * 20 >= n_ante)",
    "held AS (SELECT sid, array_to_string(s, ',') || '|' || array_to_string(n, ',') AS ante FROM L1 UNION ALL SELECT sid, array_to_string(s, ',') || '|' || array_to_string(n, ',') FROM L2)",
)


@query("predict_next", PREDICT)
def predict_next(spark, d):
    rules, own = day_rules(spark, d)
    return match.predict(rules, own).filter("rank <= 3").select("sid", F.col("rule_id").alias("rule"), "score", "rank")


@query("target_rules", O.mine("items_by_type", 0.002, 0.03, 3, tail="AND list_contains(string_split(split_part(split_part(rule, '>', 2), '|', 1), ','), (SELECT min(sym) FROM log))"))
def target_rules(spark, d):
    log = T.items_by_type(spark, d)
    first = log.agg(F.min("sym")).first()[0]
    return rule_rows(match.target(search.mine(log, minutil_ratio=0.002, minconf=0.03, max_size=3).rules, [first]))


@query("rare_rules", O.mine("items_by_type", 0.002, 0.03, 3, tail="AND n_rule <= 150"))
def rare_rules(spark, d):
    return rule_rows(match.rare(search.mine(T.items_by_type(spark, d), minutil_ratio=0.002, minconf=0.03, max_size=3).rules, 150))


REDUNDANT = O.mine("short_order_spans", 0.001, 0.02, 4).replace("\nSELECT rule, n_rule, n_ante, utility FROM rated", ", good AS (SELECT rule, n_rule, n_ante, utility FROM rated") + "), parts AS (SELECT *, string_split(split_part(rule, '>', 1), ',') AS x, split_part(split_part(rule, '>', 2), '|', 1) AS y FROM good) SELECT rule, n_rule, n_ante, utility FROM parts a WHERE NOT EXISTS (SELECT 1 FROM parts b WHERE b.y = a.y AND len(b.x) < len(a.x) AND a.x[1:len(b.x)] = b.x AND b.utility >= a.utility AND b.n_rule * a.n_ante >= a.n_rule * b.n_ante)"


@query("non_redundant_rules", REDUNDANT)
def non_redundant_rules(spark, d):
    return rule_rows(match.non_redundant(search.mine(short(spark, d), minutil_ratio=0.001, minconf=0.02, max_size=4).rules))


# ---- generated data ----


@query("gaussian_utility_stats")
def gaussian_utility_stats(spark, d):
    rows = synth.gaussian_duration(T.user_weeks(spark, d), 10.0, 3.0, 42, unit=3_600_000_000)
    return rows.agg(F.count(F.lit(1)).alias("intervals"), F.sum("u").alias("utility"), F.min("u").alias("least"))


@query("synthetic_log_features")
def synthetic_log_features(spark, d):
    """A generated timeline for each customer of the table."""
    log = model.clean(synth.interval_log(spark, T.customers(spark, d), 200, 32)).good
    return log.agg(F.count_distinct("sid").alias("timelines"), F.count_distinct("sym").alias("symbols"), F.count(F.lit(1)).alias("intervals"), F.sum("u").alias("utility"))


@query("synthetic_top_k")
def synthetic_top_k(spark, d):
    return rule_rows(search.mine_top_k(synth.interval_log(spark, 300, 40, 12), 20, 0.05, max_size=3).rules)
