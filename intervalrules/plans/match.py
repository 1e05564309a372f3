"""Where rules occur, what they predict, and which are worth keeping."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import relations as R
from .scratch import Tables, partitioned_checkpoint, small


def flat_intervals(arrays: DataFrame) -> DataFrame:
    return arrays.select("sid", F.explode("iv").alias("e")).select("sid", "e.*")


def pattern_occurrences(arrays: DataFrame, x: list[int], rel: list[int], split: int | None = None) -> DataFrame:
    """(sid, at) of one pattern; x: codes, rel: numbers from the second interval on. With `split` the interval at that place starts later than all before."""
    items = flat_intervals(arrays)
    out = None
    for k, code in enumerate(x):
        own = items.filter(F.col("code") == code).select("sid", *[F.col(c).alias(f"{c}{k}") for c in ("pos", "st", "ft", "u")])
        if out is None:
            out = own
            continue
        want = [rel[k - 1] // R.BASE ** (k - 1 - j) % R.BASE for j in range(k)]  # the digits of a number of any size
        same = reduce(lambda a, b: a & b, [R.digit(F.col(f"st{j}"), F.col(f"ft{j}"), F.col(f"st{k}"), F.col(f"ft{k}")) == want[j] for j in range(k)])
        out = out.join(own, "sid").filter((F.col(f"pos{k - 1}") < F.col(f"pos{k}")) & same)
        if split == k:
            out = out.filter(F.col(f"st{k - 1}") < F.col(f"st{k}"))
    n = len(x)
    return out.select("sid", F.array(*[f"pos{k}" for k in range(n)]).alias("at"), reduce(lambda a, b: a + b, [F.col(f"u{k}") for k in range(n)]).alias("u"))


def occurrences(rules: DataFrame, arrays: DataFrame, side: str = "rule") -> DataFrame:
    """(rule_id, sid, at, u) of many rules at once; side: rule or ante.

    rules: rule_id, x, y, rel with codes. Prefixes that rules share are grown once, timeline by timeline as in the search: a level stays partitioned by sid
    and is written before the next one; what is wanted of it is a table of prefixes, broadcast only where its counted size allows it.
    """
    tables = Tables(rules.sparkSession, "matches")
    nx = F.size("x")
    ante = side == "ante"
    want = tables.put("rules", rules.select("rule_id", (F.col("x") if ante else F.concat("x", "y")).alias("w"), (F.slice("rel", 1, R.limbs_before(nx)) if ante else F.col("rel")).alias("wrel"), nx.alias("nx")))
    longest = want.agg(F.coalesce(F.max(F.size("w")), F.lit(0))).first()[0]
    arrays = partitioned_checkpoint(arrays)
    e, level, done = F.col("e"), None, None
    point = F.struct(e["st"].alias("st"), e["ft"].alias("ft"))
    for k in range(1, longest + 1):
        prefixes = tables.put(f"prefixes-{k}", want.filter(F.size("w") >= k).select(F.slice("w", 1, k).alias("x"), F.slice("wrel", 1, R.limbs_before(F.lit(k))).alias("xrel")).distinct())
        if level is None:
            rows = arrays.select("sid", F.explode("iv").alias("e"))
            rows = rows.select("sid", F.array(e["code"]).alias("x"), F.array().cast("array<bigint>").alias("xrel"), F.array(point).alias("xi"), F.array(e["pos"]).alias("at"), e["u"].alias("u"))
        else:
            rows = level.join(arrays, "sid").select(*level.columns, F.explode(F.expr("slice(iv, at[size(at) - 1] + 1, size(iv))")).alias("e"))
            number = R.limbs(R.digits_against(F.col("xi"), e["st"], e["ft"]))
            rows = rows.select("sid", F.concat("x", F.array(e["code"])).alias("x"), F.concat("xrel", number).alias("xrel"), F.concat("xi", F.array(point)).alias("xi"), F.concat("at", F.array(e["pos"])).alias("at"), (F.col("u") + e["u"]).alias("u"))
        level = partitioned_checkpoint(rows.join(small(prefixes, prefixes.count()), ["x", "xrel"], "left_semi").select("sid", "x", "xrel", "xi", "at", "u"))
        own = want.filter(F.size("w") == k).withColumnsRenamed({"w": "x", "wrel": "xrel"})
        hit = level.join(small(own, own.count()), ["x", "xrel"])
        if not ante and k > 1:
            hit = hit.filter(F.element_at("xi", F.col("nx"))["st"] < F.element_at("xi", F.col("nx") + 1)["st"])
        hit = hit.select("rule_id", "sid", "at", "u")
        done = hit if done is None else done.unionByName(hit)
    if done is None:
        return rules.select("rule_id", F.lit(0).cast("long").alias("sid"), F.array().cast("array<int>").alias("at"), F.lit(0).cast("long").alias("u")).limit(0)
    return done


def predict(rules: DataFrame, arrays: DataFrame) -> DataFrame:
    """(sid, rule_id, score, rank): rules whose antecedent a timeline holds, by confidence times the mean utility of the rule."""
    held = occurrences(rules, arrays, "ante").select("rule_id", "sid").distinct()
    # whole numbers: millionths of confidence times mean utility
    score = F.expr("CAST(utility * 1000000 DIV n_ante AS BIGINT)")
    from pyspark.sql import Window

    order = Window.partitionBy("sid").orderBy(F.desc("score"), "rule_id")
    return held.join(rules.select("rule_id", "n_ante", "utility"), "rule_id").withColumn("score", score).withColumn("rank", F.row_number().over(order)).select("sid", "rule_id", "score", "rank")


def target(rules: DataFrame, symbols: list[str]) -> DataFrame:
    """Rules whose consequent holds one of the symbols."""
    return rules.filter(F.arrays_overlap("y", F.array(*map(F.lit, symbols))))


def rare(rules: DataFrame, most: int) -> DataFrame:
    return rules.filter(F.col("n_rule") <= most)


def non_redundant(rules: DataFrame) -> DataFrame:
    """Drops a rule if another with the same consequent symbols, a shorter antecedent among its prefixes, earns and holds at least as much."""
    cut = rules.filter(F.size("x") > 1)
    short = rules.select(F.col("x").alias("sx"), F.col("y").alias("sy"), F.col("utility").alias("su"), F.col("n_rule").alias("sn"), F.col("n_ante").alias("sa"))
    prefixes = cut.withColumn("k", F.explode(F.sequence(F.lit(1), F.size("x") - 1))).withColumn("sx", F.slice("x", 1, F.col("k"))).withColumn("sy", F.col("y"))
    worse = prefixes.join(short, ["sx", "sy"]).filter("su >= utility AND sn * n_ante >= n_rule * sa").select("x", "y", "rel").distinct()
    return rules.join(worse, ["x", "y", "rel"], "left_anti")
