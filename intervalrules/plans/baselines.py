"""Methods the search is compared with: two-stage, support-only, utility-only, point events, exhaustive enumeration."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import relations as R
from . import measures, model, search, timelines
from .scratch import Tables, partitioned_checkpoint

PATTERN = ["x", "rel"]


def _point(e):
    return F.struct(e["st"].alias("st"), e["ft"].alias("ft"))


def _candidates(live: DataFrame, size: int) -> DataFrame:
    """Level-wise join: two kept patterns of which one without its first interval is the other without its last, in every relation of the ends.

    Columns x, rel (the parent), next and rows: the symbol that may follow and the digits it may have. Relations are triangles here.
    """
    without_first = F.transform(F.slice("rel", 2, size), lambda row: F.slice(row, 2, size))
    left = live.select("x", "rel", F.slice("x", 2, size).alias("sx"), without_first.alias("sr"))
    right = live.select(F.slice("x", 1, size - 1).alias("sx"), F.slice("rel", 1, max(size - 2, 0)).alias("sr"), F.element_at("x", -1).alias("next"), F.element_at("rel", -1).alias("row"))
    joined = left.join(right, ["sx", "sr"])
    return joined.select("x", "rel", "next", F.explode(F.transform(F.sequence(F.lit(0), F.lit(6)), lambda d: F.concat(F.array(d), "row"))).alias("row"))


def pattern_levels(log: DataFrame, max_size: int | None, keep, style: str = "growth"):
    """Patterns of growing size with those of the level that `keep` (stats -> filter) holds.

    Yields (size, occurrences, statistics, dictionary); statistics: x, rel, support, utility, bound. The growth style extends every occurrence of a kept
    pattern; relations are base-7 numbers. The level-wise style joins kept patterns to candidates first, extends occurrences only by
    symbols that some candidate has, compares all pairs, and keeps a square (triangular) matrix with each occurrence.
    """
    if style not in ("growth", "levelwise"):
        raise ValueError(style)
    matrix = style == "levelwise"
    coded, codes, _, _ = search.stored(log)
    arrays = partitioned_checkpoint(timelines.arrays(coded, search.partitions(log)))
    tables = Tables(log.sparkSession, "patterns")
    e = F.col("e")
    rows = arrays.select("sid", F.explode("iv").alias("e"))
    occ = rows.select("sid", F.array(e["code"]).alias("x"), F.array().cast("array<array<int>>" if matrix else "array<bigint>").alias("rel"), F.array(_point(e)).alias("xi"), e["pos"].alias("last"), e["tail"].alias("tail"), e["u"].alias("u"), F.array(e["pos"]).alias("at"))
    size = 1
    while True:
        per = occ.groupBy("sid", *PATTERN).agg(F.max("u").alias("u"), F.max(F.col("u") + F.col("tail")).alias("bound"))
        stats = tables.put(f"stats-{size}", per.groupBy(*PATTERN).agg(F.count(F.lit(1)).alias("support"), F.sum("u").alias("utility"), F.sum("bound").alias("bound")))
        live = tables.put(f"live-{size}", keep(stats).select(*PATTERN))
        if matrix:
            plain = lambda df: df.withColumn("rel", R.matrix_numbers(F.col("rel")))
            yield size, plain(occ), plain(stats), codes
        else:
            yield size, occ, stats, codes
        n = live.count()
        if not n or (max_size is not None and size >= max_size):
            return
        digits = R.digits_against(F.col("xi"), e["st"], e["ft"])
        if matrix and size > 1:
            found = tables.put(f"candidates-{size}", _candidates(live, size))
            allowed = found.groupBy(*PATTERN).agg(F.collect_set("next").alias("allowed"))
            grown = occ.join(allowed, PATTERN).join(arrays, "sid").select(*occ.columns, F.explode(F.expr("filter(slice(iv, last + 1, size(iv)), e -> array_contains(allowed, e.code))")).alias("e"))
            grown = grown.withColumns({"next": e["code"], "row": digits}).join(found, [*PATTERN, "next", "row"], "left_semi")
        else:
            grown = occ.join(live, PATTERN).join(arrays, "sid").select(*occ.columns, F.explode(F.expr("slice(iv, last + 1, size(iv))")).alias("e"))
        if matrix:
            number = F.array(digits)
        elif size > R.LONG_DIGITS:
            number = R.limbs(digits)
        else:
            before = F.element_at("rel", -1) if size > 1 else F.lit(0)
            number = F.array(R.append_number(F.col("xi"), before, e["st"], e["ft"], size))
        new = grown.select("sid", F.concat("x", F.array(e["code"])).alias("x"), F.concat("rel", number).alias("rel"), F.concat("xi", F.array(_point(e))).alias("xi"), e["pos"].alias("last"), e["tail"].alias("tail"), (F.col("u") + e["u"]).alias("u"), F.concat("at", F.array(e["pos"])).alias("at"))
        occ = partitioned_checkpoint(new)
        size += 1


def _patterns(log: DataFrame, max_size: int | None, keep, style: str = "growth"):
    out = codes = None
    for _, _, stats, codes in pattern_levels(log, max_size, keep, style):
        own = keep(stats)
        out = own if out is None else out.unionByName(own)
    return out, codes


def frequent_patterns(log: DataFrame, minsup: int, max_size: int | None = None, style: str = "growth") -> DataFrame:
    """Interval patterns that at least minsup timelines hold: x, rel, support."""
    out, codes = _patterns(log, max_size, lambda s: s.filter(F.col("support") >= minsup), style)
    return model.named(out.select("x", "rel", "support"), codes, "x")


def profitable_patterns(log: DataFrame, minutil: int, max_size: int | None = None) -> DataFrame:
    """Interval patterns with utility >= minutil: x, rel, support, utility. Grown while utility plus the tail suffices."""
    found = codes = None
    for _, _, stats, codes in pattern_levels(log, max_size, lambda s: s.filter(F.col("bound") >= minutil)):
        own = stats.filter(F.col("utility") >= minutil)
        found = own if found is None else found.unionByName(own)
    return model.named(found.select("x", "rel", "support", "utility"), codes, "x")


def split_rules(log: DataFrame, max_size: int | None, keep, style: str = "growth") -> DataFrame:
    """Second stage: every kept pattern cut at every place where all of the antecedent starts earlier; x, y, rel, n_rule, n_ante, utility."""
    out = antes = codes = None
    for size, occ, stats, codes in pattern_levels(log, max_size, keep, style):
        ante = stats.select("x", F.col("rel").alias("xrel"), F.col("support").alias("n_ante"))
        antes = ante if antes is None else antes.unionByName(ante)
        if size == 1:
            continue
        cuts = occ.join(keep(stats).select(*PATTERN), PATTERN, "left_semi").select("sid", "x", "rel", "xi", "u", F.explode(F.sequence(F.lit(1), F.lit(size - 1))).alias("k"))
        cuts = cuts.filter(F.element_at("xi", F.col("k"))["st"] < F.element_at("xi", F.col("k") + 1)["st"])
        x, y = F.slice("x", 1, F.col("k")), F.slice("x", F.col("k") + 1, F.lit(size))
        cuts = cuts.select("sid", x.alias("x"), y.alias("y"), "rel", "u").filter(~F.arrays_overlap("x", "y"))
        per = cuts.groupBy("sid", "x", "y", "rel").agg(F.max("u").alias("u"))
        own = per.groupBy("x", "y", "rel").agg(F.count(F.lit(1)).alias("n_rule"), F.sum("u").alias("utility"))
        out = own if out is None else out.unionByName(own)
    if out is None:
        raise ValueError("rules have two intervals at least")
    out = out.withColumn("xrel", search.antecedent_of(F.col("rel"), F.col("x"))).join(antes, ["x", "xrel"])
    return model.named(out.select("x", "y", "rel", "n_rule", "n_ante", "utility"), codes, "x", "y")


def _good(rules: DataFrame, minutil: int, minconf: float) -> DataFrame:
    return rules.filter((F.col("utility") >= minutil) & measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), minconf))


def two_stage(log: DataFrame, minutil: int, minconf: float, max_size: int | None = None) -> DataFrame:
    """All patterns first, then rules from each: the same rules as the search, at the cost of every pattern."""
    return _good(split_rules(log, max_size, lambda s: s), minutil, minconf)


def brute_force(log: DataFrame, max_size: int | None = None) -> DataFrame:
    """Every rule of the log up to a size, unpruned."""
    return split_rules(log, max_size, lambda s: s)


def frequent_rules(log: DataFrame, minsup: int, minconf: float, max_size: int | None = None, style: str = "growth") -> DataFrame:
    """Rules by support and confidence, from frequent patterns grown level-wise with parent checks or by occurrence lists."""
    rules = split_rules(log, max_size, lambda s: s.filter(F.col("support") >= minsup), style)
    return rules.filter((F.col("n_rule") >= minsup) & measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), minconf))


def as_points(log: DataFrame) -> DataFrame:
    """Starts only: intervals of length one on a doubled clock, so that two starts are either before or equal."""
    return model.clean(log).good.groupBy("sid", "sym", "st").agg(F.sum("u").alias("u")).select("sid", "sym", (F.col("st") * 2).alias("st"), (F.col("st") * 2 + 1).alias("ft"), "u")


def point_rules(log: DataFrame, minsup: int, minconf: float, max_size: int | None = None) -> DataFrame:
    """Sequential rules of point events by support and confidence."""
    return frequent_rules(as_points(log), minsup, minconf, max_size)


def point_utility_rules(log: DataFrame, minutil: int, minconf: float, max_size: int | None = None) -> DataFrame:
    """Sequential rules of point events by utility and confidence, with the same bounds as the interval search."""
    return search.mine(as_points(log), minutil=minutil, minconf=minconf, max_size=max_size).rules

