"""Level-by-level search for profitable rules.

A level is a table of occurrences of all live rules of one size, hash-partitioned by timeline for the whole run. Growing a rule joins
the level with the intervals on `sid` (a merge join without an exchange); only statistics of rules and of classes are shuffled. Each level takes two passes: the
first sums class bounds over all possible extensions without storing any, the second materialises the extensions of the surviving classes.

Where rules have a longest size and names that fit one LONG, the same levels are searched by packed.PackedSearch, which stores no occurrence.

Every rule has one derivation: one interval on each side, then the antecedent grows in timeline order, then the consequent; so no
duplicates arise. Rules and symbols are never collected; statistics live in Parquet tables of the shared folder.

Engines: "frontier" takes all live rules of a size at once; "subtrees" deals the one-to-one rules into batches and finishes the subtree of one batch
before the next, so that only one batch's levels are stored; "prefix" searches the rules of a first symbol in one task.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions import relations as R
from . import bounds, measures, model, timelines
from .scratch import Tables, partitioned_checkpoint, release

KEY = ["x", "y", "rel"]
RULES = "x array<int>, y array<int>, rel array<bigint>, n_rule bigint, n_ante bigint, utility bigint"


@dataclass
class Options:
    minutil: int
    minconf: float
    layout: str = "base7"  # or matrix: all pairs recomputed, relations kept as a triangle
    class_budget: bool = True
    zero_carry: bool = True
    occurrence: str = "max"
    disjoint: str = "symbol"
    max_x: int | None = None
    max_y: int | None = None
    max_size: int | None = None
    disable: frozenset = frozenset()  # of: symbols, open_bound, right_bound, confidence

    def __post_init__(self):
        allowed = {"layout": ("base7", "matrix"), "occurrence": ("max", "first"), "disjoint": ("symbol", "interval")}
        for name, values in allowed.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name}: {getattr(self, name)}")
        self.disable = frozenset(self.disable)
        if unknown := self.disable - {"symbols", "open_bound", "right_bound", "confidence"}:
            raise ValueError(f"disable: {sorted(unknown)}")


@dataclass
class Metrics:
    candidates: int = 0
    levels: list[dict] = field(default_factory=list)
    symbols: list[dict] = field(default_factory=list)
    seconds: float = 0.0
    minutil: int = 0


@dataclass
class MiningResult:
    rules: DataFrame  # x, y as strings, rel, rel_text, n_rule, n_ante, confidence, support, utility
    metrics: Metrics


def resolve_threshold(log: DataFrame, minutil: int | None, ratio: float | None) -> int:
    if (minutil is None) == (ratio is None):
        raise ValueError("give minutil or minutil_ratio")
    if minutil is not None:
        return minutil
    total = log.agg(F.coalesce(F.sum("u"), F.lit(0))).first()[0]
    return math.ceil(ratio * total)


def _bounded(df: DataFrame) -> DataFrame:
    """Adds left and right reserves, open and right bounds."""
    left = bounds.left_reserve(F.col("tail_x"), F.col("tail_tie"))
    right = bounds.right_reserve(F.col("tail_y"))
    return df.withColumns({"open": bounds.open_bound(F.col("u"), left, right), "right": bounds.right_bound(F.col("u"), right)})


def _renamed(items: DataFrame, prefix: str, *cols: str) -> DataFrame:
    return items.select("sid", *[F.col(c).alias(f"{prefix}{c}") for c in cols])


def _root_pairs(items: DataFrame, opt: Options) -> DataFrame:
    """Pairs of intervals that form a rule of one interval on each side, in plain columns: arrays are made only for those that grow."""
    a = _renamed(items, "a_", "pos", "code", "st", "ft", "u", "tail")
    b = _renamed(items, "b_", "pos", "code", "st", "ft", "u", "tail", "tie", "head")
    pairs = a.hint("merge").join(b, "sid").filter("b_pos > a_pos AND b_st > a_st" + (" AND a_code <> b_code" if opt.disjoint == "symbol" else ""))
    return pairs.withColumns({"d": R.digit(F.col("a_st"), F.col("a_ft"), F.col("b_st"), F.col("b_ft")).cast("bigint"), "u": F.col("a_u") + F.col("b_u"), "tail_x": F.col("a_tail"), "tail_tie": F.col("b_head"), "tail_y": F.col("b_tail")})


def roots(items: DataFrame, opt: Options, live: DataFrame | None = None) -> DataFrame:
    """Occurrences of all rules of one interval on each side, or of the rules in live (with live's other columns)."""
    pairs = _root_pairs(items, opt)
    more = [c for c in live.columns if c not in KEY] if live is not None else []
    if live is not None:
        wanted = live.select(F.element_at("x", 1).alias("a_code"), F.element_at("y", 1).alias("b_code"), F.element_at("rel", 1).alias("d"), *more)
        pairs = pairs.join(wanted, ["a_code", "b_code", "d"])
    point = lambda p: F.struct(F.col(f"{p}st").alias("st"), F.col(f"{p}ft").alias("ft"))
    out = pairs.select(
        "sid",
        F.array("a_code").alias("x"),
        F.array("b_code").alias("y"),
        F.array("d").alias("rel"),
        F.array(point("a_")).alias("xi"),
        F.array(point("b_")).alias("yi"),
        F.col("a_pos").alias("last_x"),
        F.col("b_tie").alias("tie_y"),
        F.col("b_pos").alias("last_y"),
        "tail_x",
        "tail_tie",
        "tail_y",
        "u",
        *([F.array("a_pos", "b_pos").alias("at")] if opt.occurrence == "first" else []),
        *more,
    )
    return _bounded(out)


def root_stats(items: DataFrame, opt: Options) -> DataFrame:
    """rule_stats(roots(items, opt), opt), grouped by plain columns."""
    keys = ["a_code", "b_code", "d"]
    value = F.max("u") if opt.occurrence == "max" else F.min(F.struct("a_pos", "b_pos", "u"))["u"]
    per = _bounded(_root_pairs(items, opt)).groupBy("sid", *keys).agg(value.alias("u"), F.max("open").alias("open"), F.max("right").alias("right"), F.count(F.lit(1)).alias("n"))
    rule = [F.array("a_code").alias("x"), F.array("b_code").alias("y"), F.array("d").alias("rel")]
    return _rule_sums(per, keys).select(*rule, "utility", "n_rule", "n_occ", "open_bound", "right_bound")


def extensions(occ: DataFrame, items: DataFrame, side: str, opt: Options) -> DataFrame:
    """Every interval (columns e_...) that may join `side` of an occurrence, with the bound of the grown rule."""
    rows = occ.hint("merge").join(_renamed(items, "e_", "pos", "code", "st", "ft", "u", "tail"), "sid")
    if side == "left":
        rows = rows.filter("e_pos > last_x AND e_pos < tie_y")
        if opt.disjoint == "symbol":
            rows = rows.filter(~F.array_contains("y", F.col("e_code")))
        prior = F.element_at("xi", -1)
        from_e = F.col("e_u") + bounds.left_reserve(F.col("e_tail"), F.col("tail_tie"))
        bound = bounds.open_bound(F.col("u"), from_e, bounds.right_reserve(F.col("tail_y")))
    else:
        rows = rows.filter("e_pos > last_y")
        if opt.disjoint == "symbol":
            rows = rows.filter(~F.array_contains("x", F.col("e_code")))
        prior = F.element_at("yi", -1)
        bound = bounds.right_bound(F.col("u"), F.col("e_u") + F.col("e_tail"))
    digit = R.digit(prior["st"], prior["ft"], F.col("e_st"), F.col("e_ft"))
    return rows.withColumns({"side": F.lit(side), "code": F.col("e_code"), "digit": digit, "bound": bound})


def materialise(rows: DataFrame, side: str, opt: Options, size: int) -> DataFrame:
    """The occurrences of the grown rules."""
    st, ft = F.col("e_st"), F.col("e_ft")
    point = F.array(F.struct(st.alias("st"), ft.alias("ft")))
    every = F.concat("xi", "yi") if side == "right" else F.col("xi")
    n = F.size("x")
    if opt.layout == "matrix" or size > R.LONG_DIGITS + 1:  # longer numbers take several limbs and are made anew
        xi = F.concat("xi", point) if side == "left" else F.col("xi")
        yi = F.col("yi") if side == "left" else F.concat("yi", point)
        rel = R.matrix_numbers(R.matrix(F.concat(xi, yi)))
    elif side == "right":
        rel = F.concat("rel", F.array(R.append_number(every, F.element_at("rel", -1), st, ft, size, opt.zero_carry)))
    else:
        before = F.when(n > 1, F.element_at("rel", F.when(n > 1, n - 1).otherwise(F.lit(1)))).otherwise(F.lit(0))
        own = R.append_number(F.col("xi"), before, st, ft, size, opt.zero_carry)
        y = F.element_at("yi", 1)
        grown = R.insert_digit(F.element_at("rel", -1), 0, R.digit(st, ft, y["st"], y["ft"]))
        rel = F.concat(F.slice("rel", 1, n - 1), F.array(own, grown))
    common = [rel.alias("rel"), (F.col("u") + F.col("e_u")).alias("u"), "sid", "tie_y", "tail_tie"]
    if side == "left":
        cols = [F.concat("x", F.array(F.col("e_code"))).alias("x"), "y", F.concat("xi", point).alias("xi"), "yi", F.col("e_pos").alias("last_x"), "last_y", F.col("e_tail").alias("tail_x"), "tail_y"]
        at = F.concat(F.slice("at", 1, n), F.array(F.col("e_pos")), F.slice("at", n + 1, F.size("at") - n)) if opt.occurrence == "first" else None
    else:
        cols = ["x", F.concat("y", F.array(F.col("e_code"))).alias("y"), "xi", F.concat("yi", point).alias("yi"), "last_x", F.col("e_pos").alias("last_y"), "tail_x", F.col("e_tail").alias("tail_y")]
        at = F.concat("at", F.array(F.col("e_pos"))) if opt.occurrence == "first" else None
    return _bounded(rows.select(*common, *cols, *([at.alias("at")] if at is not None else [])))


def rule_stats(occ: DataFrame, opt: Options) -> DataFrame:
    """Utility, number of timelines and bounds of each rule."""
    value = F.max("u") if opt.occurrence == "max" else F.min(F.struct("at", "u"))["u"]
    per = occ.groupBy("sid", *KEY).agg(value.alias("u"), F.max("open").alias("open"), F.max("right").alias("right"), F.count(F.lit(1)).alias("n"))
    return _rule_sums(per, KEY)


def _rule_sums(per: DataFrame, keys: list[str]) -> DataFrame:
    return per.groupBy(*keys).agg(F.sum("u").alias("utility"), F.count(F.lit(1)).alias("n_rule"), F.sum("n").alias("n_occ"), F.sum("open").alias("open_bound"), F.sum("right").alias("right_bound"))


def gates(stats: DataFrame, opt: Options, minutil: int, size: int) -> DataFrame:
    """Adds grow_left and grow_right."""
    nx, ny = F.size("x"), F.size("y")
    left = ny == 1
    if "open_bound" not in opt.disable:
        left = left & (F.col("open_bound") >= minutil)
    right = F.lit(True)
    if "right_bound" not in opt.disable:
        right = F.col("right_bound") >= minutil
    if "confidence" not in opt.disable:
        right = right & measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), opt.minconf)
    if opt.max_x is not None:
        left = left & (nx < opt.max_x)
    if opt.max_y is not None:
        right = right & (ny < opt.max_y)
    if opt.max_size is not None and size >= opt.max_size:
        left = right = F.lit(False)
    return stats.withColumns({"grow_left": left, "grow_right": right})


def singles(items: DataFrame) -> DataFrame:
    """Antecedent patterns of one interval."""
    return items.select("sid", F.array("code").alias("x"), F.array().cast("array<bigint>").alias("xrel"), F.array(F.struct("st", "ft")).alias("xi"), F.col("pos").alias("last_x"))


def grow_antecedents(ante: DataFrame, items: DataFrame, wanted: DataFrame, size: int, opt: Options) -> DataFrame:
    """Occurrences of the wanted patterns (x, xrel), one interval longer than those of ante, in all timelines."""
    rows = ante.hint("merge").join(_renamed(items, "e_", "pos", "code", "st", "ft"), "sid").filter("e_pos > last_x")
    if size > R.LONG_DIGITS + 1:
        number = R.limbs(R.digits_against(F.col("xi"), F.col("e_st"), F.col("e_ft")))
    else:
        before = F.when(F.size("xrel") > 0, F.element_at("xrel", F.when(F.size("xrel") > 0, F.lit(-1)).otherwise(F.lit(1)))).otherwise(F.lit(0)) if size > 2 else F.lit(0)
        number = F.array(R.append_number(F.col("xi"), before, F.col("e_st"), F.col("e_ft"), size, opt.zero_carry))
    point = F.struct(F.col("e_st").alias("st"), F.col("e_ft").alias("ft"))
    grown = rows.select("sid", F.concat("x", F.array("e_code")).alias("x"), F.concat("xrel", number).alias("xrel"), F.concat("xi", F.array(point)).alias("xi"), F.col("e_pos").alias("last_x"))
    return grown.join(wanted, ["x", "xrel"], "left_semi").select("sid", "x", "xrel", "xi", "last_x")


def antecedent_of(rel: Column, x: Column) -> Column:
    return F.slice(rel, 1, R.limbs_before(F.size(x)))


def _level() -> list[Column]:
    """Counts of gated statistics."""
    return [F.count(F.lit(1)).alias("candidates"), F.sum("n_occ").alias("occurrences"), F.count_if(F.col("grow_left")).alias("left"), F.count_if(F.col("grow_right")).alias("right")]


class Search:
    """State of one run; step() advances a level."""

    def __init__(self, items: DataFrame, opt: Options):
        """items: of timelines.items, written."""
        self.opt, self.spark, self.items = opt, items.sparkSession, items
        self.tables = Tables(self.spark, "rules")
        self.size, self.occ, self.root_items = 2, roots(items, opt), items
        self.ante = singles(items)
        self.held: dict[str, DataFrame] = {}  # checkpoints of this search that may still be read
        self.inherited: DataFrame | None = None
        self.metrics = Metrics(minutil=opt.minutil)
        self.found: list[DataFrame] = []

    def _with_antecedents(self, stats: DataFrame) -> DataFrame:
        """n_ante of each rule: counted for antecedents of this level, inherited from the last level by rules that grew right."""
        fresh = measures.antecedent_count(self.ante, ["x", "xrel"])
        if self.inherited is not None:
            fresh = fresh.unionByName(self.inherited)
        keyed = stats.withColumn("xrel", antecedent_of(F.col("rel"), F.col("x")))
        return keyed.join(fresh, ["x", "xrel"]).drop("xrel")

    def rated(self, gated: bool = False) -> DataFrame:
        """Statistics of this level's rules with their antecedent counts; with `gated` also what may grow, counted while they are written."""
        stats = self.tables.put(f"stats-{self.size}", root_stats(self.root_items, self.opt) if self.size == 2 else rule_stats(self.occ, self.opt))
        if self.size > 2:
            wanted = stats.filter(F.size("y") == 1).select("x", antecedent_of(F.col("rel"), F.col("x")).alias("xrel")).distinct()
            grown = grow_antecedents(self.ante, self.items, wanted, self.size, self.opt)
            self.ante = self._stored("ante", grown)
        full = self._with_antecedents(stats)
        if gated:
            self.seen = Observation()
            full = gates(full, self.opt, self.opt.minutil, self.size).observe(self.seen, *_level())
        out = self.tables.put(f"rated-{self.size}", full)
        self.inherited = out.select("x", antecedent_of(F.col("rel"), F.col("x")).alias("xrel"), "n_ante").distinct()
        return out

    def last(self) -> bool:
        """Whether no rule may be longer, so that a level's occurrences are read once and need not be stored."""
        return self.opt.max_size is not None and self.size >= self.opt.max_size

    def _stored(self, name: str, rows: DataFrame) -> DataFrame:
        """A level's rows, stored in place of those of the level before unless they are read once."""
        if self.last():
            return rows
        rows = partitioned_checkpoint(rows)
        if name in self.held:
            release(self.held[name])
        self.held[name] = rows
        return rows

    def only(self, kept: DataFrame) -> None:
        """Symbols (code) that may still join a rule."""
        self.items = partitioned_checkpoint(self.items.join(kept, "code", "left_semi"))
        self.held["items"] = self.items

    def end(self) -> None:
        """Removes the checkpoints; statistics stay."""
        for rows in self.held.values():
            release(rows)
        self.held = {}

    def step(self) -> bool:
        stats = self.rated(gated=True)
        return self.step_from(stats, self.seen.get)

    def step_from(self, stats: DataFrame, level: dict | None = None) -> bool:
        """Rules of this level; prepares the next one. False when nothing can grow. level: counts of gated statistics."""
        opt, minutil = self.opt, self.opt.minutil
        if level is None:
            stats = gates(stats, opt, minutil, self.size)
            level = stats.agg(*_level()).first().asDict()
        level = {k: v or 0 for k, v in level.items()}
        good = (F.col("utility") >= minutil) & measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), opt.minconf)
        self.found.append(stats.filter(good).select(*KEY, "n_rule", "n_ante", "utility"))
        self.metrics.candidates += level["candidates"]
        self.metrics.levels.append({"size": self.size} | level)
        if not level["left"] and not level["right"]:
            return False
        live = stats.select(*KEY, "grow_left", "grow_right").filter("grow_left OR grow_right")
        occ = roots(self.root_items, opt, live) if self.size == 2 else self.occ.join(live, KEY)  # statistics tables have known sizes, so the planner broadcasts them below its threshold only
        grown = {side: extensions(occ.filter(f"grow_{side}").drop("grow_left", "grow_right"), self.items, side, opt) for side in ("left", "right") if level[side]}
        both = None
        for rows in grown.values():
            part = rows.select("sid", *KEY, "side", "code", "digit", "bound")
            both = part if both is None else both.unionByName(part)
        seen, kept = Observation(), Observation()
        every = F.count(F.lit(1)).alias("n")
        if opt.class_budget:
            classes, by = bounds.class_budget(bounds.class_bound(both, KEY).observe(seen, every), KEY, minutil), [*KEY, "side", "code", "digit"]
        else:
            classes, by = bounds.symbol_budget(both, KEY).observe(seen, every).filter(F.col("bound") >= minutil), [*KEY, "side", "code"]
        classes = self.tables.put(f"classes-{self.size}", classes.select(*by).observe(kept, every))
        n = kept.get["n"]
        self.metrics.levels[-1] |= {"classes": seen.get["n"], "classes_kept": n}
        if not n:
            return False
        self.size += 1
        new = None
        for side, rows in grown.items():
            part = materialise(rows.join(classes, by, "left_semi"), side, opt, self.size)
            new = part if new is None else new.unionByName(part)
        self.occ = self._stored("occ", new)
        return True

    def rules(self) -> DataFrame:
        out = self.found[0]
        for more in self.found[1:]:
            out = out.unionByName(more)
        return out


def decode(rules: DataFrame, codes: DataFrame, n_timelines: int) -> DataFrame:
    """Symbols for codes, text for numbers, ratios."""
    return model.named(rules, codes, "x", "y").select(
        "x", "y", "rel", R.letters(F.col("rel"), F.size("x") + F.size("y")).alias("rel_text"), "n_rule", "n_ante",
        measures.confidence(F.col("n_rule"), F.col("n_ante")).alias("confidence"), measures.support(F.col("n_rule"), max(n_timelines, 1)).alias("support"), "utility",
    )


def packable(items: DataFrame, opt: Options):
    """A maker of packed.PackedSearch where rules have names of one LONG, or None."""
    from . import packed

    codes = items.agg(F.coalesce(F.max("code"), F.lit(0))).first()[0]
    if opt.occurrence != "max" or not packed.fits(codes, opt.max_size):
        return None
    return lambda rows, options: packed.PackedSearch(rows, options, codes)


def _whole(items: DataFrame, opt: Options, run):
    """run(maker of a search): by passes over packed timelines, or by stored levels if those are too wide."""
    from .packed import TooMany

    if make := packable(items, opt):
        try:
            return run(make)
        except TooMany:
            pass
    return run(Search)


def _frontier(items: DataFrame, opt: Options, make) -> tuple[DataFrame, Metrics]:
    search = make(items, opt)
    while search.step():
        pass
    search.end()
    return search.rules(), search.metrics


def _subtrees(items: DataFrame, opt: Options, batch_timelines: int, make=Search) -> tuple[DataFrame, Metrics]:
    """Rules and metrics, the subtrees of a batch of one-to-one rules at a time; a batch's rules occur about batch_timelines times together."""
    top = make(items, opt)
    stats = top.tables.put("gated", gates(top.rated(), opt, opt.minutil, top.size))
    grows = F.col("grow_left") | F.col("grow_right")
    total = stats.filter(grows).agg(F.coalesce(F.sum("n_rule"), F.lit(0))).first()[0]
    batches = max(1, -(-total // batch_timelines))
    # rules that cannot grow have no subtree: they are rated together
    alone = make(items, opt)
    alone.step_from(stats.filter(~grows).drop("grow_left", "grow_right"))
    rules, merged = alone.rules(), top.metrics
    merged.candidates, merged.levels = alone.metrics.candidates, alone.metrics.levels
    for b in range(batches):
        own = make(items, opt)
        own.ante, own.inherited = top.ante, top.inherited
        more = own.step_from(stats.filter(grows & (F.pmod(F.xxhash64(*KEY), F.lit(batches)) == b)).drop("grow_left", "grow_right"))
        while more:
            more = own.step()
        part = top.tables.put(f"rules-{b}", own.rules())
        rules = rules.unionByName(part)
        merged.candidates += own.metrics.candidates
        merged.levels += [{"batch": b} | level for level in own.metrics.levels]
        own.end()
        own.tables.drop("")
    return rules, merged


def prepare(log: DataFrame) -> tuple[DataFrame, DataFrame]:
    return model.encode_symbols(model.clean(log).good)


@dataclass
class Ready:
    """A coded log for several runs: `log` as of stored(), and the intervals that a run which drops no symbol uses as they are."""

    log: tuple[DataFrame, DataFrame, int, int]
    items: DataFrame
    own: DataFrame  # of bounds.symbol_utility


def ready(log: DataFrame) -> Ready:
    own = stored(log)
    return Ready(own, partitioned_checkpoint(timelines.items(own[0], partitions(log))), bounds.symbol_utility(own[0]))


def stored(log: DataFrame) -> tuple[DataFrame, DataFrame, int, int]:
    """The coded log and its dictionary, written once, with the number of timelines and the total utility."""
    tables = Tables(log.sparkSession, "log")
    good = tables.put("good", model.clean(log).good)
    coded, codes = model.encode_symbols(good)
    row = good.agg(F.count_distinct("sid").alias("n"), F.coalesce(F.sum("u"), F.lit(0)).alias("u")).first()
    return good.join(codes, "sym"), codes, row["n"], row["u"]


def partitions(log: DataFrame) -> int:
    return int(log.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def mine(
    log: DataFrame | Ready,
    minutil: int | None = None,
    minutil_ratio: float | None = None,
    minconf: float = 0.6,
    layout: str = "base7",
    class_budget: bool = True,
    occurrence: str = "max",
    disjoint: str = "symbol",
    max_x: int | None = None,
    max_y: int | None = None,
    max_size: int | None = None,
    zero_carry: bool = True,
    disable=frozenset(),
    engine: str = "frontier",
    batch_timelines: int = 50_000_000,
) -> MiningResult:
    """All rules with utility >= minutil and confidence >= minconf. batch_timelines: of the engine "subtrees"."""
    began = time.perf_counter()
    coded, codes, n_timelines, total = log.log if isinstance(log, Ready) else stored(log)
    if (minutil is None) == (minutil_ratio is None):
        raise ValueError("give minutil or minutil_ratio")
    minutil = math.ceil(minutil_ratio * total) if minutil is None else minutil
    opt = Options(minutil, minconf, layout, class_budget, zero_carry, occurrence, disjoint, max_x, max_y, max_size, frozenset(disable))
    trace: list[dict] = []
    if "symbols" not in opt.disable:
        coded, trace = bounds.prune_symbols(coded, minutil, log.own if isinstance(log, Ready) else None)
    if engine not in ("frontier", "subtrees", "prefix"):
        raise ValueError(engine)
    shared = isinstance(log, Ready) and len(trace) < 2  # no symbol was dropped
    items = None
    if engine != "prefix":
        items = log.items if shared else partitioned_checkpoint(timelines.items(coded, partitions(coded)))
    if engine == "prefix":
        from .prefix import mine_prefixes

        rules, metrics = mine_prefixes(coded, opt)
    elif engine == "subtrees":
        rules, metrics = _whole(items, opt, lambda make: _subtrees(items, opt, batch_timelines, make))
    else:
        rules, metrics = _whole(items, opt, lambda make: _frontier(items, opt, make))
    if items is not None and not shared:
        release(items)
    metrics.symbols, metrics.minutil = trace, minutil
    metrics.seconds = time.perf_counter() - began
    return MiningResult(decode(rules, codes, n_timelines), metrics)


def mine_top_k(log: DataFrame | Ready, k: int = 200, minconf: float = 0.6, **options) -> MiningResult:
    """The k most useful rules with confidence >= minconf; ties by confidence, then by the rule.

    The threshold is the k-th best confident utility seen so far, a lower bound of the final one, so nothing is lost.
    """
    began = time.perf_counter()
    shared = isinstance(log, Ready)
    coded, codes, n_timelines, _ = log.log if shared else stored(log)
    items = log.items if shared else partitioned_checkpoint(timelines.items(coded, partitions(coded)))
    weights = Tables(coded.sparkSession, "weights").put("weights", bounds.symbol_weight(log.own if shared else coded))
    # a run starts with options of its own, since its threshold rises
    best, metrics = _whole(items, Options(1, minconf, **options), lambda make: _best(make(items, Options(1, minconf, **options)), weights, k))
    if not shared:
        release(items)
    metrics.seconds = time.perf_counter() - began
    return MiningResult(decode(best, codes, n_timelines), metrics)


def _best(search: Search, weights: DataFrame, k: int) -> tuple[DataFrame, Metrics]:
    """The k best rules of a search, whose threshold it raises."""
    minconf = search.opt.minconf
    order = [F.desc("utility"), F.desc(F.col("n_rule") / F.col("n_ante")), "x", "y", "rel"]
    best = None
    while True:
        # the level's own rules may raise the threshold before its gates are set
        stats = search.rated()
        found = stats.filter(measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), minconf)).select(*KEY, "n_rule", "n_ante", "utility")
        best = search.tables.put(f"best-{search.size}", (found if best is None else best.unionByName(found)).orderBy(*order).limit(k))
        bar = best.agg(F.count(F.lit(1)).alias("n"), F.min("utility").alias("u")).first()
        if bar["n"] == k:
            if search.size == 2 and bar["u"] > search.opt.minutil:  # symbols that cannot reach the new threshold join no longer rule
                search.only(weights.filter(F.col("weight") >= bar["u"]).select("code"))
            search.opt.minutil = max(search.opt.minutil, bar["u"])
        if not search.step_from(stats):
            break
    search.end()
    search.metrics.minutil = search.opt.minutil
    return best, search.metrics
