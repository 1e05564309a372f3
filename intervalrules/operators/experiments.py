"""The experiments: sweeps of the threshold and of the number of timelines over logs and variants.

Each sweep is registered twice: with its exact columns (candidates, rules, bytes), which SQL reproduces from an unpruned enumeration, and
with its cost columns (milliseconds, memory, shuffle, spill), which differ from run to run.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import metrics, model, search
from ..plans.variants import VARIANTS
from ..sources import synth
from ..sources import tables as T
from . import oracles as O
from .rules import rule_rows

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


EXACT = "log string, minutil_ppm long, variant string, candidates long, rules long, bytes_base7 long, bytes_matrix long"
COST = "ms long, task_ms long, executor_heap_mb long, driver_python_mb long, peak_execution_mb long, shuffle_mb long, spill_mb long"


def sweep(spark: SparkSession, log: str, rows: DataFrame, ratios: Iterable[float], variants: Iterable[str], minconf: float, cap: int | None) -> DataFrame:
    """One row for each threshold and variant. The log is read, cleaned and coded once, before the runs and outside their costs."""
    out, coded = [], search.ready(rows)
    for ratio in ratios:
        for variant in variants:
            got = metrics.run(coded, minutil_ratio=ratio, minconf=minconf, max_size=cap, **VARIANTS[variant])
            exact = (log, round(ratio * 1_000_000), variant, got["candidates"], got["rules"], got["bytes_base7"], got["bytes_matrix"])
            out.append((*exact, round(got["seconds"] * 1000), *(round(got[c.split()[0]]) for c in COST.split(", ")[1:])))
    return spark.createDataFrame(out, f"{EXACT}, {COST}")


# log: thresholds, variants of the exact and of the cost sweep, minconf, cap of the search, cap of the enumeration
SWEEPS = {
    "short_order_spans": ((0.002, 0.01), ("full", "no_budget"), ("full", "matrix", "no_budget"), 0.05, None, 7),
    "items_by_type": ((0.002, 0.01), ("full", "no_budget"), ("full", "matrix", "no_budget"), 0.03, 4, 4),
    "items_by_brand": ((0.004, 0.007), ("full", "no_budget"), ("full", "no_budget"), 0.05, 4, 4),
    "quarter_spans": ((0.01, 0.02), ("full", "matrix"), ("full", "matrix"), 0.1, 4, 4),
    "user_weeks": ((0.04, 0.045, 0.05, 0.055, 0.06, 0.065, 0.07), ("full",), ("full", "matrix"), 0.25, 3, 3),
    "talk_turns": ((0.1, 0.2), ("full",), ("full", "matrix", "no_budget"), 0.6, None, 8),
}


def _costs(df: DataFrame) -> DataFrame:
    return df.select("log", "minutil_ppm", "variant", *[c.split()[0] for c in COST.split(", ")])


for _log, (_ratios, _exact, _timed, _conf, _cap, _all) in SWEEPS.items():
    _run = lambda spark, d, variants, n=_log, a=_ratios, c=_conf, m=_cap: sweep(spark, n, T.LOGS[n](spark, d), a, variants, c, m)
    query(f"sweep_{_log}", O.sweep(_log, _ratios, _exact, _conf, _all))(lambda spark, d, f=_run, v=_exact: f(spark, d, v).select(*[c.split()[0] for c in EXACT.split(", ")]))
    query(f"sweep_cost_{_log}")(lambda spark, d, f=_run, v=_timed: _costs(f(spark, d, v)))


@query("sweep_cost_synthetic")
def sweep_cost_synthetic(spark, d):
    """Generated log of many symbols and long timelines, one for each customer of the table."""
    return sweep(spark, "synthetic", synth.interval_log(spark, T.customers(spark, d), 200, 32), (0.002, 0.004), ("full", "matrix", "no_budget"), 0.02, 3)


def scalability(spark, sizes: Iterable[int], variants: Iterable[str], k: int = 200, n_symbols: int = 100, avg_len: int = 32, minconf: float = 0.05, cap: int | None = 3) -> DataFrame:
    """The k most useful rules of generated logs of growing size, each coded once, outside the costs."""
    out = []
    for n in sizes:
        log = search.ready(synth.interval_log(spark, n, n_symbols, avg_len))
        for variant in variants:
            got = metrics.run(log, k, minconf=minconf, max_size=cap, **VARIANTS[variant])
            out.append((n, variant, got["rules"], got["candidates"], got["minutil"], got["bytes_base7"], got["bytes_matrix"], round(got["seconds"] * 1000), *(round(got[c.split()[0]]) for c in COST.split(", ")[1:])))
    return spark.createDataFrame(out, f"timelines long, variant string, rules long, candidates long, minutil long, bytes_base7 long, bytes_matrix long, {COST}")


@query("scalability_top_k")
def scalability_top_k(spark, d):
    """Top 200 for two sizes that follow the customers table: half of its rows and all of them as numbers of timelines."""
    n = T.table(spark, d, "customer").count()
    return scalability(spark, (n // 2, n), ("full", "matrix", "no_budget"))


RENTAL = [(1, "A", 0, 5, 5), (1, "B", 1, 4, 3), (2, "A", 0, 50, 50), (2, "B", 5, 45, 40), (2, "D", 60, 160, 100)]
O.RAW["rental"] = "SELECT * FROM (VALUES " + ", ".join(map(str, RENTAL)) + ") t(sid, sym, st, ft, u)"


@query("rental_rules", O.mine("rental", None, 0.0, 3, minutil=90))
def rental_rules(spark, d):
    """Rentals with the same relation and different value."""
    return rule_rows(search.mine(spark.createDataFrame(RENTAL, model.LOG), minutil=90, minconf=0).rules)


@query("pruning_detail")
def pruning_detail(spark, d):
    """What each level evaluated and kept."""
    rows = []
    for variant in ("full", "no_budget"):
        got = search.mine(T.short_order_spans(spark, d), minutil_ratio=0.001, minconf=0.05, **VARIANTS[variant]).metrics
        rows += [(variant, level["size"], level["candidates"], level["occurrences"], level["left"], level["right"], level.get("classes", 0), level.get("classes_kept", 0)) for level in got.levels]
    return spark.createDataFrame(rows, "variant string, size int, candidates long, occurrences long, grow_left long, grow_right long, classes long, classes_kept long")


_FEW = ("short_order_spans", (0.002,), ("full", "no_budget"), 0.05)


@query("candidates_by_variant", f"SELECT variant, minutil_ppm, candidates, rules FROM ({O.sweep(*_FEW, 7)})")
def candidates_by_variant(spark, d):
    """Candidates with and without the class budget; the rules are the same."""
    log, ratios, variants, minconf = _FEW
    return sweep(spark, log, T.LOGS[log](spark, d), ratios, variants, minconf, None).select("variant", "minutil_ppm", "candidates", "rules")
