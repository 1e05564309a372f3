"""Cost measures of a run: time, memory, shuffle and spill, from the clock and Spark's status store."""

from __future__ import annotations

import resource
import time

from pyspark.sql import DataFrame, SparkSession


class Meter:
    """With-block that measures what runs inside: `seconds` and, in `cost`, MB and task milliseconds."""

    def __init__(self, spark: SparkSession):
        self.context = spark.sparkContext._jsc.sc()
        self.jvm = spark.sparkContext._jvm
        self.seconds, self.cost = 0.0, {}

    def _next_stage(self) -> int:
        return self.context.dagScheduler().nextStageId()

    def __enter__(self) -> "Meter":
        self.first, self.began = self._next_stage(), time.perf_counter()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.perf_counter() - self.began
        self.context.listenerBus().waitUntilEmpty(30_000)
        store, total = self.context.statusStore(), {"task_ms": 0, "shuffle_mb": 0.0, "spill_mb": 0.0, "peak_execution_mb": 0.0}
        for stage in range(self.first, self._next_stage()):
            try:
                data = store.lastStageAttempt(stage)
            except Exception:  # a stage that was never submitted, its output being there already
                continue
            total["task_ms"] += data.executorRunTime()
            total["shuffle_mb"] += data.shuffleWriteBytes() / 1e6
            total["spill_mb"] += data.diskBytesSpilled() / 1e6
            total["peak_execution_mb"] = max(total["peak_execution_mb"], data.peakExecutionMemory() / 1e6)
        self.cost = total | {"executor_heap_mb": self._executor_heap(store), "driver_python_mb": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024}

    def _executor_heap(self, store) -> float:
        """Highest JVM heap of any executor since the application began."""
        best, each = 0, store.executorList(False).iterator()
        while each.hasNext():
            found = each.next().peakMemoryMetrics()
            if found.isDefined():
                best = max(best, found.get().getMetricValue("JVMHeapMemory"))
        return best / 1e6


def run(log, top_k: int | None = None, **options) -> dict:
    """Runtime, candidates, rules, output bytes of both layouts, memory, shuffle and spill of one mining run (top_k: of one top-k run).

    log: a log, or search.ready(log), whose coding is then no part of the run. What the run stores is removed.
    """
    from . import report, search
    from .scratch import Tables, temporary

    spark = (log.items if isinstance(log, search.Ready) else log).sparkSession
    with temporary(spark):
        with Meter(spark) as meter:
            result = search.mine_top_k(log, top_k, **options) if top_k else search.mine(log, **options)
            rules = Tables(spark, "run").put("rules", result.rules)
            n = rules.count()
        out = {"seconds": meter.seconds, "candidates": result.metrics.candidates, "rules": n, "minutil": result.metrics.minutil, "levels": result.metrics.levels, "symbols": result.metrics.symbols}
        out |= report.output_sizes(rules, ("base7", "matrix")) | meter.cost
        del result, rules  # with their plans
    return out
