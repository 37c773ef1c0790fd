"""Wall time, dollars and bytes of an analysis."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame

from corpus_audit.sources.io import drain

#: Fixed value: dollars an hour of the node that the published timings used.
DOLLARS_PER_HOUR = 9.46


def dollars(seconds: float, rate: float = DOLLARS_PER_HOUR) -> float:
    return round(seconds / 3600 * rate, 4)


def timed(name: str, make, *args) -> dict:
    """Run ``make(*args)`` to its end: query, seconds, dollars."""
    began = time.perf_counter()
    drain(make(*args))
    seconds = time.perf_counter() - began
    return {"query": name, "seconds": round(seconds, 3), "dollars": dollars(seconds)}


def plan_facts(df: DataFrame) -> dict:
    """Exchanges, nested loops and Python nodes of a physical plan, and whether filters reached the scan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: text.count(k) for k in ("Exchange", "NestedLoop", "CartesianProduct", "Python", "Arrow", "PushedFilters")}


def executor_memory(spark) -> list[dict]:
    """Storage and heap use of each executor, from the status store."""
    store = spark.sparkContext._jsc.sc().statusStore()
    return [{"id": e.id(), "memory_used": e.memoryUsed(), "max_memory": e.maxMemory()} for e in (store.executorList(False).apply(i) for i in range(store.executorList(False).size()))]
