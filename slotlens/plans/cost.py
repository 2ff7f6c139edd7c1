"""Cost measures: wall time, driver-side allocations, and bytes moved by Spark."""

from __future__ import annotations

import time
import tracemalloc
from collections.abc import Callable

from pyspark.sql import DataFrame


def measured(make: Callable[[], DataFrame]) -> dict[str, float]:
    """Runs a plan into a sink that keeps nothing: seconds to build and to run, peak MB of the driver's Python."""
    tracemalloc.start()
    try:
        t0 = time.monotonic()
        df = make()
        t1 = time.monotonic()
        df.write.format("noop").mode("overwrite").save()
        t2 = time.monotonic()
        peak = tracemalloc.get_traced_memory()[1] / 1e6
    finally:
        tracemalloc.stop()
    return {"build_s": t1 - t0, "run_s": t2 - t1, "driver_peak_mb": peak}


def plan_shape(df: DataFrame) -> dict[str, int]:
    """Counts of exchanges, joins and Python nodes in the physical plan, for tests that guard it."""
    text = df._jdf.queryExecution().executedPlan().toString()
    names = ("Exchange hashpartitioning", "Exchange SinglePartition", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "InPandas", "InArrow", "ArrowEvalPython")
    return {n: text.count(n) for n in names}


def kernel_memory(fn: Callable[[], object]) -> float:
    """Peak MB allocated by a plain Python kernel."""
    tracemalloc.start()
    try:
        fn()
        return tracemalloc.get_traced_memory()[1] / 1e6
    finally:
        tracemalloc.stop()
