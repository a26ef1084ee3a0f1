"""Costs: what a plan reads and shuffles, wall time, throughput, space and sharing."""

from __future__ import annotations

import re
import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def span(df: DataFrame) -> int:
    """Shuffles on the plan, the stage barriers of a run."""
    return len(re.findall(r"\bExchange\b(?! SinglePartition)", plan_text(df)))


def work(m) -> dict:
    """Rows and blocks of a map, the least that a scan of it touches."""
    t = m.block_table().agg(F.count("*").alias("blocks"), F.sum("n").alias("rows")).first()
    return {"blocks": t.blocks, "rows": t.rows or 0}


def blocks_touched(m, h) -> int:
    """Blocks that a summary filter has to open."""
    return m.block_table().filter(h(F.col("a"))).count()


def timed(fn: Callable[[], DataFrame], warm: int = 1, reps: int = 3) -> float:
    """Median seconds to compute all rows."""
    took = []
    for k in range(warm + reps):
        at = time.perf_counter()
        fn().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - at)
    return statistics.median(took[warm:])


def throughput(n: int, seconds: float) -> float:
    return n / max(seconds, 1e-9)


def speedup(one: float, many: float) -> float:
    return one / many


def overhead(with_: float, without: float) -> float:
    return with_ / without - 1


def space_overhead(summary_bytes: int, other_bytes: int) -> float:
    return summary_bytes / max(1, other_bytes)
