"""Timing of stages: best of several runs, results thrown away by the noop sink."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def run(df: DataFrame) -> float:
    """Seconds to compute all of a frame."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def best_of(make: Callable[[], DataFrame], runs: int = 5, trials: int = 1) -> float:
    """Mean over trials of the best of `runs` runs; the published protocol has 5 and 10."""
    return sum(min(run(make()) for _ in range(runs)) for _ in range(trials)) / trials


def stages(fn_g: Callable[[], DataFrame], fn_h: Callable[[], DataFrame], fn_d: Callable[[], DataFrame], runs: int = 3) -> list[tuple[str, float]]:
    """Seconds of query tables, of encoding and of the scan, each from its own inputs."""
    return [(name, best_of(f, runs)) for name, f in (("tables", fn_g), ("encode", fn_h), ("scan", fn_d))]


def read_write(log: DataFrame) -> DataFrame:
    """(kind, ops, seconds): total cost of reads and of writes in a log (kind, op, seconds)."""
    return log.groupBy("kind").agg(F.count(F.lit(1)).alias("ops"), F.sum("seconds").alias("seconds"))


def speedup(table: DataFrame, base: str, by: str = "workload") -> DataFrame:
    """(workload, method, ratio): seconds of the base method over each method's, on one workload."""
    b = table.where(F.col("method") == base).select(by, F.col("seconds").alias("base"))
    return table.join(b, by).select(by, "method", (F.col("base") / F.col("seconds")).alias("ratio"))


def gb_per_second(rows: int, dims: int, seconds: float) -> float:
    """Single-precision bytes of vectors a second."""
    return rows * dims * 4 / seconds / 1e9
