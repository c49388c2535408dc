"""Wall-clock measures: builds, queries, phases, scaling."""

from __future__ import annotations

import time
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

SCHEMA = "run string, method string, dataset string, k int, metric string, value double"


class Clock:
    """Seconds by phase."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def phase(self, name: str):
        at = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - at

    def table(self, spark: SparkSession, run: str, method: str, dataset: str, k: int) -> DataFrame:
        return spark.createDataFrame([(run, method, dataset, k, f"{n}_s", float(s)) for n, s in self.seconds.items()], SCHEMA)


def force(df: DataFrame) -> None:
    """Run a plan wholly and throw its rows away."""
    df.write.format("noop").mode("overwrite").save()


def timed(f: Callable[[], DataFrame]) -> float:
    at = time.perf_counter()
    force(f())
    return time.perf_counter() - at


def qps(search: Callable[[], DataFrame], queries: int, warm: int = 1, runs: int = 2) -> float:
    """Queries a second of a batch search: the whole batch's wall time, after warm runs (a batch engine has no single-query time)."""
    for _ in range(warm):
        force(search())
    best = min(timed(search) for _ in range(runs))
    return queries / best


def speedup(original: float, fast: float) -> float:
    return original / max(fast, 1e-9)
