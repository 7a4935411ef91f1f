"""Cost and accuracy measures."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(fn: Callable):
    """(result, seconds) of an action: what-if time and transpile time."""
    began = time.perf_counter()
    out = fn()
    return out, time.perf_counter() - began


def speed_up(baseline_s: float, engine_s: float) -> float:
    return baseline_s / engine_s if engine_s else float("inf")


def peak_memory_mb() -> float:
    """Peak resident memory of this process; executors report theirs in their own metrics."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


def round_trips(calls: DataFrame, per_call: dict[str, float]) -> DataFrame:
    """(fn, n_calls, b_trips, t_trips): round trips of statement-wise and of transpiled execution."""
    cost = F.lit(None).cast("double")
    for fn, n in per_call.items():
        cost = F.when(F.col("fn") == fn, F.lit(float(n))).otherwise(cost)
    return calls.groupBy("fn").agg(F.count("*").alias("n_calls"), F.sum(cost).cast("long").alias("b_trips"), F.count("*").alias("t_trips"))


def log_bytes(statement_log: DataFrame, dependency_log: DataFrame, statement: str, dependency: str) -> DataFrame:
    """(statement_bytes, dependency_bytes) of a query on average."""
    a = statement_log.agg(F.avg(F.octet_length(statement)).alias("statement_bytes"))
    b = dependency_log.groupBy("idx").agg(F.sum(F.octet_length(dependency)).alias("n")).agg(F.avg("n").alias("dependency_bytes"))
    return a.crossJoin(b)


def overhead_percent(plain_s: float, logged_s: float) -> float:
    """Logging overhead, overhead of hashes without a match, or slowdown beside a running what-if."""
    return 100 * (logged_s / plain_s - 1)


def dependency_ratio(affected: int, total: int, after: int) -> tuple[float, float]:
    """Affected statements as a share of the history, and of the part after the target: the published rate does not say which."""
    return affected / total if total else 0.0, affected / after if after else 0.0


def hit_ratio(match_idx: int | None, total: int) -> float | None:
    return None if match_idx is None else match_idx / total


def parallelism(waves: DataFrame) -> DataFrame:
    """(statements, waves, widest, mean_width) of a wave plan."""
    width = waves.groupBy("wave").agg(F.count("*").alias("n"))
    return width.agg(F.sum("n").alias("statements"), F.count("*").alias("waves"), F.max("n").alias("widest"), F.avg("n").alias("mean_width"))


def precision(changed: int, affected: int) -> float:
    """Truly changed statements among those that the analysis replays."""
    return changed / affected if affected else 1.0


def same_state(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def executor_peak_mb(spark) -> float:
    """Largest JVM heap in use among executors, as Spark's status reports it."""
    status = spark.sparkContext._jsc.sc().getExecutorMemoryStatus()
    it, most = status.iterator(), 0.0
    while it.hasNext():
        pair = it.next()._2()
        most = max(most, (pair._1() - pair._2()) / 1e6)
    return most
