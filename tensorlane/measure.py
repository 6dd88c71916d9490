"""Measures: time, cost, agreement of outputs, coverage and speed-up summaries."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sources import run_noop


def truncated_mean(values: list[float]) -> float:
    """Mean without the smallest and the largest, where there are more than two."""
    v = sorted(values)
    v = v[1:-1] if len(v) > 2 else v
    return sum(v) / len(v)


def timed(make: Callable[[], DataFrame], runs: int = 5) -> float:
    """Seconds to compute a DataFrame to no output: truncated mean over runs."""
    took = []
    for _ in range(runs):
        began = time.perf_counter()
        run_noop(make())
        took.append(time.perf_counter() - began)
    return truncated_mean(took)


def compile_time(make: Callable[[], object], runs: int = 5) -> float:
    took = []
    for _ in range(runs):
        began = time.perf_counter()
        make()
        took.append(time.perf_counter() - began)
    return truncated_mean(took)


def peak_memory_mb() -> float:
    """The most memory that this process has held, in MB."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024.0


def throughput(records: int, seconds: float) -> float:
    return records / seconds if seconds > 0 else float("inf")


def scaling(seconds: dict[int, float]) -> dict[int, float]:
    """Speed-up over the smallest number of cores, by number of cores."""
    first = seconds[min(seconds)]
    return {cores: first / s for cores, s in sorted(seconds.items())}


def model_size(dag) -> int:
    """Bytes of a pipeline as it is sent to the workers."""
    import pickle

    return len(pickle.dumps(dag))


def cost_per_prediction(rate_per_hour: float, seconds: float, records: int) -> float:
    return rate_per_hour / 3600.0 * seconds / records


def allclose(a: DataFrame, b: DataFrame, keys: list[str], columns: list[str], rtol: float = 1e-5, atol: float = 1e-5) -> DataFrame:
    """One row: rows of either side, mismatching rows, their share, and the largest absolute difference.

    Keys (null equals null) that stand on one side only are mismatches, and so are values missing on one side only.
    """
    left = a.select(*[F.col(k).alias(f"_ka{n}") for n, k in enumerate(keys)], *columns, F.lit(True).alias("_in_a"))
    other = b.select(*[F.col(k).alias(f"_kb{n}") for n, k in enumerate(keys)], *[F.col(c).alias(f"_{c}") for c in columns], F.lit(True).alias("_in_b"))
    same = F.lit(True)
    for n in range(len(keys)):
        same &= F.col(f"_ka{n}").eqNullSafe(F.col(f"_kb{n}"))
    pairs = left.join(other, same, "full")
    apart = [F.abs(F.col(c) - F.col(f"_{c}")) for c in columns]
    any_bad = F.col("_in_a").isNull() | F.col("_in_b").isNull()
    for d, c in zip(apart, columns, strict=True):
        close = d <= atol + rtol * F.abs(F.col(f"_{c}"))
        any_bad |= ~F.coalesce(close, F.col(c).isNull() & F.col(f"_{c}").isNull())
    worst = F.greatest(*apart) if len(apart) > 1 else apart[0]
    n = F.count("*")
    return pairs.agg(n.alias("rows"), F.sum(any_bad.cast("long")).alias("mismatches"), (F.sum(any_bad.cast("long")) / n).alias("share"), F.max(worst).alias("max_abs_diff"))


def speedup_summary(results: DataFrame) -> DataFrame:
    """From (pipeline, baseline, ours) seconds: how many, the share faster, least, median and greatest ratio."""
    ratio = F.col("baseline") / F.col("ours")
    return results.agg(F.count("*").alias("pipelines"), F.avg((ratio > 1).cast("double")).alias("faster"), F.min(ratio).alias("least"), F.percentile(ratio, 0.5).alias("median"), F.max(ratio).alias("greatest"))


def coverage(results: DataFrame) -> DataFrame:
    """From (pipeline, supported, failed): counts of each."""
    return results.agg(F.count("*").alias("pipelines"), F.sum(F.col("supported").cast("long")).alias("supported"), F.sum((F.col("supported") & F.col("failed")).cast("long")).alias("failed"), F.sum((F.col("supported") & ~F.col("failed")).cast("long")).alias("reported"))
