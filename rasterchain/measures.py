"""Cost measures: counted, derived from published formulas, or timed."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

METHODS = ("direct", "proposed", "queue", "library", "gpu")


def timed(fn: Callable[[], object], reps: int = 3) -> float:
    """Milliseconds of the best of some runs."""
    best = float("inf")
    for _ in range(reps):
        t = time.perf_counter()
        fn()
        best = min(best, time.perf_counter() - t)
    return 1000 * best


def run_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def speedup(other_ms: float, ours_ms: float) -> float:
    return other_ms / ours_ms


def mean_speedup(pairs: list[tuple[float, float]]) -> float:
    return sum(a / b for a, b in pairs) / len(pairs)


def throughput(n_filters: int, workers: int, width: int, height: int, ms: float) -> float:
    """Pipeline throughput in millions (2 to the 20) of pixels a second."""
    return n_filters / workers * width * height / (1 << 20) / (ms / 1000)


def fps(ms: float) -> float:
    return 1000 / ms


def comparisons(method: str, s: int = 1) -> int:
    """Pairwise comparisons a pixel of an erosion of size s; the queue's figure is amortised, and the same for every s."""
    return {"direct": (2 * s + 1) ** 2 - 1, "proposed": 4 * s, "queue": 6, "library": 4 * s, "gpu": 4 * s}[method]


def memory(method: str, width: int, height: int, workers: int) -> int:
    """Values of working memory."""
    return {"direct": width * height, "proposed": 2 * width * workers, "queue": (3 * width + 3) * workers, "library": width * height, "gpu": width * height}[method]


def passes(n_filters: int, workers: int) -> int:
    """Also of columns."""
    if isinstance(n_filters, Column):
        return F.ceil(n_filters / workers).cast("int")
    return -(-n_filters // workers)


def sync_ops(n_filters: int, height: int) -> int:
    return n_filters * height


def break_even(queue_ms: float, chain_ms: float) -> int:
    """Largest size s at which a chain of s filters still beats one filter by queues."""
    return int(queue_ms / chain_ms)


def scaling(one_ms: float, many_ms: float) -> float:
    return one_ms / many_ms


def asf_length(s: int) -> int:
    return 2 * s * (s + 1)


def spectrum_length(s: int) -> int:
    """Filters of openings of all sizes up to s with shared erosions."""
    return s + s * (s + 1) // 2


def mismatches(a: DataFrame, b: DataFrame) -> DataFrame:
    """(n_bad): pixels that one side lacks or that differ; 0 for equal rasters."""
    left, right = a.select("img", "y", "x", F.col("v").alias("va")), b.select("img", "y", "x", F.col("v").alias("vb"))
    bad = ~F.col("va").eqNullSafe(F.col("vb"))
    return left.join(right, ["img", "y", "x"], "full_outer").agg(F.coalesce(F.sum(bad.cast("bigint")), F.lit(0)).alias("n_bad"))
