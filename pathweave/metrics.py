"""What is measured about queries: time, limits, time-outs, and their spread over a set of patterns."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LIMIT, TIMEOUT_S = 100_000, 60.0


def timed(spark: SparkSession, make: Callable[[], DataFrame], timeout_s: float = TIMEOUT_S, limit: int | None = LIMIT, warmup: int = 0) -> dict:
    """wall_s, rows, timed_out of a query run to its first limit rows. Beyond the time its jobs (found by their tag) are cancelled."""
    for _ in range(warmup):
        timed(spark, make, timeout_s, limit)
    tag, gone = f"timed-{time.monotonic_ns()}", threading.Event()

    def stop() -> None:
        gone.set()
        spark.interruptTag(tag) if hasattr(spark, "interruptTag") else spark.sparkContext.cancelJobsWithTag(tag)

    timer = threading.Timer(timeout_s, stop)
    spark.addTag(tag)
    began = time.monotonic()
    timer.start()
    rows = None
    try:
        df = make()
        rows = (df if limit is None else df.limit(limit)).count()
    except Exception as e:
        # A search that looks at its own clock ends with PathTimeout, in a worker or here.
        if "PathTimeout" in f"{type(e).__name__} {e}":
            gone.set()
        if not gone.is_set():
            raise
    finally:
        timer.cancel()
        spark.removeTag(tag)
    return {"wall_s": time.monotonic() - began, "rows": rows, "timed_out": gone.is_set()}


def spread(spark: SparkSession, runs: Iterable[tuple[str, str, float, bool]]) -> DataFrame:
    """runs (mode, pattern, wall_s, timed_out) -> by mode: quartiles, mean, number and time-outs."""
    df = spark.createDataFrame(list(runs), "mode string, pattern string, wall_s double, timed_out boolean")
    q = F.percentile("wall_s", F.array(*[F.lit(x) for x in (0.0, 0.25, 0.5, 0.75, 1.0)]))
    return df.groupBy("mode").agg(F.count(F.lit(1)).alias("queries"), F.avg("wall_s").alias("mean_s"), q.alias("quartiles"), F.sum(F.col("timed_out").cast("long")).alias("timeouts"))


def delay(enumerated_cells: int, paths: DataFrame) -> float:
    """Elements written for each element delivered; constant for output-linear delay."""
    out = paths.agg(F.coalesce(F.sum(F.col("length") + 1), F.lit(0))).first()[0]
    return enumerated_cells / max(out, 1)
