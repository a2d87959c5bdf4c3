"""Cost of the scan strategies and growth of time."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators.kernels import scan_by_pattern

__all__ = ["ablation", "growth", "pattern_counts", "peak_memory_mb", "range_reduction", "stage_costs", "timed"]


def ablation(occ: DataFrame, ranges: DataFrame, width: int, sigma: int, t_max: int) -> DataFrame:
    """(strategy, windows, runs): every position; every position of the ranges; stride-skip over the ranges."""
    out = None
    for name, kernel, limits in (("every", "every", None), ("every_ranges", "every", ranges), ("skip_ranges", "skip", ranges)):
        found = scan_by_pattern(occ, width, sigma, t_max=t_max, kernel=kernel, ranges=limits)
        row = found.agg(F.coalesce(F.sum("windows"), F.lit(0)).alias("windows"), F.count("s").alias("runs")).select(F.lit(name).alias("strategy"), "windows", "runs")
        out = row if out is None else out.unionByName(row)
    return out


def range_reduction(ranges: DataFrame, width: int, t_max: int) -> DataFrame:
    """(pattern, starts, share): window starts that the ranges leave, and their share of all starts."""
    starts = F.sum(F.col("e") - F.lit(width) - F.col("s") + 1)
    return ranges.groupBy("pattern").agg(starts.alias("starts"), F.round(starts / F.lit(t_max - width + 1), 6).alias("share"))


def pattern_counts(res: DataFrame) -> DataFrame:
    """(len, n_patterns, n_intervals)."""
    return res.groupBy("len").agg(F.countDistinct("pattern").alias("n_patterns"), F.count(F.lit(1)).alias("n_intervals"))


def timed(make: Callable[[], DataFrame], repeats: int = 3) -> float:
    """Mean seconds of running a plan into the ``noop`` sink, the first run dropped."""
    import time

    took = []
    for _ in range(repeats + 1):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - t)
    return sum(took[1:]) / max(1, len(took) - 1)


def growth(rows: DataFrame, x: str, y: str) -> DataFrame:
    """One row: least-squares slope, intercept and R squared of y over x."""
    return rows.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def peak_memory_mb(spark) -> dict[str, float]:
    """Largest resident memory so far of this Python process and of the driver's JVM, in MB (the whole engine in local mode)."""
    import os

    def high_water(pid: int) -> float:
        with open(f"/proc/{pid}/status") as f:
            return next(int(line.split()[1]) / 1024 for line in f if line.startswith("VmHWM"))

    jvm = spark.sparkContext._jvm.java.lang.ProcessHandle.current().pid()
    return {"python_mb": high_water(os.getpid()), "jvm_mb": high_water(int(jvm))}


#: The fields of Spark's event log that count here.
_EVENT = """Event string, `Stage ID` long, `Task Info` struct<`Launch Time`: long, `Finish Time`: long>, `Task Metrics` struct<`Executor Run Time`: long,
 `Memory Bytes Spilled`: long, `Disk Bytes Spilled`: long, `Shuffle Write Metrics`: struct<`Shuffle Bytes Written`: long>,
 `Shuffle Read Metrics`: struct<`Remote Bytes Read`: long, `Local Bytes Read`: long>>"""


def stage_costs(spark: SparkSession, log: str, *, since: int = 0, until: int | None = None) -> DataFrame:
    """(stage, tasks, written, read, spilled, seconds, median_s, longest_s, skew) of the tasks in an event log, by stage.

    ``log`` is a file or folder of Spark's uncompressed event logs; ``since`` and ``until`` limit the finish times (ms). Bytes are of shuffles
    and of spills to disk; skew is the longest task over the median one, null where that took no time. Tasks without metrics count with none.
    """
    done = F.col("Task Info")["Finish Time"]
    kept = (F.col("Event") == "SparkListenerTaskEnd") & (done >= since)
    if until is not None:
        kept &= done <= until
    m = F.col("Task Metrics")
    read = m["Shuffle Read Metrics"]["Remote Bytes Read"] + m["Shuffle Read Metrics"]["Local Bytes Read"]
    number = lambda c: F.coalesce(c, F.lit(0))
    tasks = spark.read.schema(_EVENT).json(log).where(kept).select(
        F.col("Stage ID").alias("stage"), number(m["Shuffle Write Metrics"]["Shuffle Bytes Written"]).alias("written"), number(read).alias("read"),
        number(m["Disk Bytes Spilled"]).alias("spilled"), (number(m["Executor Run Time"]) / 1000).alias("s"))
    total = tasks.groupBy("stage").agg(
        F.count(F.lit(1)).alias("tasks"), F.sum("written").alias("written"), F.sum("read").alias("read"), F.sum("spilled").alias("spilled"),
        F.round(F.sum("s"), 3).alias("seconds"), F.round(F.median("s"), 3).alias("median_s"), F.round(F.max("s"), 3).alias("longest_s"))
    return total.withColumn("skew", F.when(F.col("median_s") > 0, F.round(F.col("longest_s") / F.col("median_s"), 3)))
