"""Start segments and runs: the declarative core of interval detection.

With occurrences t_1 < t_2 < ..., a window start l is dense exactly if some i has t_{i+sigma-1} - width <= l <= t_i.
The dense starts of a pattern are the union of these segments over i, and both ends of the segments grow with i, so one ordered pass merges
them. No position of the window is ever visited on its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

__all__ = ["dense_segments", "merge_monotone", "merge_runs"]


def dense_segments(occ: DataFrame, width: int, sigma: int, keys: list[str], *, last_start=None, discrete: bool = True) -> DataFrame:
    """(keys, a, b): segments of dense starts from occurrences. ``last_start`` caps them (a column or number), None leaves them open."""
    if sigma < 1 or width < 1:
        raise ValueError("width and sigma must be at least 1")
    far = F.lead("t", sigma - 1).over(Window.partitionBy(*keys).orderBy("t")) if sigma > 1 else F.col("t")
    near = occ.select(*keys, "t", far.alias("_far")).where(F.col("_far") - F.col("t") <= width)
    a = F.greatest(F.lit(0).cast("long"), F.col("_far") - width)
    b = F.col("t") if last_start is None else F.least(F.col("t"), last_start if not isinstance(last_start, int) else F.lit(last_start))
    return near.select(*keys, a.alias("a"), b.alias("b")).where("a <= b")


def merge_monotone(segments: DataFrame, keys: list[str], *, gap: int = 1) -> DataFrame:
    """(keys, s, d) from segments whose ends both grow along the order: a look back by one row finds the breaks."""
    by = Window.partitionBy(*keys).orderBy("a", "b")
    before = F.lag("b").over(by)
    marked = segments.withColumn("_new", F.when(before.isNull() | (F.col("a") > before + gap), 1).otherwise(0))
    runs = marked.withColumn("_run", F.sum("_new").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    return runs.groupBy(*keys, "_run").agg(F.min("a").alias("s"), F.max("b").alias("d")).drop("_run")


def merge_runs(runs: DataFrame, keys: list[str], *, gap: int = 1) -> DataFrame:
    """Joins (keys, s, d) runs of neighbouring shards that touch or overlap."""
    by = Window.partitionBy(*keys).orderBy("s", "d")
    before = F.max("d").over(by.rowsBetween(Window.unboundedPreceding, -1))
    marked = runs.withColumn("_new", F.when(before.isNull() | (F.col("s") > before + gap), 1).otherwise(0))
    numbered = marked.withColumn("_run", F.sum("_new").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(*keys, "_run").agg(F.min("s").alias("s"), F.max("d").alias("d")).drop("_run")
