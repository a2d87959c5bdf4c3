"""Interval algebra. Overlaps are found by one sweep over end points, or by bucketed equi-joins; never by a theta join."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

__all__ = ["count_overlaps", "coverage", "covers", "intersect_intervals", "merge_intervals", "overlap_length", "overlap_table", "subtract_intervals", "sweep"]


def merge_intervals(df: DataFrame, keys: list[str], *, gap: int = 0) -> DataFrame:
    """Union coverage: overlapping and touching intervals joined; for any intervals, so the look back is a running maximum."""
    by = Window.partitionBy(*keys).orderBy("s", "e")
    before = F.max("e").over(by.rowsBetween(Window.unboundedPreceding, -1))
    marked = df.select(*keys, "s", "e").withColumn("_new", F.when(before.isNull() | (F.col("s") > before + gap), 1).otherwise(0))
    numbered = marked.withColumn("_run", F.sum("_new").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(*keys, "_run").agg(F.min("s").alias("s"), F.max("e").alias("e")).drop("_run")


def sweep(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, s, e, in_a, in_b): the pieces between end points, with how many intervals of each side cover them.

    Per side each interval adds one at its start and takes one away at its end; changes at one place are summed before the
    exchange, so a hot key costs one row per place.
    """
    def ends(df: DataFrame, da: int, db: int) -> DataFrame:
        points = F.explode(F.array(F.struct(F.col("s").alias("x"), F.lit(da).alias("da"), F.lit(db).alias("db")), F.struct(F.col("e").alias("x"), F.lit(-da).alias("da"), F.lit(-db).alias("db"))))
        return df.select(*keys, points.alias("p")).select(*keys, "p.x", "p.da", "p.db")

    moves = ends(a, 1, 0).unionByName(ends(b, 0, 1)).groupBy(*keys, "x").agg(F.sum("da").alias("da"), F.sum("db").alias("db"))
    by = Window.partitionBy(*keys).orderBy("x")
    upto = by.rowsBetween(Window.unboundedPreceding, 0)
    return moves.select(*keys, F.col("x").alias("s"), F.lead("x").over(by).alias("e"), F.sum("da").over(upto).alias("in_a"), F.sum("db").over(upto).alias("in_b")).where("e is not null")


def intersect_intervals(a: DataFrame, b: DataFrame, keys: list[str], *, min_len: int = 0) -> DataFrame:
    """Common parts per key, joined where they touch, of at least ``min_len``."""
    both = sweep(a, b, keys).where("in_a > 0 and in_b > 0").select(*keys, "s", "e")
    return merge_intervals(both, keys).where(F.col("e") - F.col("s") >= min_len)


def subtract_intervals(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """The parts of a that b does not cover."""
    only = sweep(a, b, keys).where("in_a > 0 and in_b = 0").select(*keys, "s", "e")
    return merge_intervals(only, keys)


def coverage(df: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, covered): length of the union."""
    return merge_intervals(df, keys).groupBy(*keys).agg(F.sum(F.col("e") - F.col("s")).alias("covered"))


def overlap_table(a: DataFrame, b: DataFrame, keys: list[str], *, measure: str = "length") -> DataFrame:
    """(keys, len_a, len_b, inter, uni) in one sweep. ``points`` counts integer points of closed intervals instead of lengths."""
    if measure == "points":
        a, b = (df.withColumn("e", F.col("e") + 1) for df in (a, b))
    d = F.col("e") - F.col("s")
    total = lambda c: F.coalesce(F.sum(F.when(F.expr(c), d)), F.lit(0)).cast("long")
    return sweep(a, b, keys).groupBy(*keys).agg(total("in_a > 0").alias("len_a"), total("in_b > 0").alias("len_b"), total("in_a > 0 and in_b > 0").alias("inter"), total("in_a > 0 or in_b > 0").alias("uni"))


def overlap_length(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, overlap) of the two unions; keys without overlap have 0."""
    return overlap_table(a, b, keys).select(*keys, F.col("inter").alias("overlap"))


def covers(points: DataFrame, intervals: DataFrame, keys: list[str], t: str = "t") -> DataFrame:
    """The points that lie in some interval of their key (ends included).

    An as-of look-up: interval ends, made monotone by a running maximum, and points go through one ordered pass, so the cost does not grow with overlaps.
    """
    tops = intervals.select(*keys, F.col("s").alias("_x"), F.lit(0).alias("_kind"), F.col("e").alias("_e"))
    marked = points.withColumn("_x", F.col(t)).withColumn("_kind", F.lit(1)).withColumn("_e", F.lit(None).cast("long"))
    rows = marked.unionByName(tops, allowMissingColumns=True)
    by = Window.partitionBy(*keys).orderBy("_x", "_kind").rowsBetween(Window.unboundedPreceding, 0)
    reached = rows.withColumn("_top", F.max("_e").over(by))
    return reached.where((F.col("_kind") == 1) & (F.col("_top") >= F.col("_x"))).select(*points.columns)


def count_overlaps(a: DataFrame, b: DataFrame, keys: list[str], *, b_id: str, bucket: int) -> DataFrame:
    """(keys, s, e, n): how many different ``b_id`` meet each interval of a in more than a point; time buckets make it an equi-join."""
    place = lambda c: F.floor(c / F.lit(bucket)).cast("long")
    left = a.select(*keys, "s", "e").distinct()
    spread = left.withColumn("_b", F.explode(F.sequence(place(F.col("s")), place(F.col("e")))))
    other = b.select(*keys, F.col("s").alias("_s"), F.col("e").alias("_e"), F.col(b_id).alias("_id"))
    other = other.withColumn("_b", F.explode(F.sequence(place(F.col("_s")), place(F.col("_e")))))
    met = spread.join(other, [*keys, "_b"]).where((F.col("_s") < F.col("e")) & (F.col("s") < F.col("_e")))
    counts = met.groupBy(*keys, "s", "e").agg(F.countDistinct("_id").alias("n"))
    return left.join(counts, [*keys, "s", "e"], "left").select(*keys, "s", "e", F.coalesce("n", F.lit(0)).alias("n"))
