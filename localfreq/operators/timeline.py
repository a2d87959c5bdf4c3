"""Integer timelines: rank, day slots, buckets, given times."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.session import checkpointed, parts

__all__ = ["bucket_timeline", "column_timeline", "day_slot_timeline", "rank_timeline", "slot_day"]

_ROW = (1 << 33) - 1


def rank_timeline(df: DataFrame, order_by: list[str], *, start: int = 1, name: str = "t") -> DataFrame:
    """Adds each row's place in the order, without a task that sees all rows.

    Rows are dealt by ranges of the order and numbered within their partition by position; partition sizes
    (one number each) give the offsets. The dealt rows are checkpointed, so both passes see the same partitions.
    """
    spark = df.sparkSession
    dealt = checkpointed(df.repartitionByRange(parts(spark), *order_by).sortWithinPartitions(*order_by).withColumn("_place", F.monotonically_increasing_id()))
    pid = F.shiftright("_place", 33).cast("int")
    sizes = sorted((r["p"], r["n"]) for r in dealt.groupBy(pid.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect())  # a row a partition
    before, rows = start, []
    for p, n in sizes:
        rows.append((p, before))
        before += n
    offsets = spark.createDataFrame(rows or [(0, start)], "_pid int, _before long")
    joined = dealt.withColumn("_pid", pid).join(F.broadcast(offsets), "_pid")
    return joined.select(*df.columns, (F.col("_before") + F.col("_place").bitwiseAND(F.lit(_ROW))).alias(name))


def day_slot_timeline(df: DataFrame, day: str, tie: list[str], *, slots: int = 1000, name: str = "t", shared: bool = False) -> DataFrame:
    """day * slots + floor(place within the day * slots / rows of the day); fails if a day has more rows than slots, unless rows may share one."""
    by = Window.partitionBy(day)
    place = F.row_number().over(by.orderBy(*tie)) - 1
    counted = df.withColumn("_n", F.count(F.lit(1)).over(by)).withColumn("_place", place)
    slot = F.floor(F.col("_place") * F.lit(slots) / F.col("_n")).cast("long")
    if shared:
        return counted.withColumn(name, F.col(day).cast("long") * slots + slot).drop("_n", "_place")
    ok = F.assert_true(F.col("_n") <= slots, F.lit("a day has more rows than slots"))
    return counted.withColumn(name, F.coalesce(ok.cast("long"), F.lit(0)) + F.col(day).cast("long") * slots + slot).drop("_n", "_place")


def slot_day(t: Column, slots: int = 1000) -> Column:
    """The day of a slot time."""
    return F.floor(t / F.lit(slots)).cast("long")


def bucket_timeline(df: DataFrame, ts: str, width_seconds: int, *, name: str = "t") -> DataFrame:
    """Epoch seconds divided by the width; timestamps without a zone are read as UTC."""
    micros = F.unix_micros(F.col(ts).cast("timestamp"))
    return df.withColumn(name, F.floor(micros / F.lit(1_000_000 * width_seconds)).cast("long"))


def column_timeline(df: DataFrame, column: str, *, name: str = "t") -> DataFrame:
    """A given integer time; null or negative times are an error."""
    t = F.col(column).cast("long")
    ok = F.assert_true(t.isNotNull() & (t >= 0), F.lit("times must be integers of at least 0"))
    return df.withColumn(name, F.coalesce(ok.cast("long"), F.lit(0)) + t)
