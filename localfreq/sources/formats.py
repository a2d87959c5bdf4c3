"""Text formats of transaction files, and result sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators.timeline import rank_timeline

__all__ = ["read_basket_lines", "read_timed_lines", "round_trip", "write_basket_lines", "write_intervals"]


def read_basket_lines(spark: SparkSession, path: str) -> DataFrame:
    """TRANSACTION from lines of blank-separated items; a line's place, by file and position, is its time. Lines starting with ``#``, ``%`` or ``@`` are comments."""
    lines = spark.read.text(path).select(F.col("_metadata.file_path").alias("f"), F.col("_metadata.file_block_start").alias("b"), F.monotonically_increasing_id().alias("i"), "value")
    kept = lines.where(~F.substring(F.trim("value"), 1, 1).isin("#", "%", "@"))
    return rank_timeline(kept, ["f", "b", "i"]).select("t", _items(F.col("value")).alias("items"))


def read_timed_lines(spark: SparkSession, path: str) -> DataFrame:
    """TRANSACTION from ``time|item item …`` lines; a time that is no integer of at least 0 is an error."""
    lines = spark.read.text(path).select(F.substring_index("value", "|", 1).alias("x"), F.expr("substring(value, instr(value, '|') + 1)").alias("rest"))
    t = F.expr("try_cast(trim(x) as bigint)")
    ok = F.assert_true(F.coalesce(t >= 0, F.lit(False)), F.lit("a line has no valid time"))
    return lines.select((F.coalesce(ok.cast("long"), F.lit(0)) + t).alias("t"), _items(F.col("rest")).alias("items"))


def _items(text):
    return F.array_sort(F.array_distinct(F.filter(F.split(text, r"\s+"), lambda x: x != "")))


def write_basket_lines(tx: DataFrame, path: str) -> None:
    tx.select(F.concat(F.col("t").cast("string"), F.lit("|"), F.array_join("items", " ")).alias("value")).write.mode("overwrite").text(path)


def write_intervals(res: DataFrame, path: str) -> None:
    """Results as Parquet by pattern length, sorted by pattern, so readers of one length or pattern skip the rest. Ranges of patterns, not lengths, are dealt to tasks."""
    res.repartitionByRange("len", "pattern", "s").sortWithinPartitions("len", "pattern", "s").write.mode("overwrite").partitionBy("len").parquet(path)


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """Write and read again in a file format, with the schema given where the format has none."""
    spark = df.sparkSession
    writer = df.write.mode("overwrite")
    if kind == "csv":
        writer.option("header", True).csv(path)
        return spark.read.schema(df.schema).option("header", True).csv(path)
    if kind == "json":
        writer.json(path)
        return spark.read.schema(df.schema).json(path)
    writer.format(kind).save(path)
    return spark.read.format(kind).load(path)
