"""Streams of events: windows, sessions, deduplication and joins, each run to completion over what there is."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.session import shared_folder

__all__ = ["deduplicated", "event_stream", "run_to_table", "sessions", "sliding", "tumbling"]

_EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, *, watermark: str | None = "1 hour", files_per_batch: int = 1) -> DataFrame:
    """The events table as a file stream; times become UTC timestamps, which watermarks need."""
    rows = spark.readStream.schema(_EVENTS).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/[e]vents.parquet")
    rows = rows.withColumn("ts", F.col("ts").cast("timestamp"))
    return rows.withWatermark("ts", watermark) if watermark else rows


def run_to_table(df: DataFrame, *, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame | None:
    """Run a stream over all available input, then read what it wrote. Files and checkpoints stand in the shared folder."""
    spark = df.sparkSession
    base = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = df.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{base}/state")
    if each is not None:
        writer.outputMode(mode).foreachBatch(each).start().awaitTermination()
        return None
    if mode == "append":
        writer.format("parquet").outputMode("append").start(f"{base}/rows").awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/rows")

    def keep(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows/batch={i}")

    writer.outputMode(mode).foreachBatch(keep).start().awaitTermination()
    return spark.read.option("basePath", f"{base}/rows").parquet(f"{base}/rows")


def _times(df: DataFrame) -> DataFrame:
    return df.select("*", F.unix_seconds("w.start").alias("start_s"), F.unix_seconds("w.end").alias("end_s")).drop("w")


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    """(event_type, start_s, end_s, n) of windows that the watermark has closed."""
    return _times(events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")))


def sliding(events: DataFrame, size: str = "2 hours", step: str = "30 minutes") -> DataFrame:
    return _times(events.groupBy(F.window("ts", size, step).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")))


def sessions(events: DataFrame, gap: str = "20 minutes") -> DataFrame:
    """Runs of events of a type whose gaps stay under the given one: the stream form of gap runs."""
    return _times(events.groupBy(F.session_window("ts", gap).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")))


def deduplicated(events: DataFrame, seconds: int) -> DataFrame:
    """(t, item) of event buckets, each once: occurrences are sets. State lives as long as the watermark lets rows come late."""
    t = F.floor(F.unix_seconds("ts") / seconds).cast("long")
    return events.select("ts", t.alias("t"), F.col("event_type").alias("item")).dropDuplicatesWithinWatermark(["t", "item"]).select("t", "item")
