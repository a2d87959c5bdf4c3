"""Dense intervals of a stream: single items with state, itemsets by re-mining only what new data can change."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from localfreq.operators.segments import merge_runs

__all__ = ["ShardedTimeline", "late_counts", "latest", "online_dense_items"]


def online_dense_items(occ: DataFrame, width: int, sigma: int, *, delay: int = 0, expire_ms: int | None = None) -> DataFrame:
    """A log of (pattern, s, e, late) from a stream of (pattern, t): runs of dense starts that new times begin or extend, and counts of late times.

    State per pattern: its largest time, and the times at most ``delay`` + ``width`` before it, which later arrivals may still meet. A time that is more than
    ``delay`` below the largest of the batches before is late: it is counted (a row without s) and left out. Repeated times count once. Adding
    times only adds dense starts, so ``latest`` of the log is exact for all times that were not late. Ends are not cut, since the last time is unknown.

    ``expire_ms`` drops a pattern's state so long after the watermark of its last batch; the stream needs an event time with a watermark then, and
    Spark itself leaves out (and counts) rows behind the watermark.
    """
    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        held, top = state.get if state.exists else ([], -1)
        arrived = np.concatenate([f["t"].to_numpy(np.int64) for f in frames])
        horizon = top - delay if top >= 0 else np.iinfo(np.int64).min
        new = np.unique(arrived[arrived >= horizon])
        late = len(arrived) - int((arrived >= horizon).sum())
        rows = [(key[0], None, None, late)] if late else []
        if len(new):
            times = np.union1d(np.array(held, np.int64), new)
            top = max(top, int(times[-1]))
            first, last = times[:len(times) - sigma + 1], times[sigma - 1:]
            near = last - first <= width
            near &= np.searchsorted(new, last, "right") > np.searchsorted(new, first, "left")  # groups that hold a new time
            a, b = np.maximum(0, last[near] - width), first[near]
            cuts = np.flatnonzero(a[1:] > b[:-1] + 1) + 1
            if len(a):
                rows += [(key[0], int(a[i]), int(b[j - 1]) + width, 0) for i, j in zip([0, *cuts], [*cuts, len(a)], strict=True)]
            held = times[times >= top - delay - width].tolist()
        state.update((held, top))
        if expire_ms is not None:
            state.setTimeoutTimestamp(max(0, state.getCurrentWatermarkMs()) + expire_ms)
        yield pd.DataFrame(rows, columns=["pattern", "s", "e", "late"]).astype({"s": "Int64", "e": "Int64", "late": "int64"})

    timeout = GroupStateTimeout.NoTimeout if expire_ms is None else GroupStateTimeout.EventTimeTimeout
    return occ.groupBy("pattern").applyInPandasWithState(update, "pattern string, s long, e long, late long", "times array<long>, top long", "append", timeout)


def latest(log: DataFrame, width: int) -> DataFrame:
    """(pattern, s, e): the intervals of a log, its runs joined where they touch."""
    runs = log.where("s is not null").select("pattern", "s", (F.col("e") - width).alias("d"))
    return merge_runs(runs, ["pattern"]).select("pattern", "s", (F.col("d") + width).alias("e"))


def late_counts(log: DataFrame) -> DataFrame:
    """(pattern, late): how many times of each pattern came too late; 0 for patterns without."""
    return log.groupBy("pattern").agg(F.sum("late").alias("late"))


class ShardedTimeline:
    """Itemsets of a stream: batches are appended by time shard, and only shards whose windows reach new data are mined again.

    The table of transactions and the table of shard runs stand under ``path``, both partitioned by shard.
    """

    def __init__(self, spark: SparkSession, path: str, width: int, sigma: int, *, shard_width: int, k_max: int | None = None):
        self.spark, self.path, self.width, self.sigma, self.c, self.k_max = spark, path, width, sigma, int(shard_width), k_max
        self.mined: list[int] = []

    def add(self, batch: DataFrame, batch_id: int) -> None:
        """For foreachBatch: TRANSACTION rows. Writing a batch again replaces it, so a retried batch changes nothing."""
        c, width = self.c, self.width
        rows = batch.select("t", "items").persist()
        own = F.floor(F.col("t") / c).cast("long")
        rows.withColumn("own", own).write.mode("overwrite").partitionBy("own").parquet(f"{self.path}/tx/batch={batch_id}")
        low = F.floor(F.greatest(F.lit(0), F.col("t") - width) / c).cast("long")
        touched = sorted(r[0] for r in rows.select(F.explode(F.sequence(low, own)).alias("s")).distinct().collect())  # shard numbers of one batch
        rows.unpersist()
        if touched:
            self._mine(touched)
            self.mined += touched

    def _mine(self, shards: list[int]) -> None:
        from localfreq.plans.sharded import mine_shard
        from localfreq.schema import pattern_text

        c, width, sigma, k_max = self.c, self.width, self.sigma, self.k_max
        tx = self.spark.read.parquet(f"{self.path}/tx").where((F.col("own") >= min(shards)) & (F.col("own") <= max(shards) + -(-width // c) + 1))
        low = F.floor(F.greatest(F.lit(0), F.col("t") - width) / c).cast("long")
        dealt = tx.select("t", "items", F.explode(F.sequence(low, F.floor(F.col("t") / c).cast("long"))).alias("shard")).where(F.col("shard").isin(shards))

        def local(key, g: pd.DataFrame) -> pd.DataFrame:
            lo = int(key[0]) * c
            found = mine_shard(list(zip(g["t"], g["items"], strict=True)), width, sigma, lo, lo + c - 1, k_max)
            return pd.DataFrame([(int(key[0]), list(p), s, d) for p, s, d in found], columns=["shard", "items", "s", "d"])

        runs = dealt.groupBy("shard").applyInPandas(local, "shard long, items array<string>, s long, d long")
        rows = runs.select(pattern_text(F.col("items")).alias("pattern"), "s", "d", "shard")
        empty = self.spark.createDataFrame([(shard,) for shard in shards], "shard long").select(F.lit(None).cast("string").alias("pattern"), F.lit(None).cast("long").alias("s"), F.lit(None).cast("long").alias("d"), "shard")
        # one job replaces the folders of all these shards as a whole; a row without pattern stands for a shard that has nothing
        rows.unionByName(empty).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("shard").parquet(f"{self.path}/runs")

    def intervals(self) -> DataFrame:
        """(pattern, s, e) of all data so far, ends not cut."""
        runs = self.spark.read.schema("pattern string, s long, d long, shard long").parquet(f"{self.path}/runs").where("pattern is not null")
        return merge_runs(runs.select("pattern", "s", "d"), ["pattern"]).select("pattern", "s", (F.col("d") + self.width).alias("e"))
