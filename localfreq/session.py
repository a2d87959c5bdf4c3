"""Session defaults and the two helpers that plans share: reliable checkpoints and shuffle sizing."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession

__all__ = ["DEFAULTS", "broadcasts", "build", "checkpointed", "dealt", "parts", "shared_folder"]

#: What a new session gets; a session that is given is used as it is.
DEFAULTS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
}


def build(master: str = "local[*]", **conf: str) -> SparkSession:
    """A session with the defaults, for tests, benches and notebooks."""
    return SparkSession.builder.master(master).config(map=DEFAULTS | {"spark.ui.enabled": "false"} | conf).getOrCreate()


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's checkpoint folder. Only a session in one machine gets a folder of its own where none is set."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not context.master.startswith("local") or context.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
            folder = tempfile.mkdtemp(prefix="checkpoints-")
        context.setCheckpointDir(folder)
    return context._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage by a reliable checkpoint, which survives lost executors."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def dealt(df: DataFrame, rows: int, *keys: str, each: int = 100_000) -> DataFrame:
    """Dealt by keys into pieces of about ``each`` of its ``rows``. Adaptive execution joins small pieces by their compressed size, and what it joins
    may be too much for several sorts in a small heap; it leaves pieces of a given number alone."""
    return df.repartition(max(df.sparkSession.sparkContext.defaultParallelism, -(-rows // each)), *keys)


def broadcasts(df: DataFrame) -> bool:
    """Whether Spark broadcasts the rows in a join, by its own estimate and limit."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size <= df.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
