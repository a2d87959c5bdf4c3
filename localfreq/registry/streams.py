"""Queries of streams, each run to completion and read back."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localfreq.registry.sqltext import TRIPLES, base, islands
from localfreq.session import shared_folder
from localfreq.sources.tables import table, transactions
from localfreq.streaming import windows
from localfreq.streaming.dense import ShardedTimeline, late_counts, latest, online_dense_items

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


_CLOSED = "w as (select max(epoch_us(ts) // 1000000) - 3600 as mark from events)"


@query(f"with {_CLOSED}, k as (select event_type, (epoch_us(ts) // 1000000) // 86400 * 86400 as start_s, count(*) as n from events group by 1, 2) select event_type, start_s, start_s + 86400 as end_s, n from k, w where start_s + 86400 <= mark")
def stream_tumbling(spark, d):
    return windows.run_to_table(windows.tumbling(windows.event_stream(spark, d)))


@query(f"with {_CLOSED}, k as (select event_type, ((epoch_us(ts) // 1000000) // 1800 - i) * 1800 as start_s, count(*) as n from events cross join range(0, 4) r(i) group by 1, 2) select event_type, start_s, start_s + 7200 as end_s, n from k, w where start_s + 7200 <= mark")
def stream_sliding(spark, d):
    return windows.run_to_table(windows.sliding(windows.event_stream(spark, d)))


@query(f"with {_CLOSED}, e as (select event_type, epoch_us(ts) as u from events), l as (select *, case when u - lag(u) over (partition by event_type order by u) < 1200000000 then 0 else 1 end as f from e), r as (select *, sum(f) over (partition by event_type order by u rows unbounded preceding) as g from l), k as (select event_type, min(u) as a, max(u) + 1200000000 as b, count(*) as n from r group by event_type, g) select event_type, a // 1000000 as start_s, b // 1000000 as end_s, n from k, w where b <= mark * 1000000")
def stream_session(spark, d):
    return windows.run_to_table(windows.sessions(windows.event_stream(spark, d)))


_MINUTES = "tx as (select (epoch_us(ts) // 1000000) // 60 as t from events), tm as (select max(t) as tmax from tx), occ as (select distinct event_type as pattern, (epoch_us(ts) // 1000000) // 60 as t from events)"


@query(f"with {_MINUTES}, {islands('r', 'occ', 60, 6, clip=False)} select pattern, s, e from r")
def stream_dense_items(spark, d):
    rows = windows.event_stream(spark, d, watermark=None).select(F.col("event_type").alias("pattern"), F.floor(F.unix_seconds("ts") / 60).cast("long").alias("t"))
    return latest(windows.run_to_table(online_dense_items(rows, 60, 6)), 60)


@query(f"{base('type')}, p as (select a.pattern || '|' || b.pattern as pattern, a.t from occ a join occ b on a.t = b.t and a.pattern < b.pattern), {islands('r1', 'occ', 250, 68, clip=False)}, {islands('r2', 'p', 250, 68, clip=False)}, {TRIPLES}, {islands('r3', 'triples', 250, 68, clip=False)} select pattern, s, e from r1 union all select pattern, s, e from r2 union all select pattern, s, e from r3")
def stream_dense_itemsets(spark, d):
    """Transactions arrive as two batches; the second re-mines only the shards that its times reach."""
    folder = f"{shared_folder(spark)}/timeline-{uuid.uuid4().hex}"
    tx = transactions(spark, d, "type")
    half = tx.agg(F.expr("percentile_approx(t, 0.5)")).first()[0] or 0
    for i, part in enumerate((tx.where(F.col("t") <= half), tx.where(F.col("t") > half))):
        part.write.parquet(f"{folder}/in/part={i}")
    miner = ShardedTimeline(spark, f"{folder}/out", 250, 68, shard_width=4000)
    stream = spark.readStream.schema("t long, items array<string>").option("maxFilesPerTrigger", 4).parquet(f"{folder}/in/part=*")
    windows.run_to_table(stream.where(F.size("items") > 0), each=miner.add)
    return miner.intervals()


_LATE = "ev as (select event_type as pattern, (epoch_us(ts) // 1000000) // 60 as t, event_id % 10 = 0 as second from events), m as (select pattern, max(t) as top from ev where not second group by 1), seen as (select ev.*, second and t < top - 1440 as late from ev join m using (pattern)), tx as (select 0 as t), tm as (select max(t) as tmax from ev), occ as (select distinct pattern, t from seen where not late)"


def _in_two_batches(spark, d) -> DataFrame:
    """(pattern, t) of the events as a stream of two files: first nine tenths, then every tenth event, most of them long overdue."""
    folder = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    rows = table(spark, d, "events", "event_id", "event_type", "ts").select("event_id", F.col("event_type").alias("pattern"), F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 60).cast("long").alias("t"))
    for i, part in enumerate((rows.where("event_id % 10 <> 0"), rows.where("event_id % 10 = 0"))):
        part.select("pattern", "t").coalesce(1).write.parquet(f"{folder}/part={i}")
    return spark.readStream.schema("pattern string, t long").option("maxFilesPerTrigger", 1).parquet(f"{folder}/part=*")


@query(f"with {_LATE}, {islands('r', 'occ', 60, 6, clip=False)} select pattern, s, e, cast((select count(*) from seen where seen.pattern = r.pattern and late) as bigint) as late from r")
def stream_late_data(spark, d):
    """Times up to a day late still make dense intervals; later ones are left out and counted."""
    log = windows.run_to_table(online_dense_items(_in_two_batches(spark, d), 60, 6, delay=1440))
    return latest(log, 60).join(late_counts(log), "pattern").select("pattern", "s", "e", "late")


@query("select event_id from events")
def stream_dedup_ids(spark, d):
    """Every event once: repeats within the watermark are dropped."""
    return windows.run_to_table(windows.event_stream(spark, d).dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@query("select distinct (epoch_us(ts) // 1000000) // 3600 as t, event_type as item from events")
def stream_dedup(spark, d):
    return windows.run_to_table(windows.deduplicated(windows.event_stream(spark, d, watermark="2 hours"), 3600))


@query("select c_mktsegment, count(*) as n from events join customer on c_custkey = user_id group by 1")
def stream_static_join(spark, d):
    joined = windows.event_stream(spark, d).join(table(spark, d, "customer", "c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey")).select("c_mktsegment", "event_id")
    return windows.run_to_table(joined).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("select a.event_id as click_id, b.event_id as purchase_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 30 minute")
def stream_stream_join(spark, d):
    a = windows.event_stream(spark, d).where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("a"))
    b = windows.event_stream(spark, d).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("v"), F.col("ts").alias("b"))
    met = a.join(b, (F.col("u") == F.col("v")) & (F.col("b") >= F.col("a")) & (F.col("b") <= F.col("a") + F.expr("interval 30 minutes")))
    return windows.run_to_table(met.select("click_id", "purchase_id"))
