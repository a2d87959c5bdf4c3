"""Dense intervals of patterns: supports, curves, and detection by window expressions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.operators.segments import dense_segments, merge_monotone, merge_runs

__all__ = ["dense_intervals", "dense_intervals_many", "dense_intervals_sql", "dense_runs", "dense_windows", "interval_support", "last_time", "support_curve", "with_support"]


def last_time(tx: DataFrame) -> int | None:
    """The last time of the whole database, empty transactions included: one small aggregate."""
    return tx.agg(F.max("t")).first()[0]


def dense_runs(occ: DataFrame, width: int, sigma: int, *, t_max: int | None = None, keys=("pattern",), clip_end: bool = True, shard_width: int | None = None, discrete: bool = True) -> DataFrame:
    """(keys, s, d): maximal runs of dense window starts.

    ``clip_end`` keeps starts up to t_max - width. ``shard_width`` splits each pattern's time into shards that are
    detected apart (each occurrence copied to the shards whose windows reach it) and joined by one small merge: a pattern
    that holds a third of all rows then spreads over many tasks. ``discrete`` false joins runs only if they meet.
    """
    keys = list(keys)
    if clip_end and t_max is None:
        t_max = last_time(occ)
    last = (t_max if t_max is not None else -1) - width if clip_end else None
    gap = 1 if discrete else 0
    if shard_width is None:
        return merge_monotone(dense_segments(occ, width, sigma, keys, last_start=last), keys, gap=gap)
    c = int(shard_width)
    low = F.floor(F.greatest(F.lit(0), F.col("t") - width) / F.lit(c)).cast("long")
    high = F.floor(F.col("t") / F.lit(c)).cast("long")
    dealt = occ.select(*keys, "t", F.explode(F.sequence(low, high)).alias("_shard"))
    segments = dense_segments(dealt, width, sigma, [*keys, "_shard"], last_start=last)
    return merge_runs(merge_monotone(segments, [*keys, "_shard"], gap=gap).drop("_shard"), keys, gap=gap)


def dense_intervals(occ: DataFrame, width: int, sigma: int, *, t_max: int | None = None, keys=("pattern",), clip_end: bool = True, shard_width: int | None = None, prefilter: bool = False, discrete: bool = True) -> DataFrame:
    """(keys, s, e): dense intervals, e = last dense start + width.

    ``prefilter`` drops patterns with fewer than sigma occurrences in all before the large exchange; worth its own
    partial aggregation where most patterns are rare.
    """
    keys = list(keys)
    if prefilter:
        often = occ.groupBy(*keys).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") >= sigma).drop("_n")
        occ = occ.join(often, keys, "left_semi")
    return dense_runs(occ, width, sigma, t_max=t_max, keys=keys, clip_end=clip_end, shard_width=shard_width, discrete=discrete).select(*keys, "s", (F.col("d") + width).alias("e"))


def dense_intervals_many(occ: DataFrame, settings: list[tuple[int, int]], *, t_max: int | None = None, keys=("pattern",), clip_end: bool = True) -> DataFrame:
    """(width, sigma, keys, s, e) for several settings: rows are copied per width in one exchange, one branch a distinct sigma."""
    t_max = last_time(occ) if t_max is None else t_max
    out = None
    for sigma in sorted({s for _, s in settings}):
        widths = sorted({w for w, s in settings if s == sigma})
        copies = occ.withColumn("width", F.explode(F.array(*(F.lit(w).cast("long") for w in widths))))
        by = ["width", *keys]
        far = F.lead("t", sigma - 1).over(Window.partitionBy(*by).orderBy("t")) if sigma > 1 else F.col("t")
        near = copies.select(*by, "t", far.alias("_far")).where(F.col("_far") - F.col("t") <= F.col("width"))
        b = F.least(F.col("t"), F.lit(t_max) - F.col("width")) if clip_end else F.col("t")
        segments = near.select(*by, F.greatest(F.lit(0).cast("long"), F.col("_far") - F.col("width")).alias("a"), b.alias("b")).where("a <= b")
        found = merge_monotone(segments, by).select("width", F.lit(sigma).cast("long").alias("sigma"), *keys, "s", (F.col("d") + F.col("width")).alias("e"))
        out = found if out is None else out.unionByName(found)
    return out


def support_curve(occ: DataFrame, width: int, *, keys=("pattern",)) -> DataFrame:
    """(keys, t, sup): occurrences in the closed window that starts at each occurrence."""
    by = Window.partitionBy(*keys).orderBy("t").rangeBetween(0, width)
    return occ.select(*keys, "t", F.count(F.lit(1)).over(by).alias("sup"))


def interval_support(occ: DataFrame, windows: DataFrame, width: int) -> DataFrame:
    """(pattern, l, sup) for given (pattern, l): an equi-join on time buckets of the window's width, never a theta join."""
    bucket = lambda c: F.floor(c / F.lit(width + 1)).cast("long")
    asked = windows.select("pattern", "l", F.explode(F.array(bucket(F.col("l")), bucket(F.col("l")) + 1)).alias("_b"))
    rows = occ.withColumn("_b", bucket(F.col("t")))
    met = asked.join(rows, ["pattern", "_b"], "left")
    hit = F.when(F.col("t").between(F.col("l"), F.col("l") + width), 1)
    return met.groupBy("pattern", "l").agg(F.count(hit).alias("sup"))


def dense_windows(occ: DataFrame, windows: DataFrame, width: int, sigma: int) -> DataFrame:
    """(pattern, l, sup, is_dense) for given window starts."""
    return interval_support(occ, windows, width).withColumn("is_dense", (F.col("sup") >= sigma).cast("int"))


def with_support(intervals: DataFrame, occ: DataFrame, width: int, *, t_max: int | None = None) -> DataFrame:
    """Adds n_occ (occurrences inside) and peak_sup (largest window count over the interval's starts).

    Occurrences find their intervals through the merged starts: bucketed by the width, so it stays an equi-join. The
    peak is reached at an occurrence among the starts or, if the end is cut, at the last start itself.
    """
    bucket = lambda c: F.floor(c / F.lit(width + 1)).cast("long")
    spread = intervals.withColumn("_b", F.explode(F.sequence(bucket(F.col("s")), bucket(F.col("e")))))
    curve = support_curve(occ, width).withColumn("_b", bucket(F.col("t")))
    inside = spread.join(curve, ["pattern", "_b"]).where("t between s and e")
    sums = inside.groupBy("pattern", "s", "e").agg(F.count(F.lit(1)).alias("n_occ"), F.max(F.when(F.col("t") <= F.col("e") - width, F.col("sup"))).alias("_at"))
    ends = interval_support(occ, intervals.select("pattern", (F.col("e") - width).alias("l")).distinct(), width)
    joined = intervals.join(sums, ["pattern", "s", "e"], "left").join(ends.withColumn("e", F.col("l") + width).select("pattern", "e", F.col("sup").alias("_end")), ["pattern", "e"], "left")
    return joined.select(*intervals.columns, F.coalesce("n_occ", F.lit(0)).alias("n_occ"), F.greatest(F.coalesce("_at", F.lit(0)), F.coalesce("_end", F.lit(0))).alias("peak_sup"))


def dense_intervals_sql(view: str, width: int, sigma: int, t_max: int) -> str:
    """The detection as one SQL statement over a view (pattern, t), for users of the SQL surface."""
    last = t_max - width
    return f"""
    with near as (select pattern, t, lead(t, {sigma - 1}) over (partition by pattern order by t) as far from {view}),
    seg as (select pattern, greatest(0, far - {width}) as a, least(t, {last}) as b from near where far - t <= {width}),
    marked as (select pattern, a, b, case when a <= lag(b) over (partition by pattern order by a, b) + 1 then 0 else 1 end as fresh from seg where a <= b),
    runs as (select pattern, a, b, sum(fresh) over (partition by pattern order by a, b rows unbounded preceding) as run from marked)
    select pattern, min(a) as s, max(b) + {width} as e from runs group by pattern, run"""
