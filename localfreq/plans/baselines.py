"""Baselines: global, periodic and gap-based miners.

All search level by level with a bound that is safe: no superset of a dropped pattern can meet the criterion. The criterion
itself often is not anti-monotone, so it only selects among the patterns that the bound keeps. Gaps are differences of
neighbouring occurrences; boundary gaps add the one before the first occurrence and the one after the last. All limits are inclusive.
Shares are compared in integers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.operators.baskets import to_occurrences
from localfreq.operators.detect import last_time
from localfreq.plans.miner import level_wise

__all__ = ["fpgrowth", "gap_runs", "gap_stats", "mine_frequent", "mine_gap_local", "mine_partial_periodic", "mine_periodic", "mine_recurring", "mine_surplus_local", "occurrences_with_support", "span_intervals"]


def _count(level: DataFrame) -> DataFrame:
    return level.groupBy("pattern").agg(F.count(F.lit(1)).alias("sup"))


def _search(tx: DataFrame, keep, k_max: int | None, columns: str) -> DataFrame:
    """Union of what ``keep`` gives per level, with the length."""
    out = None
    for k, _, kept in level_wise(to_occurrences(tx), keep, k_max):
        rows = kept.withColumn("len", F.lit(k).cast("int"))
        out = rows if out is None else out.unionByName(rows)
    return out if out is not None else tx.sparkSession.createDataFrame([], f"pattern string, {columns}, len int")


def gap_stats(occ: DataFrame, t_max: int, *, keys=("pattern",)) -> DataFrame:
    """(keys, sup, max_gap, first, last): max_gap includes the boundary gaps."""
    by = Window.partitionBy(*keys).orderBy("t")
    gaps = occ.select(*keys, "t", (F.col("t") - F.lag("t", 1).over(by)).alias("gap"))
    ends = F.greatest(F.coalesce(F.max("gap"), F.lit(0)), F.min("t"), F.lit(t_max) - F.max("t"))
    return gaps.groupBy(*keys).agg(F.count(F.lit(1)).alias("sup"), ends.cast("long").alias("max_gap"), F.min("t").alias("first"), F.max("t").alias("last"))


def occurrences_with_support(tx: DataFrame, min_sup: int, k_max: int | None) -> DataFrame:
    """(pattern, len, t): occurrences of all patterns of at least ``min_sup`` occurrences: the universe that grids share."""
    out = None
    for k, occ, _ in level_wise(to_occurrences(tx), lambda level, k: _count(level).where(F.col("sup") >= min_sup), k_max):
        rows = occ.select("pattern", F.lit(k).cast("int").alias("len"), "t")
        out = rows if out is None else out.unionByName(rows)
    return out if out is not None else tx.sparkSession.createDataFrame([], "pattern string, len int, t long")


def mine_frequent(tx: DataFrame, min_sup: int, *, k_max: int | None = None) -> DataFrame:
    """(pattern, sup, len): at least ``min_sup`` occurrences in the whole database."""
    return _search(tx, lambda level, k: _count(level).where(F.col("sup") >= min_sup), k_max, "sup long").select("pattern", "sup", "len")


def fpgrowth(tx: DataFrame, min_sup: int, *, k_max: int | None = None) -> DataFrame:
    """The same patterns by the library's FP-growth, as a cross-check."""
    from pyspark.ml.fpm import FPGrowth

    from localfreq.schema import pattern_text

    n = tx.count()
    model = FPGrowth(itemsCol="items", minSupport=max(0.0, (min_sup - 0.5) / max(1, n)), minConfidence=1.0).fit(tx.where(F.size("items") > 0).select("items"))
    share = model.freqItemsets.select(pattern_text(F.col("items")).alias("pattern"), F.col("freq").alias("sup"), F.size("items").alias("len"))
    out = share.where(F.col("sup") >= min_sup)
    return out if k_max is None else out.where(F.col("len") <= k_max)


def mine_periodic(tx: DataFrame, max_per: int, min_sup: int, *, k_max: int | None = None) -> DataFrame:
    """(pattern, sup, max_gap, len): no gap, boundaries included, over ``max_per``. The largest gap never shrinks for a superset."""
    t_max = last_time(tx) or 0

    def keep(level: DataFrame, k: int) -> DataFrame:
        return gap_stats(level, t_max).where((F.col("sup") >= min_sup) & (F.col("max_gap") <= max_per)).select("pattern", "sup", "max_gap")

    return _search(tx, keep, k_max, "sup long, max_gap long").select("pattern", "sup", "max_gap", "len")


def short_gaps(occ: DataFrame, max_per, t_max: int, *, keys=("pattern",)) -> DataFrame:
    """(keys, sup, short): how many of the sup + 1 gaps, boundaries included, are at most ``max_per`` (a number or column)."""
    by = Window.partitionBy(*keys).orderBy("t")
    limit = F.lit(max_per) if isinstance(max_per, int) else max_per
    lag, lead = F.lag("t").over(by), F.lead("t").over(by)
    marked = occ.select(*keys, F.when(F.col("t") - F.coalesce(lag, F.lit(0)) <= limit, 1).otherwise(0).alias("g"), F.when(lead.isNull() & (F.lit(t_max) - F.col("t") <= limit), 1).otherwise(0).alias("z"))
    return marked.groupBy(*keys).agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("g") + F.col("z")).alias("short"))


def mine_partial_periodic(tx: DataFrame, max_per: int, min_pr: int, min_sup: int, *, k_max: int | None = None) -> DataFrame:
    """(pattern, sup, short, len): at least ``min_pr`` per cent of all gaps, boundaries included, are at most ``max_per``.

    The share is not anti-monotone; the number of short gaps is, and must be at least min_pr per cent of min_sup + 1.
    """
    t_max = last_time(tx) or 0

    def keep(level: DataFrame, k: int) -> DataFrame:
        stats = short_gaps(level, max_per, t_max)
        return stats.where((F.col("sup") >= min_sup) & (F.col("short") * 100 >= min_pr * (min_sup + 1)))

    found = _search(tx, keep, k_max, "sup long, short long")
    return found.where(F.col("short") * 100 >= F.lit(min_pr) * (F.col("sup") + 1)).select("pattern", "sup", "short", "len")


def gap_runs(occ: DataFrame, max_gap, *, keys=("pattern",), ordinals: DataFrame | None = None) -> DataFrame:
    """(keys, s, e, n): maximal runs of occurrences whose gaps are at most ``max_gap`` (a number or column), with their occurrences.

    With ``ordinals`` (t, ord) the run's transactions are counted too (n_tx).
    """
    limit = F.lit(max_gap) if isinstance(max_gap, int) else max_gap
    extra = ["ord"] if ordinals is not None else []
    if ordinals is not None:
        occ = occ.join(ordinals, "t")
    by = Window.partitionBy(*keys).orderBy("t")
    fresh = F.when(F.col("t") - F.lag("t").over(by) <= limit, 0).otherwise(1)
    marked = occ.select(*keys, "t", *extra, fresh.alias("_f"))
    runs = marked.withColumn("_r", F.sum("_f").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    more = [(F.max("ord") - F.min("ord") + 1).alias("n_tx")] if extra else []
    return runs.groupBy(*keys, "_r").agg(F.min("t").alias("s"), F.max("t").alias("e"), F.count(F.lit(1)).alias("n"), *more).drop("_r")


def _ordinals(tx: DataFrame) -> DataFrame:
    from localfreq.operators.timeline import rank_timeline

    return rank_timeline(tx.select("t"), ["t"], name="ord")


def mine_gap_local(tx: DataFrame, local_sup: int, max_gap: int, min_dur: int, *, k_max: int | None = None, complete: bool = True) -> DataFrame:
    """INTERVAL with local support: runs of gaps up to ``max_gap``, of at least ``min_dur``, in which at least ``local_sup`` per cent of the transactions hold the pattern.

    The support part is not anti-monotone. ``complete`` prunes by the duration of runs alone, which is safe; else patterns without
    a full interval are dropped at once, as a plain level-wise search does.
    """
    ordinals = _ordinals(tx)
    full = F.col("n") * 100 >= F.lit(local_sup) * F.col("n_tx")

    def keep(level: DataFrame, k: int) -> DataFrame:
        runs = gap_runs(level, max_gap, ordinals=ordinals).where(F.col("e") - F.col("s") >= min_dur)
        return runs if complete else runs.where(full)

    found = _search(tx, keep, k_max, "s long, e long, n long, n_tx long")
    return found.where(full).select("pattern", "len", "s", "e", F.col("n").alias("n_occ"))


def _surplus_fold(times: Column, max_per: int, max_so_per: int, min_dur: int) -> Column:
    """Intervals of one session's sorted times, as array of (s, e): opened by a short gap, closed when the surplus of long gaps passes its limit."""
    kind = "struct<start:bigint,prev:bigint,surplus:bigint,out:array<struct<s:bigint,e:bigint>>>"
    state = lambda start, prev, surplus, out: F.struct(start.alias("start"), prev.alias("prev"), surplus.alias("surplus"), out.alias("out")).cast(kind)
    none, zero = F.lit(None).cast("long"), F.lit(0).cast("long")
    closed = lambda a: F.when(a["prev"] - a["start"] >= min_dur, F.concat(a["out"], F.array(F.struct(a["start"].alias("s"), a["prev"].alias("e"))))).otherwise(a["out"])

    def step(a: Column, t: Column) -> Column:
        gap = t - a["prev"]
        over = F.greatest(zero, a["surplus"] + gap - max_per)
        opened = F.when(gap <= max_per, state(a["prev"], t, zero, a["out"])).otherwise(state(none, t, zero, a["out"]))
        grown = F.when(over > max_so_per, state(none, t, zero, closed(a))).otherwise(state(a["start"], t, over, a["out"]))
        return F.when(a["start"].isNull(), opened).otherwise(grown)

    return F.aggregate(times, state(none, none, zero, F.array()), step, closed)


def mine_surplus_local(tx: DataFrame, max_per: int, min_dur: int, max_so_per: int, *, k_max: int | None = None) -> DataFrame:
    """INTERVAL of patterns with a period allowed to run over by a bounded surplus.

    A gap over max_per + max_so_per ends any interval, so occurrences split into sessions at such gaps; a session of at
    least ``min_dur`` is the safe bound, and each session is folded on its own.
    """
    widest = max_per + max_so_per

    def sessions(level: DataFrame) -> DataFrame:
        by = Window.partitionBy("pattern").orderBy("t")
        fresh = F.when(F.col("t") - F.lag("t").over(by) <= widest, 0).otherwise(1)
        return level.select("pattern", "t", fresh.alias("f")).select("pattern", "t", F.sum("f").over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("session"))

    out = None
    keep = lambda level, k: sessions(level).groupBy("pattern", "session").agg((F.max("t") - F.min("t")).alias("d")).where(F.col("d") >= min_dur)
    for k, occ, _ in level_wise(to_occurrences(tx), keep, k_max):
        rows = sessions(occ).groupBy("pattern", "session").agg(F.array_sort(F.collect_list("t")).alias("times")).select("pattern", F.lit(k).cast("int").alias("len"), F.inline(_surplus_fold(F.col("times"), max_per, max_so_per, min_dur)))
        out = rows if out is None else out.unionByName(rows)
    return out if out is not None else tx.sparkSession.createDataFrame([], "pattern string, len int, s long, e long")


def mine_recurring(tx: DataFrame, max_per: int, min_ps: int, *, min_rec: int = 1, k_max: int | None = None) -> DataFrame:
    """INTERVAL with run support: runs of gaps up to ``max_per`` with at least ``min_ps`` occurrences, of patterns that have at least ``min_rec`` of them.

    The number of such runs is not anti-monotone (a superset may split one run in two); the sum of floor(run / min_ps) is.
    """
    def keep(level: DataFrame, k: int) -> DataFrame:
        runs = gap_runs(level, max_per).where(F.col("n") >= min_ps)
        able = runs.groupBy("pattern").agg(F.sum(F.floor(F.col("n") / min_ps)).alias("x")).where(F.col("x") >= min_rec)
        return runs.join(able.select("pattern"), "pattern", "left_semi")

    found = _search(tx, keep, k_max, "s long, e long, n long")
    often = found.groupBy("pattern").agg(F.count(F.lit(1)).alias("rec")).where(F.col("rec") >= min_rec)
    return found.join(often, "pattern").select("pattern", "len", "s", "e", F.col("n").alias("n_occ"), "rec")


def span_intervals(occ: DataFrame, patterns: DataFrame) -> DataFrame:
    """INTERVAL from the first to the last occurrence of each reference pattern."""
    from localfreq.schema import pattern_len

    kept = occ.join(patterns.select("pattern").distinct(), "pattern", "left_semi")
    spans = kept.groupBy("pattern").agg(F.min("t").alias("s"), F.max("t").alias("e"))
    return spans.select("pattern", pattern_len(F.col("pattern")).alias("len"), "s", "e")
