"""Level-wise search and the dense miner built on it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localfreq.operators.baskets import to_occurrences
from localfreq.operators.candidates import candidate_ranges, extend_occurrences, join_candidates, joined, prune_by_subsets
from localfreq.operators.detect import dense_intervals, dense_intervals_many, last_time
from localfreq.operators.intervals import covers
from localfreq.schema import pattern_len
from localfreq.session import checkpointed

__all__ = ["as_map", "check_monotone", "closed_patterns", "dense_items", "filter_patterns", "level_wise", "maximal_patterns", "mine_dense", "mine_dense_many", "nested", "prune_counters", "topk_patterns", "trim_occurrences"]


def level_wise(occ: DataFrame, keep: Callable[[DataFrame, int], DataFrame], k_max: int | None = None, *, trim: Callable[[DataFrame, DataFrame], DataFrame] | None = None, counters: list | None = None) -> Iterator[tuple[int, DataFrame, DataFrame]]:
    """(k, occurrences, kept) level by level from OCC of single items.

    ``keep(occurrences, k)`` gives a frame with the column ``pattern`` whose patterns go on; it must be safe: a superset of a dropped
    pattern is dropped as well. ``trim`` may remove occurrences that cannot help a larger pattern. A level's occurrences are made once
    and held while ``keep`` and ``trim`` read them; what stays is checkpointed, so lineage stays short. The driver sees one emptiness test a level.
    """
    level = occ.select(F.lit("").alias("prefix"), F.col("pattern").alias("last"), "pattern", "t").persist()
    k = 1
    while k_max is None or k <= k_max:
        kept = checkpointed(keep(level, k))
        if counters is not None:
            counters.append({"level": k, "kept": kept.select("pattern").distinct().count()})
        if kept.isEmpty():
            level.unpersist()
            return
        made = level
        level = made.join(kept.select("pattern").distinct(), "pattern", "left_semi")
        if trim is not None:
            level = trim(level, kept)
        if k == k_max:  # nobody extends this level: its occurrences are made again only if they are asked for
            made.unpersist()
            yield k, level, kept
            return
        level = checkpointed(level)
        made.unpersist()
        yield k, level, kept
        shape = level.select("prefix", "last").distinct()
        generated = join_candidates(shape)
        candidates = prune_by_subsets(generated, shape, k + 1)
        if k > 1:
            candidates = checkpointed(candidates)
        if counters is not None:
            n = generated.count()
            counters[-1] |= {"generated": n, "pruned_subset": n - candidates.count()}
        level = extend_occurrences(level, candidates, narrow=k > 1).persist()
        k += 1


def dense_items(occ: DataFrame, width: int, sigma: int, *, t_max: int | None = None, clip_end: bool = True) -> DataFrame:
    """INTERVAL of single items, after dropping items with fewer than sigma occurrences."""
    found = dense_intervals(occ, width, sigma, t_max=t_max, clip_end=clip_end, prefilter=True)
    return found.select("pattern", F.lit(1).cast("int").alias("len"), "s", "e")


def trim_occurrences(occ: DataFrame, intervals: DataFrame) -> DataFrame:
    """The occurrences that lie in a dense interval of their own pattern: others can't help a larger pattern."""
    return covers(occ, intervals.select("pattern", "s", "e"), ["pattern"])


def mine_dense(tx: DataFrame, width: int, sigma: int, *, k_max: int | None = None, min_len: int = 1, restrict: str = "parents", clip_end: bool = True, counters: list | None = None) -> DataFrame:
    """INTERVAL of all dense patterns of the transactions.

    ``restrict`` none: search all times; items: only where all items are dense (the common part of their dense intervals); parents:
    occurrences outside the dense intervals of the pattern one level below are dropped. Results are the same.
    """
    if restrict not in ("none", "items", "parents"):
        raise ValueError(f"no such restriction: {restrict}")
    t_max = last_time(tx)  # of the whole database, before anything is dropped
    if t_max is None:
        t_max = -1
    singles: list[DataFrame] = []

    def keep(level: DataFrame, k: int) -> DataFrame:
        if restrict == "items" and k > 1:
            ranges = candidate_ranges(level.select("pattern").distinct(), singles[0], width, k)
            level = covers(level, ranges, ["pattern"])
        found = dense_intervals(level, width, sigma, t_max=t_max, clip_end=clip_end, prefilter=True)
        found = found.select("pattern", F.lit(k).cast("int").alias("len"), "s", "e")
        if k == 1:
            found = checkpointed(found)
            singles.append(found)
        return found

    def trim(level: DataFrame, kept: DataFrame) -> DataFrame:
        return trim_occurrences(level, kept)

    out = None
    for k, _, kept in level_wise(to_occurrences(tx), keep, k_max, trim=trim if restrict != "none" else None, counters=counters):
        if k >= min_len:
            out = kept if out is None else out.unionByName(kept)
    return out if out is not None else tx.sparkSession.createDataFrame([], "pattern string, len int, s long, e long")


def mine_dense_many(tx: DataFrame, settings: list[tuple[int, int]], *, k_max: int = 2) -> DataFrame:
    """(width, sigma, pattern, len, s, e) for several settings in one search: a pattern goes on if any setting has it dense."""
    t_max = last_time(tx)
    out = None
    for k, _, kept in level_wise(to_occurrences(tx), lambda level, k: dense_intervals_many(level, settings, t_max=t_max), k_max):
        rows = kept.select("width", "sigma", "pattern", F.lit(k).cast("int").alias("len"), "s", "e")
        out = rows if out is None else out.unionByName(rows)
    return out if out is not None else tx.sparkSession.createDataFrame([], "width long, sigma long, pattern string, len int, s long, e long")


def prune_counters(tx: DataFrame, width: int, sigma: int, k_max: int | None = None) -> DataFrame:
    """Per level: candidates generated, dropped for a missing subset, without a common occurrence, without a common range of their items, scanned, and dense."""
    t_max = last_time(tx)
    counters: list[dict] = []
    met: list[tuple[int, int]] = []
    singles: list[DataFrame] = []

    def keep(level: DataFrame, k: int) -> DataFrame:
        names = level.select("pattern").distinct()
        found = dense_intervals(level, width, sigma, t_max=-1 if t_max is None else t_max)
        n = names.count()
        if k == 1:
            found = checkpointed(found)
            singles.append(found)
            met.append((n, n))
        else:
            met.append((n, candidate_ranges(names, singles[0], width, k).select("pattern").distinct().count()))
        return found

    for _ in level_wise(to_occurrences(tx), keep, k_max, counters=counters):
        pass
    rows, made = [], {"generated": met[0][0] if met else 0, "pruned_subset": 0}
    for c, (occurring, ranged) in zip(counters, met, strict=True):
        left = made["generated"] - made["pruned_subset"]
        rows.append((c["level"], made["generated"], made["pruned_subset"], left - occurring, occurring - ranged, ranged, c["kept"]))
        made = c
    return tx.sparkSession.createDataFrame(rows, "level int, generated long, pruned_subset long, empty_occurrences long, empty_ranges long, scanned long, dense long")


def nested(res: DataFrame) -> DataFrame:
    """One row a pattern with all its intervals, in order."""
    return res.groupBy("pattern").agg(F.sort_array(F.collect_list(F.struct("s", "e"))).alias("intervals"))


def as_map(res: DataFrame) -> DataFrame:
    """One row: the map from pattern to intervals. For results that fit one row."""
    return nested(res).agg(F.map_from_entries(F.collect_list(F.struct("pattern", "intervals"))).alias("patterns"))


def filter_patterns(res: DataFrame, *, min_len: int = 1, max_len: int | None = None, min_duration: int = 0) -> DataFrame:
    out = res.where((F.col("len") >= min_len) & (F.col("e") - F.col("s") >= min_duration))
    return out if max_len is None else out.where(F.col("len") <= max_len)


def _subsets(res: DataFrame) -> DataFrame:
    """(pattern, subset): each pattern's subsets of one item less."""
    from localfreq.operators.candidates import items_of

    items = items_of(F.col("pattern"))
    n = F.size(items)
    less = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.array_join(F.filter(items, lambda x, j: j != i), "|"))
    return res.select("pattern").distinct().where(n > 1).select("pattern", F.explode(less).alias("subset"))


def maximal_patterns(res: DataFrame) -> DataFrame:
    """Dense patterns that no dense pattern of one more item contains (so, by anti-monotonicity, no larger one does)."""
    below = _subsets(res).select(F.col("subset").alias("pattern")).distinct()
    return res.select("pattern", "len").distinct().join(below, "pattern", "left_anti")


def closed_patterns(res: DataFrame) -> DataFrame:
    """Dense patterns whose intervals no dense pattern of one more item has in the same form: (pattern, len)."""
    form = lambda df, name: nested(df).select("pattern", F.xxhash64("intervals").alias(name))
    above = _subsets(res).join(form(res, "h"), "pattern").select(F.col("subset").alias("pattern"), "h").distinct()
    return res.select("pattern", "len").distinct().join(form(res, "h"), "pattern").join(above, ["pattern", "h"], "left_anti").select("pattern", "len")


def topk_patterns(res: DataFrame, k: int, *, by: str = "duration") -> DataFrame:
    """(len, rank, pattern, ``by``): per length the k patterns of longest total duration, or of the highest ``peak_sup`` (from ``with_support``), ties by text."""
    from pyspark.sql.window import Window

    if by not in ("duration", "peak_sup"):
        raise ValueError(f"no such order: {by}")
    value = F.sum(F.col("e") - F.col("s")) if by == "duration" else F.max("peak_sup")
    total = res.groupBy("len", "pattern").agg(value.alias(by))
    order = Window.partitionBy("len").orderBy(F.desc(by), "pattern")
    return total.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("len", "rank", "pattern", by)


def check_monotone(res: DataFrame) -> DataFrame:
    """Violations of containment (none, for a right result): intervals that no interval of some subset contains."""
    asked = _subsets(res).join(res.select("pattern", "s", "e"), "pattern")
    tops = res.select(F.col("pattern").alias("subset"), F.col("s").alias("x"), F.col("e").alias("top"), F.lit(0).alias("kind"), F.lit(None).cast("string").alias("of"), F.lit(None).cast("long").alias("end"))
    rows = asked.select("subset", F.col("s").alias("x"), F.lit(None).cast("long").alias("top"), F.lit(1).alias("kind"), F.col("pattern").alias("of"), F.col("e").alias("end")).unionByName(tops)
    from pyspark.sql.window import Window

    by = Window.partitionBy("subset").orderBy("x", "kind").rowsBetween(Window.unboundedPreceding, 0)
    reached = rows.withColumn("reach", F.max("top").over(by)).where("kind = 1")
    return reached.where("reach is null or reach < end").select(F.col("of").alias("pattern"), "subset", F.col("x").alias("s"), F.col("end").alias("e"))
