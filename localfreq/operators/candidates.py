"""Candidate patterns of the level-wise search, as joins.

A level holds (prefix, last): all items but the last as text, and the last. Two patterns with the same prefix give a
candidate; since time is part of the key when their occurrences meet, a hot prefix spreads over tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from localfreq.operators.intervals import intersect_intervals

__all__ = ["candidate_ranges", "extend_occurrences", "join_candidates", "joined", "prune_by_subsets"]

#: Splits a pattern's text at separators that are not escaped.
_CUT = r"(?<=(?<!\\)(?:\\\\){0,8})\|"


def joined(prefix: Column, last: Column) -> Column:
    return F.when(prefix == "", last).otherwise(F.concat(prefix, F.lit("|"), last))


def join_candidates(level: DataFrame) -> DataFrame:
    """(prefix, last, pattern) of the next level from (prefix, last): an equi-join on the prefix."""
    a = level.select(F.col("prefix").alias("p"), F.col("last").alias("a"))
    b = level.select(F.col("prefix").alias("p"), F.col("last").alias("b"))
    pairs = a.join(b, "p").where("a < b")
    return pairs.select(joined(F.col("p"), F.col("a")).alias("prefix"), F.col("b").alias("last")).withColumn("pattern", joined(F.col("prefix"), F.col("last")))


def items_of(pattern: Column) -> Column:
    return F.split(pattern, _CUT)


def prune_by_subsets(candidates: DataFrame, level: DataFrame, k: int) -> DataFrame:
    """Candidates of k items all of whose subsets of k - 1 items are in the level. The two that made it are known to be."""
    if k <= 2:
        return candidates
    items = items_of(F.col("pattern"))
    without = F.transform(F.sequence(F.lit(1), F.lit(k - 2)), lambda i: F.array_join(F.filter(items, lambda x, j: j != i - 1), "|"))
    asked = candidates.select("pattern", F.explode(without).alias("subset"))
    known = level.select(joined(F.col("prefix"), F.col("last")).alias("subset"))
    full = asked.join(known, "subset", "left_semi").groupBy("pattern").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == k - 2)
    return candidates.join(full, "pattern", "left_semi")


def extend_occurrences(occ: DataFrame, candidates: DataFrame, *, narrow: bool = False) -> DataFrame:
    """Occurrences (prefix, last, pattern, t) of the candidates from those (prefix, last, t) of the level below.

    Times are intersected by joining on (prefix, t); candidates keep only what may be dense. No item's times are ever one array.
    ``narrow`` first drops occurrences of patterns that no candidate is made of: worth its two joins once candidates are pruned.
    """
    a = occ.select(F.col("prefix").alias("p"), F.col("last").alias("a"), "t")
    b = occ.select(F.col("prefix").alias("p"), F.col("last").alias("b"), "t")
    if narrow:
        a = a.withColumn("of", joined(F.col("p"), F.col("a"))).join(candidates.select(F.col("prefix").alias("of")).distinct(), "of", "left_semi").drop("of")
        uppers = candidates.select(joined(F.array_join(F.slice(items_of(F.col("prefix")), 1, F.greatest(F.size(items_of(F.col("prefix"))) - 1, F.lit(0))), "|"), F.col("last")).alias("of")).distinct()
        b = b.withColumn("of", joined(F.col("p"), F.col("b"))).join(uppers, "of", "left_semi").drop("of")
    pairs = a.join(b, ["p", "t"]).where("a < b").select(joined(F.col("p"), F.col("a")).alias("prefix"), F.col("b").alias("last"), "t")
    return pairs.join(candidates.select("prefix", "last", "pattern"), ["prefix", "last"])


def candidate_ranges(candidates: DataFrame, item_intervals: DataFrame, width: int, k: int) -> DataFrame:
    """(pattern, s, e): the common part of the dense intervals of each candidate's items, of at least the width.

    Intersection is done in the space of window starts, where an item's runs never overlap: [s, e] stands for starts s..e-width.
    """
    items = candidates.select("pattern", F.posexplode(items_of(F.col("pattern"))).alias("i", "item"))
    starts = item_intervals.select(F.col("pattern").alias("item"), "s", (F.col("e") - width + 1).alias("e"))
    spread = items.join(starts, "item")
    out = spread.where("i = 0").select("pattern", "s", "e")
    for i in range(1, k):
        out = intersect_intervals(out, spread.where(F.col("i") == i).select("pattern", "s", "e"), ["pattern"])
    return out.select("pattern", "s", (F.col("e") - 1 + width).alias("e")).where(F.col("e") - F.col("s") >= width)
