"""Baskets and occurrences: from rows to transactions, to the long form, and back."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localfreq.operators.timeline import rank_timeline
from localfreq.schema import escape_item

__all__ = ["encode_items", "occurrences_from_rows", "occurrences_of", "profile", "resolve_duplicates", "to_baskets", "to_occurrences"]


def to_baskets(rows: DataFrame, t: str, item: str) -> DataFrame:
    """TRANSACTION from (time, item) rows; null and blank items are dropped, times without items stay with an empty set."""
    clean = F.when(F.trim(F.col(item)) != "", F.col(item))
    return rows.groupBy(F.col(t).cast("long").alias("t")).agg(F.array_sort(F.collect_set(clean)).alias("items"))


def resolve_duplicates(tx: DataFrame, policy: str = "union", *, slots: int = 1000) -> DataFrame:
    """One transaction a time. union: sets of one time are joined; rank: times become places in the order; slot: time * slots + place within the time; error: fail."""
    if policy == "union":
        return tx.groupBy("t").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    if policy == "rank":
        keyed = tx.withColumn("_key", F.array_join("items", "|"))
        return rank_timeline(keyed, ["t", "_key"], name="_t").select(F.col("_t").alias("t"), "items")
    if policy == "slot":
        from localfreq.operators.timeline import day_slot_timeline

        return day_slot_timeline(tx.withColumn("_key", F.array_join("items", "|")), "t", ["_key"], slots=slots, name="_t").select(F.col("_t").alias("t"), "items")
    if policy == "error":
        only = F.when(F.count(F.lit(1)) == 1, F.first("items")).otherwise(F.raise_error("a time has several transactions").cast("array<string>"))
        return tx.groupBy("t").agg(only.alias("items"))
    raise ValueError(f"no such policy: {policy}")


def to_occurrences(tx: DataFrame) -> DataFrame:
    """OCC of single items. Sets have no repeated items, so nothing is shuffled."""
    return tx.select(F.explode("items").alias("pattern"), "t").select(escape_item(F.col("pattern")).alias("pattern"), "t")


def occurrences_from_rows(rows: DataFrame, t: str, item: str) -> DataFrame:
    """OCC of single items straight from (time, item) rows: one shuffle of distinct pairs, no baskets."""
    return rows.where(F.col(item).isNotNull() & (F.trim(F.col(item)) != "")).select(escape_item(F.col(item)).alias("pattern"), F.col(t).cast("long").alias("t")).distinct()


def occurrences_of(tx: DataFrame, itemset: list[str]) -> DataFrame:
    """Times of the transactions that hold all given items: one narrow scan."""
    wanted = F.array(*map(F.lit, itemset)) if itemset else F.array().cast("array<string>")
    return tx.where(F.size(F.array_except(wanted, "items")) == 0).select("t")


def profile(tx: DataFrame) -> DataFrame:
    """One row: transactions, last time, mean length, distinct items. Empty transactions count."""
    sizes = tx.agg(F.count(F.lit(1)).alias("n_tx"), F.max("t").alias("t_max"), F.round(F.avg(F.size("items")), 6).alias("mean_len"), F.sum(F.size("items")).cast("long").alias("n_pairs"))
    items = to_occurrences(tx).agg(F.countDistinct("pattern").alias("n_items"))
    return sizes.join(F.broadcast(items), how="cross")


def encode_items(occ: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(OCC with integer items, dictionary). Codes follow the binary order of the items, numbered without a single task."""
    words = rank_timeline(occ.select("pattern").distinct(), ["pattern"], start=0, name="code")
    return occ.join(words, "pattern").select(F.col("code").alias("item"), "t"), words
