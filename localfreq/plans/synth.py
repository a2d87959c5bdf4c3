"""Synthetic transactions: background baskets and planted patterns, reproducible under any partitioning."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

__all__ = ["background_rate", "generate", "plant"]


def _uniform(seed: int, *keys: Column) -> Column:
    """A number in (0, 1) from a hash of the keys: the same on any cluster."""
    return (F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(1 << 40)) + 0.5) / float(1 << 40)


def generate(spark: SparkSession, transactions: int, items: int, mean_len: int, *, seed: int = 1, patterns: int = 50, pattern_len: int = 5, occurrences: int = 100, duration: int = 10_000, parts: int | None = None) -> DataFrame:
    """TRANSACTION rows: gaps of 1 to 3, lengths normal around ``mean_len``, uniform items, and planted patterns.

    Each planted pattern has its own items and ``occurrences`` evenly spaced transactions in one stretch of ``duration``. Gaps are 2 on
    average: transaction i stands at 2 * i plus a hashed 0 or 1, so neighbours differ by 1, 2 or 3 and no running sum over all rows is needed.
    """
    base = spark.range(0, transactions, 1, parts) if parts else spark.range(transactions)
    i = F.col("id")
    t = i * 2 + F.floor(_uniform(seed, i, F.lit("gap")) * 2).cast("long")
    normal = F.sqrt(-2 * F.log(_uniform(seed, i, F.lit("u")))) * F.cos(2 * math.pi * _uniform(seed, i, F.lit("v")))
    size = F.greatest(F.lit(0), F.least(F.lit(items), F.round(mean_len + normal * max(1.0, mean_len / 3)).cast("int")))
    # distinct items: an affine walk modulo the least prime of at least the number of items; no number comes twice, and those past the items are skipped
    prime = next(p for p in range(max(2, items), 2 * max(2, items) + 1) if all(p % q for q in range(2, math.isqrt(p) + 1)))
    first, step = F.floor(_uniform(seed, i, F.lit("first")) * prime), 1 + F.floor(_uniform(seed, i, F.lit("step")) * (prime - 1))
    draws = F.transform(F.sequence(F.lit(0), F.least(F.lit(prime - 1), size + (prime - items))), lambda k: ((first + k * step) % prime).cast("int"))
    chosen = F.slice(F.filter(draws, lambda x: x < items), F.lit(1), size)
    background = F.transform(chosen, lambda x: F.concat(F.lit("i"), x.cast("string")))
    rows = base.select(i.alias("id"), t.alias("t"), background.alias("items"))
    if not patterns:
        return rows.select("t", F.array_sort("items").alias("items"))
    slots = max(1, duration // 2)  # transactions in a stretch
    step = max(1, slots // occurrences)
    room = max(1, transactions - slots)
    start = lambda p: F.floor(F.lit(room) * (p + 0.5) / patterns).cast("long")
    planted = F.flatten(F.transform(
        F.filter(F.sequence(F.lit(0), F.lit(patterns - 1)), lambda p: (i >= start(p)) & (i < start(p) + step * occurrences) & ((i - start(p)) % step == 0)),
        lambda p: F.transform(F.sequence(F.lit(1), F.lit(pattern_len)), lambda j: F.concat(F.lit("P"), p.cast("string"), F.lit("_"), j.cast("string"))),
    ))
    return rows.select("t", F.array_sort(F.concat("items", planted)).alias("items"))


def background_rate(transactions: int, items: int, mean_len: int, width: int, sigma: int) -> dict[str, float]:
    """Expected occurrences of a background item and pair per window; both must stay well below sigma."""
    in_window = width / 2
    single = in_window * mean_len / items
    pair = in_window * mean_len * (mean_len - 1) / (items * (items - 1))
    return {"item": single, "pair": pair, "item_over_sigma": single / sigma, "pair_over_sigma": pair / sigma}


def plant(tx: DataFrame, *, patterns: int = 10, size: int = 5, occurrences: int = 100, first: int = 1000, apart: int = 1300, step: int = 10) -> DataFrame:
    """Adds items X{i}_{j} to the transactions at first + apart * i + step * m: one locality per pattern, by arithmetic alone."""
    m = F.col("t") - first
    i = F.floor(m / apart).cast("int")
    rest = F.pmod(m, F.lit(apart))
    here = (m >= 0) & (i < patterns) & (rest % step == 0) & (rest < step * occurrences)
    extra = F.transform(F.sequence(F.lit(1), F.lit(size)), lambda j: F.concat(F.lit("X"), i.cast("string"), F.lit("_"), j.cast("string")))
    return tx.select("t", F.when(here, F.array_sort(F.concat("items", extra))).otherwise(F.col("items")).alias("items"))
