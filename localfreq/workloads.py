"""The experiments over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators.detect import dense_intervals
from localfreq.plans.miner import mine_dense
from localfreq.sources.tables import occurrences, transactions

__all__ = ["SETTINGS", "dense_intervals_items", "reference"]

#: Settings (view, width, sigma) of the accuracy and ablation experiments, by workload.
SETTINGS = {
    "A1": [("brand", 250, 10), ("brand", 250, 14), ("brand", 500, 24), ("brand", 1000, 40)],
    "A2": [("supp", 100, 3), ("supp", 250, 5), ("brandtype", 250, 4)],
    "A3": [("type", 250, 60), ("type", 250, 100)],
}


def dense_intervals_items(spark: SparkSession, sf_dir: str, *, view: str = "brand", width: int = 250, sigma: int = 14) -> DataFrame:
    """(pattern, s, e) of single items of a view over the orders' rank timeline."""
    occ, t_max = occurrences(spark, sf_dir, view)
    return dense_intervals(occ, width, sigma, t_max=t_max)


def reference(spark: SparkSession, sf_dir: str, view: str, width: int, sigma: int, *, k_max: int = 2) -> DataFrame:
    """INTERVAL of dense patterns of two items or more: the exact answer that baselines are scored against."""
    return mine_dense(transactions(spark, sf_dir, view), width, sigma, k_max=k_max, min_len=2)
