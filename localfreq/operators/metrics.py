"""Accuracy of predicted patterns and intervals against a reference; with keys, one row per setting in one plan."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localfreq.operators.intervals import overlap_table

__all__ = ["interval_scores", "pattern_f1", "score"]


def _names(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.select(*keys, "pattern").distinct()


def pattern_f1(pred: DataFrame, ref: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, n_pred, n_ref, n_common, f1, precision, recall) on sets of patterns; an empty side counts 0, both empty give 1."""
    keys = keys or []
    p, r = _names(pred, keys), _names(ref, keys)
    both = p.withColumn("p", F.lit(1)).join(r.withColumn("r", F.lit(1)), [*keys, "pattern"], "full_outer")
    n_pred, n_ref, n_common = F.count("p"), F.count("r"), F.count(F.when(F.col("p").isNotNull() & F.col("r").isNotNull(), 1))
    ratio = lambda x, y: F.round(F.when(y > 0, x / y).otherwise(F.lit(0.0)), 6)
    f1 = F.round(F.when(n_pred + n_ref > 0, 2 * n_common / (n_pred + n_ref)).otherwise(F.lit(1.0)), 6)
    return both.groupBy(*keys).agg(n_pred.alias("n_pred"), n_ref.alias("n_ref"), n_common.alias("n_common"), f1.alias("f1"), ratio(n_common, n_pred).alias("precision"), ratio(n_common, n_ref).alias("recall"))


def interval_scores(pred: DataFrame, ref: DataFrame, keys: list[str] | None = None, *, measure: str = "length") -> DataFrame:
    """(keys, jaccard, tp): mean Jaccard over all reference patterns, mean temporal precision over the common ones.

    One sweep per (keys, pattern) gives overlap, union and predicted coverage. 0 / 0 counts 0.
    """
    keys = keys or []
    table = overlap_table(pred.select(*keys, "pattern", "s", "e"), ref.select(*keys, "pattern", "s", "e"), [*keys, "pattern"], measure=measure)
    named = table.join(_names(ref, keys).withColumn("r", F.lit(1)), [*keys, "pattern"], "left").join(_names(pred, keys).withColumn("p", F.lit(1)), [*keys, "pattern"], "left")
    share = lambda x, y: F.when(F.col(y) > 0, F.col(x) / F.col(y)).otherwise(F.lit(0.0))
    jaccard = F.avg(F.when(F.col("r") == 1, share("inter", "uni")))
    tp = F.avg(F.when((F.col("r") == 1) & (F.col("p") == 1), share("inter", "len_a")))
    return named.groupBy(*keys).agg(F.round(jaccard, 6).alias("jaccard"), F.round(tp, 6).alias("tp"))


def score(pred: DataFrame, ref: DataFrame, keys: list[str] | None = None, *, intervals: bool = True, measure: str = "length") -> DataFrame:
    """Scorecard: f1, precision, recall, and jaccard and tp for methods that give intervals."""
    keys = keys or []
    f1 = pattern_f1(pred, ref, keys)
    if not intervals:
        return f1.withColumns({"jaccard": F.lit(None).cast("double"), "tp": F.lit(None).cast("double")})
    scores = interval_scores(pred, ref, keys, measure=measure)
    return f1.join(scores, keys, "left") if keys else f1.join(F.broadcast(scores), how="cross")
