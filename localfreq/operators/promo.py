"""Dense intervals against promotion campaigns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators.candidates import items_of
from localfreq.operators.intervals import coverage, merge_intervals, sweep
from localfreq.operators.timeline import slot_day

__all__ = ["campaign_profile", "campaigns", "campaigns_per_interval", "compare_windows", "discount_campaigns", "in_days", "overlap_distribution", "pattern_days", "promo_examples", "promo_overlap_ratio", "window_summary"]


def campaigns(spark: SparkSession) -> DataFrame:
    """CAMPAIGN rows by a fixed rule: 30 campaigns of kinds A, B and C, of 32 to 161 days, each over five brands."""
    c = spark.range(1, 31).select(F.col("id").cast("int").alias("campaign_id"))
    dur = F.when(F.col("campaign_id") == 15, 161).when(F.col("campaign_id") == 30, 96).otherwise(32 + 3 * (F.col("campaign_id") % 8))
    kind = F.element_at(F.array(F.lit("A"), F.lit("B"), F.lit("C")), F.col("campaign_id") % 3 + 1)
    start = (F.col("campaign_id") * 79) % 2240
    brands = F.transform(F.filter(F.sequence(F.lit(1), F.lit(25)), lambda b: (b + F.col("campaign_id")) % 5 == 0), lambda b: F.concat(F.lit("Brand#"), b.cast("string")))
    return c.select("campaign_id", kind.alias("kind"), start.cast("int").alias("start_day"), (start + dur).cast("int").alias("end_day"), brands.alias("items"))


def discount_campaigns(lines: DataFrame, parts: DataFrame, day_zero: str) -> DataFrame:
    """(campaign_id, kind, start_day, end_day): a campaign per part, from the first to the last day on which a line of it is shipped at a discount; its kind is the part's type."""
    day = F.datediff("l_shipdate", F.lit(day_zero).cast("date"))
    spans = lines.where("l_discount > 0").groupBy("l_partkey").agg(F.min(day).alias("start_day"), F.max(day).alias("end_day"))
    return spans.join(parts, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_partkey").alias("campaign_id"), F.col("p_type").alias("kind"), "start_day", "end_day")


def in_days(res: DataFrame, slots: int = 1000) -> DataFrame:
    """INTERVAL on day slots as whole days; intervals of one pattern that become equal stay apart by number."""
    return res.select("pattern", "len", slot_day(F.col("s"), slots).alias("s"), slot_day(F.col("e"), slots).alias("e"), F.col("s").alias("slot_s"))


def _promoted(res: DataFrame, camps: DataFrame) -> DataFrame:
    """(pattern, campaign_id, s, e): campaigns of each pattern's items."""
    rows = camps.select("campaign_id", F.col("start_day").cast("long").alias("s"), F.col("end_day").cast("long").alias("e"), F.explode("items").alias("item"))
    items = res.select("pattern").distinct().select("pattern", F.explode(items_of(F.col("pattern"))).alias("item"))
    return items.join(rows, "item").select("pattern", "campaign_id", "s", "e").distinct()


def promo_overlap_ratio(res: DataFrame, camps: DataFrame) -> DataFrame:
    """(pattern, ratio): days of the pattern's intervals inside the union of its items' campaigns, over all days of its intervals.

    Intervals are added up one by one, so overlapping intervals count as often as they are listed: a sweep counts how many
    intervals cover each piece.
    """
    union = merge_intervals(_promoted(res, camps), ["pattern"])
    pieces = sweep(res.select("pattern", "s", "e"), union, ["pattern"]).withColumn("d", (F.col("e") - F.col("s")) * F.col("in_a"))
    inside = F.coalesce(F.sum(F.when(F.col("in_b") > 0, F.col("d"))), F.lit(0))
    total = F.sum("d")
    return pieces.where("in_a > 0").groupBy("pattern").agg(F.round(F.when(total > 0, inside / total).otherwise(F.lit(0.0)), 6).alias("ratio"))


def campaigns_per_interval(res: DataFrame, camps: DataFrame, *, bucket: int = 64) -> DataFrame:
    """(pattern, s, e, n): campaigns of the pattern's items that share more than a point with the interval."""
    from localfreq.operators.intervals import count_overlaps

    return count_overlaps(res, _promoted(res, camps), ["pattern"], b_id="campaign_id", bucket=bucket)


def overlap_distribution(counts: DataFrame) -> DataFrame:
    """One row: intervals, share with at most one and with two campaigns or more, mean."""
    share = lambda c: F.round(F.avg(F.when(c, 1.0).otherwise(0.0)), 6)
    return counts.agg(F.count(F.lit(1)).alias("n_intervals"), share(F.col("n") <= 1).alias("share_le1"), share(F.col("n") >= 2).alias("share_ge2"), F.round(F.avg("n"), 6).alias("mean_campaigns"))


def window_summary(res: DataFrame) -> DataFrame:
    """One row: patterns, intervals a pattern, mean length over intervals and over patterns."""
    per = res.groupBy("pattern").agg(F.count(F.lit(1)).alias("k"), F.avg(F.col("e") - F.col("s")).alias("mean"), F.sum(F.col("e") - F.col("s")).alias("total"))
    return per.agg(F.count(F.lit(1)).alias("n_patterns"), F.round(F.avg("k"), 6).alias("intervals_per_pattern"), F.round(F.sum("total") / F.sum("k"), 6).alias("mean_len_intervals"), F.round(F.avg("mean"), 6).alias("mean_len_patterns"))


def compare_windows(narrow: DataFrame, wide: DataFrame, ratios: DataFrame) -> DataFrame:
    """(part, n_patterns, mean_ratio): patterns only of the narrow window, and common ones; ratios are (pattern, ratio) of the narrow one."""
    a, b = narrow.select("pattern").distinct(), wide.select("pattern").distinct()
    marked = a.join(b.withColumn("w", F.lit(1)), "pattern", "left").join(ratios, "pattern", "left")
    part = F.when(F.col("w").isNull(), "only_narrow").otherwise("common")
    return marked.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n_patterns"), F.round(F.avg("ratio"), 6).alias("mean_ratio"))


def pattern_days(res: DataFrame) -> DataFrame:
    """(pattern, covered): days of the union of the pattern's intervals."""
    return coverage(res, ["pattern"])


def promo_examples(ratios: DataFrame, n: int) -> DataFrame:
    """(side, rank, pattern, ratio): the n patterns of highest and of lowest ratio, ties by text."""
    from pyspark.sql.window import Window

    def ranked(side: str, order) -> DataFrame:
        top = ratios.orderBy(order, "pattern").limit(n)
        by = Window.orderBy(order, "pattern")  # over n rows
        return top.select(F.lit(side).alias("side"), F.row_number().over(by).alias("rank"), "pattern", "ratio")

    return ranked("high", F.desc("ratio")).unionByName(ranked("low", F.asc("ratio")))


def campaign_profile(camps: DataFrame) -> DataFrame:
    """(kind, n, min_days, max_days, mean_days)."""
    d = F.col("end_day") - F.col("start_day")
    return camps.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.min(d).cast("long").alias("min_days"), F.max(d).cast("long").alias("max_days"), F.round(F.avg(d), 6).alias("mean_days"))
