"""The given tables, read with only the columns that are asked for, and the item views made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators.baskets import occurrences_from_rows
from localfreq.operators.timeline import bucket_timeline, rank_timeline
from localfreq.session import broadcasts, dealt

__all__ = ["DAY_ZERO", "event_occurrences", "item_column", "line_items", "order_days", "order_ranks", "order_rows", "occurrences", "table", "token_rows", "transactions"]

#: Day 0 of the day timeline.
DAY_ZERO = "1995-01-01"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def order_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, t): every order's place by date and key, from 1; orders without lines count."""
    return rank_timeline(table(spark, sf_dir, "orders", "o_orderkey", "o_orderdate"), ["o_orderdate", "o_orderkey"]).select("o_orderkey", "t")


def order_days(spark: SparkSession, sf_dir: str, slots: int = 1000, *, rows: int | None = None) -> DataFrame:
    """(o_orderkey, t) on day slots; orders of a day that has more than ``slots`` share some. ``rows``, the number of orders, has them dealt by it."""
    from localfreq.operators.timeline import day_slot_timeline

    days = table(spark, sf_dir, "orders", "o_orderkey", "o_orderdate").withColumn("day", F.datediff("o_orderdate", F.lit(DAY_ZERO).cast("date")))
    return day_slot_timeline(days if rows is None else dealt(days, rows, "day"), "day", ["o_orderkey"], slots=slots, shared=True).select("o_orderkey", "t")


#: view -> item expression over lineitem and part
_ITEMS: dict[str, str] = {"brand": "p_brand", "type": "p_type", "brandtype": "concat(p_brand, p_type)", "supp": "cast(l_suppkey as string)", "pname": "p_name"}


def item_column(view: str) -> Column:
    return F.expr(_ITEMS[view])


def line_items(spark: SparkSession, sf_dir: str, view: str, *, rows: int | None = None) -> DataFrame:
    """(l_orderkey, item) rows of an item view. ``part`` is joined only where the view needs it. ``rows``, the number of lines, has them dealt by it where both sides are sorted."""
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    if view != "supp":
        parts = table(spark, sf_dir, "part", "p_partkey", "p_brand", "p_type", "p_name")
        lines = lines if rows is None or broadcasts(parts) else dealt(lines, rows, "l_partkey")
        lines = lines.join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return lines.select("l_orderkey", item_column(view).alias("item"))


def order_rows(spark: SparkSession, sf_dir: str, view: str, times: DataFrame) -> DataFrame:
    """(t, item) rows of an item view."""
    return line_items(spark, sf_dir, view).join(times, F.col("l_orderkey") == F.col("o_orderkey")).select("t", "item")


def occurrences(spark: SparkSession, sf_dir: str, view: str, *, days: bool = False) -> tuple[DataFrame, int]:
    """(OCC of single items, last time) of an item view over orders; the last time is that of all orders."""
    times = order_days(spark, sf_dir) if days else order_ranks(spark, sf_dir)
    t_max = times.agg(F.max("t")).first()[0]
    return occurrences_from_rows(order_rows(spark, sf_dir, view, times), "t", "item"), t_max if t_max is not None else -1


def transactions(spark: SparkSession, sf_dir: str, view: str, *, days: bool = False) -> DataFrame:
    """TRANSACTION of an item view over orders; orders without lines are empty transactions, orders that share a slot one."""
    if days:
        return _day_transactions(spark, sf_dir, view)
    times = order_ranks(spark, sf_dir)
    sets = order_rows(spark, sf_dir, view, times).groupBy("t").agg(F.array_sort(F.collect_set("item")).alias("items"))
    return times.select("t").join(sets, "t", "left").select("t", F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def _day_transactions(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    """One pass over orders and lines, each step over pieces of a bounded number of rows; orders without a time make one empty transaction."""
    orders, lines = (table(spark, sf_dir, name).count() for name in ("orders", "lineitem"))
    times = order_days(spark, sf_dir, rows=orders)
    items = dealt(line_items(spark, sf_dir, view, rows=lines), lines, "l_orderkey")
    rows = times.join(items, F.col("l_orderkey") == F.col("o_orderkey"), "left").select("t", F.when(F.col("t").isNotNull(), F.col("item")).alias("item"))
    return dealt(rows, orders + lines, "t").groupBy("t").agg(F.array_sort(F.collect_set("item")).alias("items"))


def event_occurrences(spark: SparkSession, sf_dir: str, item: str, seconds: int) -> DataFrame:
    """OCC of events by bucket, from 0: equal items of one bucket are one occurrence."""
    rows = bucket_timeline(table(spark, sf_dir, "events", "ts", item), "ts", seconds)
    first = rows.agg(F.min("t").alias("m"))
    shifted = rows.join(F.broadcast(first), how="cross").withColumn("t", F.col("t") - F.col("m"))
    return occurrences_from_rows(shifted.withColumn(item, F.col(item).cast("string")), "t", item)


def token_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(t, item): lower-case words of more than three letters of each document, t = doc_id."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    words = F.explode(F.split(F.lower("text"), r"[^\p{L}]+"))
    return docs.select(F.col("doc_id").alias("t"), words.alias("item")).where(F.length("item") > 3)
