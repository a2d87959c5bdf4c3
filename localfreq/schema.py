"""The data model: fixed schemas at module boundaries.

TRANSACTION  t, items             a set of items at an integer time; items sorted, distinct, maybe none
OCC          pattern, t           one row per occurrence; long form, so no item is ever one giant array
RUN          pattern, s, d        maximal run of dense window starts
INTERVAL     pattern, len, s, e   dense (or predicted) interval; e = d + width for dense ones
CAMPAIGN     campaign_id, kind, start_day, end_day, items
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

__all__ = ["CAMPAIGN", "INTERVAL", "OCC", "RUN", "TRANSACTION", "escape_item", "pattern_len", "pattern_text", "require"]

_L, _S = T.LongType(), T.StringType()
TRANSACTION = T.StructType([T.StructField("t", _L), T.StructField("items", T.ArrayType(_S, False))])
OCC = T.StructType([T.StructField("pattern", _S), T.StructField("t", _L)])
RUN = T.StructType([T.StructField("pattern", _S), T.StructField("s", _L), T.StructField("d", _L)])
INTERVAL = T.StructType([T.StructField("pattern", _S), T.StructField("len", T.IntegerType()), T.StructField("s", _L), T.StructField("e", _L)])
CAMPAIGN = T.StructType([T.StructField("campaign_id", T.IntegerType()), T.StructField("kind", _S), T.StructField("start_day", T.IntegerType()), T.StructField("end_day", T.IntegerType()), T.StructField("items", T.ArrayType(_S))])


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` if it has the schema's columns with their types, else a clear error. Further columns are allowed."""
    have = {f.name: f.dataType for f in df.schema.fields}
    for f in schema.fields:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing; there are {sorted(have)}")
        if have[f.name].simpleString() != f.dataType.simpleString():
            raise TypeError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df


def escape_item(item: Column) -> Column:
    """An item as it stands in a pattern's text: the separator and the escape mark are escaped."""
    return F.replace(F.replace(item, F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|"))


def pattern_text(items: Column) -> Column:
    """The text of an itemset: items in binary order, joined by ``|``."""
    return F.array_join(F.array_sort(F.transform(items, escape_item)), "|")


def pattern_len(pattern: Column) -> Column:
    """Items in a pattern's text: separators that are not escaped, and one."""
    return (F.length(F.regexp_replace(pattern, r"\\.", "")) - F.length(F.regexp_replace(F.regexp_replace(pattern, r"\\.", ""), r"\|", "")) + 1).cast("int")
