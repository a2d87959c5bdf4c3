"""Functions for SQL users: an Arrow UDF, a grouped-aggregate UDF, and a table function; and their registration."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from localfreq.operators.kernels import scan_skip

__all__ = ["DenseIntervalsOf", "dense_run_count", "peak_support", "register"]


@F.pandas_udf(LongType())
def dense_run_count(times: pd.Series, width: pd.Series, sigma: pd.Series, t_max: pd.Series) -> pd.Series:
    """Dense intervals in each row's array of times."""
    def one(t, w, s, m) -> int:
        if t is None or m < w:
            return 0
        return len(scan_skip(np.unique(np.asarray(t, np.int64)), int(w), int(s), [(0, int(m - w))])[0])

    return pd.Series([one(*x) for x in zip(times, width, sigma, t_max, strict=True)], dtype="int64")


@F.pandas_udf(LongType())
def peak_support(t: pd.Series, width: pd.Series) -> int:
    """Largest number of a group's times in a closed window of the width."""
    x = np.sort(t.to_numpy())
    return int((np.searchsorted(x, x + width.iloc[0], "right") - np.arange(len(x))).max()) if len(x) else 0


class DenseIntervalsOf:
    """Table function: the dense intervals (s, e) of an array of times."""

    def eval(self, times: list, width: int, sigma: int, t_max: int) -> Iterator[tuple[int, int]]:
        if times and t_max >= width:
            runs, _ = scan_skip(np.unique(np.asarray(times, np.int64)), width, sigma, [(0, t_max - width)])
            for s, d in runs:
                yield s, d + width


def register(spark: SparkSession) -> None:
    """Makes dense_run_count, peak_support and dense_intervals_of known to SQL."""
    spark.udf.register("dense_run_count", dense_run_count)
    spark.udf.register("peak_support", peak_support)
    spark.udtf.register("dense_intervals_of", F.udtf(DenseIntervalsOf, returnType="s: bigint, e: bigint"))
