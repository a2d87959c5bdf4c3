"""Scan kernels in numpy: every position, and stride-skip, with counts of evaluated windows.

Both take one pattern's sorted times and ranges of window starts (closed), and give the runs of dense starts. The declarative
detection needs neither; the kernels are the paper-like second implementation and the measure of scan cost.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

__all__ = ["KERNELS", "keep_position", "scan_by_pattern", "scan_every", "scan_skip", "skip_positions", "skip_profile"]

_CHUNK = 1 << 20


def scan_every(times: np.ndarray, width: int, sigma: int, ranges: list[tuple[int, int]]) -> tuple[list[tuple[int, int]], int]:
    """(runs, windows) by counting the window of every start of the ranges, in vectorised chunks."""
    runs, windows = [], 0
    for lo, hi in ranges:
        open_at, at = None, lo
        while at <= hi:
            starts = np.arange(at, min(hi + 1, at + _CHUNK))
            dense = np.searchsorted(times, starts + width, "right") - np.searchsorted(times, starts, "left") >= sigma
            windows += len(starts)
            edges = np.flatnonzero(np.diff(np.concatenate([[open_at is not None], dense]).astype(np.int8)))
            for i in edges:
                if open_at is None:
                    open_at = int(starts[i])
                else:
                    runs.append((open_at, int(starts[i]) - 1))
                    open_at = None
            at += len(starts)
        if open_at is not None:
            runs.append((open_at, hi))
    return runs, windows


def keep_position(times: np.ndarray, start: int, width: int, sigma: int) -> int | None:
    """The first of the last sigma occurrences in the window at ``start``: every start up to it is dense. None for a sparse window."""
    end = int(np.searchsorted(times, start + width, "right"))
    count = end - int(np.searchsorted(times, start, "left"))
    return int(times[end - sigma]) if count >= sigma else None


def scan_skip(times: np.ndarray, width: int, sigma: int, ranges: list[tuple[int, int]]) -> tuple[list[tuple[int, int]], int]:
    """(runs, windows) by jumping: over starts known to be dense, and over starts whose windows cannot yet gain an occurrence."""
    runs, windows, n = [], 0, len(times)
    for lo, hi in ranges:
        first = int(np.searchsorted(times, lo, "left")) + sigma - 1
        if first >= n:
            continue
        at, run = max(lo, int(times[first]) - width), None
        while at <= hi:
            windows += 1
            kept = keep_position(times, at, width, sigma)
            if kept is not None:
                run = [at, kept] if run is None else [run[0], max(run[1], kept)]
                at = kept + 1
                continue
            if run is not None:
                runs.append((run[0], min(run[1], hi)))
                run = None
            upcoming = int(np.searchsorted(times, at + width, "right"))
            if upcoming >= n:
                break
            at = max(at + 1, int(times[upcoming]) - width)
        if run is not None:
            runs.append((run[0], min(run[1], hi)))
    return runs, windows


KERNELS = {"every": scan_every, "skip": scan_skip}


def scan_by_pattern(occ: DataFrame, width: int, sigma: int, *, t_max: int, kernel: str = "skip", ranges: DataFrame | None = None) -> DataFrame:
    """(pattern, s, d, windows) by a kernel per pattern; a row without run (s null) carries the windows of patterns that have none.

    ``ranges`` (pattern, s, e) restricts the scan: occurrences and ranges of a pattern meet by cogroup. A pattern's times
    must fit one worker; use ``dense_runs`` with shards for hot patterns.
    """
    scan, last = KERNELS[kernel], t_max - width

    def rows_of(name, times, spans) -> pd.DataFrame:
        runs, windows = scan(np.unique(np.asarray(times, np.int64)), width, sigma, spans)
        rows = [(name, s, d, windows if i == 0 else 0) for i, (s, d) in enumerate(runs)] or [(name, None, None, windows)]
        return pd.DataFrame(rows, columns=["pattern", "s", "d", "windows"]).astype({"s": "Int64", "d": "Int64"})

    schema = "pattern string, s long, d long, windows long"
    if ranges is None:
        spans = [(0, last)] if last >= 0 else []
        return occ.groupBy("pattern").applyInPandas(lambda g: rows_of(g["pattern"].iloc[0], g["t"], spans), schema)

    def both(key, o: pd.DataFrame, r: pd.DataFrame) -> pd.DataFrame:
        spans = sorted((max(0, int(s)), min(int(e) - width, last)) for s, e in zip(r["s"], r["e"], strict=True))
        return rows_of(key[0], o["t"], [x for x in spans if x[0] <= x[1]])

    named = ranges.select(F.col("pattern").alias("of"), "s", "e")  # a name of its own: both sides may come from one frame
    return occ.groupBy("pattern").cogroup(named.groupBy("of")).applyInPandas(both, schema)


def skip_positions(occ: DataFrame, width: int, sigma: int) -> DataFrame:
    """(pattern, t, c, keep) of occurrences that start a dense window.

    The window at occurrence i holds c occurrences; the scan may go on after the first of the last sigma, which is c - sigma places on.
    """
    from pyspark.sql.window import Window

    by = Window.partitionBy("pattern").orderBy("t")
    count = F.count(F.lit(1)).over(by.rangeBetween(0, width))
    curve = occ.select("pattern", "t", F.row_number().over(by).alias("i"), count.alias("c"))
    dense = curve.where(F.col("c") >= sigma).withColumn("j", F.col("i") + F.col("c") - sigma)
    kept = curve.select("pattern", F.col("i").alias("j"), F.col("t").alias("keep"))
    return dense.join(kept, ["pattern", "j"]).select("pattern", "t", "c", "keep")


def skip_profile(occ: DataFrame, width: int, sigma: int) -> DataFrame:
    """(pattern, n_dense, mean_surplus, mean_stride) over occurrences that start a dense window."""
    joined = skip_positions(occ, width, sigma)
    return joined.groupBy("pattern").agg(F.count(F.lit(1)).alias("n_dense"), F.round(F.avg(F.col("c") - sigma), 6).alias("mean_surplus"), F.round(F.avg(F.col("keep") + 1 - F.col("t")), 6).alias("mean_stride"))
