"""Parameter grids, evaluated in one plan per method: the universe of patterns once, settings as rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.plans.baselines import gap_stats, short_gaps
from localfreq.session import checkpointed

__all__ = ["best", "f1_by_setting", "grid_gap_local", "grid_partial", "grid_periodic", "grid_recurring", "grid_surplus_local", "values"]


def values(df: DataFrame, name: str, low: int, high: int, step: int) -> DataFrame:
    """A grid axis as rows, made by the engine."""
    return df.sparkSession.range(low, high + 1, step).select(F.col("id").cast("long").alias(name))


def f1_by_setting(counts: DataFrame, n_ref: int) -> DataFrame:
    """Adds f1 to (…, n_pred, n_common); settings without predictions are not listed."""
    return counts.withColumn("f1", F.round(2 * F.col("n_common") / (F.col("n_pred") + F.lit(n_ref)), 6))


def best(rows: DataFrame, params: list[str]) -> DataFrame:
    """The first row by f1, then Jaccard where there is one, then smallest parameters: a top-1 that every task reduces first."""
    order = [F.desc("f1"), *([F.desc_nulls_last("jaccard")] if "jaccard" in rows.columns else []), *params]
    return rows.orderBy(*order).limit(1)


def _marked(stats: DataFrame, ref: DataFrame) -> DataFrame:
    names = ref.select("pattern").distinct().withColumn("hit", F.lit(1))
    return stats.join(names, "pattern", "left").withColumn("hit", F.coalesce("hit", F.lit(0)))


def grid_periodic(occ: DataFrame, ref: DataFrame, t_max: int, min_sup: int, high: int, step: int = 5) -> DataFrame:
    """(max_per, n_pred, n_common, f1). A pattern counts from its largest gap on, so the whole grid is one running sum over grid points."""
    stats = gap_stats(occ, t_max).where(F.col("sup") >= min_sup)
    first = F.greatest(F.lit(step), F.ceil(F.col("max_gap") / step) * step).cast("long")
    added = _marked(stats, ref).groupBy(first.alias("max_per")).agg(F.count(F.lit(1)).alias("n"), F.sum("hit").alias("h"))
    axis = values(occ, "max_per", step, high, step).join(added, "max_per", "left")
    by = Window.orderBy("max_per").rowsBetween(Window.unboundedPreceding, 0)  # over grid points, whose number is fixed
    sums = axis.select("max_per", F.sum(F.coalesce("n", F.lit(0))).over(by).alias("n_pred"), F.sum(F.coalesce("h", F.lit(0))).over(by).alias("n_common"))
    return f1_by_setting(sums.where("n_pred > 0"), ref.select("pattern").distinct().count())


def grid_partial(occ: DataFrame, ref: DataFrame, t_max: int, min_sup: int, high: int, step: int = 5) -> DataFrame:
    """(max_per, min_pr, n_pred, n_common, f1), min_pr in steps of 5 per cent."""
    spread = occ.crossJoin(F.broadcast(values(occ, "max_per", step, high, step)))
    stats = short_gaps(spread, F.col("max_per"), t_max, keys=("max_per", "pattern")).where(F.col("sup") >= min_sup)
    reach = F.floor(F.col("short") * 100 / (F.col("sup") + 1) / 5) * 5
    exact = F.least(F.lit(95), reach).cast("long")
    marked = _marked(stats, ref).withColumn("min_pr", F.explode(F.when(exact >= 5, F.sequence(F.lit(5).cast("long"), exact, F.lit(5).cast("long"))).otherwise(F.array().cast("array<bigint>"))))
    counts = marked.groupBy("max_per", "min_pr").agg(F.count(F.lit(1)).alias("n_pred"), F.sum("hit").cast("long").alias("n_common"))
    return f1_by_setting(counts, ref.select("pattern").distinct().count())


def _merged(s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of intervals, as sorted intervals that do not touch."""
    order = np.argsort(s, kind="stable")
    s, e = s[order], np.maximum.accumulate(e[order]) if len(e) else e
    new = np.concatenate([[True], s[1:] > e[:-1]]) if len(s) else np.zeros(0, bool)
    return s[new], e[np.concatenate([new[1:], [True]])] if len(s) else e


class _Reference:
    """One pattern's reference intervals: their length in all, and what they cover of others."""

    def __init__(self, s: np.ndarray, e: np.ndarray):
        self.known = len(s) > 0
        self.s, self.e = _merged(s, e)
        self.sums = np.concatenate([[0], np.cumsum(self.e - self.s)])
        self.length = int(self.sums[-1])

    def _upto(self, x: np.ndarray) -> np.ndarray:
        k = np.searchsorted(self.s, x, "right")
        return self.sums[k] - np.where(k > 0, np.maximum(0, self.e[k - 1] - x), 0) if self.length else np.zeros(len(x), np.int64)

    def inside(self, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        """Length of each interval's part that the reference covers."""
        return self._upto(e) - self._upto(s)

    def scores(self, inter: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Jaccard and temporal precision by setting, from overlaps and predicted lengths of intervals that do not overlap; 0 / 0 counts 0."""
        union = length + self.length - inter
        return np.where(union > 0, inter / np.maximum(union, 1), 0.0), np.where(length > 0, inter / np.maximum(length, 1), 0.0)


def _per_pattern(occ: DataFrame, ref: DataFrame, f, schema: str) -> DataFrame:
    """``f(times, ordinals or None, reference)`` of each pattern: arrays in the schema's order. A pattern's times and reference must fit one worker."""
    fields = [x.split() for x in schema.split(", ")]
    types = {"long": pa.int64(), "double": pa.float64(), "string": pa.string(), "int": pa.int32()}
    ranked = "ord" in occ.columns

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return pa.table({name: pa.array([], types[t]) for name, t in fields})
        times, first = np.unique(left.column("t").to_numpy(), return_index=True)
        at = left.column("ord").to_numpy()[first] if ranked else None
        found = f(times, at, _Reference(right.column("s").to_numpy(), right.column("e").to_numpy()))
        pattern = left.column("pattern")[0].as_py()
        n = len(found[0])
        columns = [pa.array([pattern] * n, pa.string()) if name == "pattern" else None for name, _ in fields]
        rest = iter(found)
        return pa.table({name: c if c is not None else pa.array(next(rest), types[t]) for (name, t), c in zip(fields, columns, strict=True)})

    a = occ.select("pattern", "t", *(["ord"] if ranked else []))
    return a.groupBy("pattern").cogroup(ref.select("pattern", "s", "e").groupBy("pattern")).applyInArrow(run, schema)


def _gap_runs(times: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """First and last places of the runs of sorted times whose gaps are at most ``limit``."""
    breaks = np.flatnonzero(np.diff(times) > limit)
    return np.concatenate([[0], breaks + 1]), np.concatenate([breaks, [len(times) - 1]])


def _means(n_ref: int) -> list:
    """Columns jaccard (over all reference patterns) and tp (over the common ones) of a grouping of rows (jac, tp) of common patterns."""
    jaccard = F.round(F.coalesce(F.sum("jac"), F.lit(0.0)) / F.lit(n_ref), 6) if n_ref else F.lit(None).cast("double")
    return [jaccard.alias("jaccard"), F.round(F.avg("tp"), 6).alias("tp")]


def grid_recurring(occ: DataFrame, ref: DataFrame, min_ps: int, high: int, step: int = 5) -> DataFrame:
    """(max_per, n_pred, n_common, f1, jaccard, tp). One pass over a pattern's times scores it for all settings, so neither occurrences nor runs are copied per setting."""
    n_ref = ref.select("pattern").distinct().count()

    def scored(times: np.ndarray, _, known: _Reference) -> tuple:
        rows = []
        for limit in range(step, high + 1, step):
            i, j = _gap_runs(times, limit)
            full = j - i + 1 >= min_ps
            if full.any():
                s, e = times[i[full]], times[j[full]]
                (jac,), (tp,) = known.scores(known.inside(s, e).sum(keepdims=True), (e - s).sum(keepdims=True))
                rows.append((limit, int(known.known), jac if known.known else None, tp if known.known else None))
        return tuple(zip(*rows, strict=True)) if rows else ((), (), (), ())

    found = _per_pattern(occ, ref, scored, "max_per long, hit int, jac double, tp double")
    sums = found.groupBy("max_per").agg(F.count(F.lit(1)).alias("n_pred"), F.sum("hit").cast("long").alias("n_common"), *_means(n_ref))
    return f1_by_setting(sums, n_ref).select("max_per", "n_pred", "n_common", "f1", "jaccard", "tp")


def _top(rows: DataFrame) -> DataFrame:
    """The settings that share the highest F1: at most as many rows as the grid has."""
    return rows.join(F.broadcast(rows.agg(F.max("f1").alias("f1"))), "f1", "left_semi")


def _counted(longest: DataFrame, ref: DataFrame, params: list[str], axis: str, low: int, high: int, step: int, grid: DataFrame) -> DataFrame:
    """(params, axis, n_pred, n_common, f1): a pattern counts at all durations up to its longest interval ``d``, so one running sum from
    the largest duration down gives the whole axis. ``grid`` holds all settings of the other parameters.
    """
    reach = F.least(F.lit(high), F.lit(low) + F.floor((F.col("d") - low) / F.lit(step)) * step).cast("long")
    added = _marked(longest.where(F.col("d") >= low), ref).groupBy(*params, reach.alias(axis)).agg(F.count(F.lit(1)).alias("n"), F.sum("hit").alias("h"))
    cells = grid.crossJoin(F.broadcast(values(longest, axis, low, high, step))).join(added, [*params, axis], "left")
    by = Window.partitionBy(*params).orderBy(F.desc(axis)).rowsBetween(Window.unboundedPreceding, 0)  # over grid points
    sums = cells.select(*params, axis, F.sum(F.coalesce("n", F.lit(0))).over(by).cast("long").alias("n_pred"), F.sum(F.coalesce("h", F.lit(0))).over(by).cast("long").alias("n_common"))
    return f1_by_setting(sums.where("n_pred > 0"), ref.select("pattern").distinct().count())


def _score_top(occ: DataFrame, ref: DataFrame, rows: DataFrame, two: list[str], axis: str, collect) -> DataFrame:
    """The settings of the highest F1 with Jaccard and temporal precision.

    ``collect(times, ordinals, reference, pairs, low)`` gives, for settings of the parameters ``two``, (setting, duration, overlap) of the intervals of
    one pattern, at least ``low`` long. They count at all durations up to their own, so sums from the longest down serve the whole axis.
    """
    top = checkpointed(_top(rows))
    wanted = top.groupBy(*two).agg(F.sort_array(F.collect_set(axis)).alias("d")).orderBy(*two).collect()  # at most the grid's size
    pairs = np.array([[r[x] for x in two] for r in wanted], np.int64).reshape(-1, 2)
    axes = [np.array(r["d"], np.int64) for r in wanted]
    low = np.array([a[0] for a in axes], np.int64)
    n_ref = ref.select("pattern").distinct().count()

    def scored(times: np.ndarray, at: np.ndarray | None, known: _Reference) -> tuple:
        empty = tuple(np.zeros(0) for _ in range(5))
        if not known.known or not len(pairs):
            return empty
        sizes = np.array([len(a) for a in axes])
        base = np.cumsum(sizes) - sizes
        length, inter = np.zeros(sizes.sum(), np.int64), np.zeros(sizes.sum(), np.int64)
        flat, owner = np.concatenate(axes), np.repeat(np.arange(len(axes)), sizes)
        span = int(max(flat.max(), times[-1] - times[0])) + 1
        keys = owner * span + flat  # grows along settings and durations
        for which, d, o in collect(times, at, known, pairs, low):
            place = np.searchsorted(keys, which * span + d, "right") - 1
            np.add.at(length, place, d)
            np.add.at(inter, place, o)
        if not length.any():
            return empty
        for sums in (length, inter):  # from the longest duration down, setting by setting
            total = np.cumsum(sums[::-1])[::-1]
            after = np.append(total, 0)[base + sizes]
            sums[:] = total - after[owner]
        kept = length > 0
        jac, tp = known.scores(inter[kept], length[kept])
        return pairs[owner[kept], 0], pairs[owner[kept], 1], flat[kept], jac, tp

    found = _per_pattern(occ, ref, scored, f"{two[0]} long, {two[1]} long, {axis} long, jac double, tp double")
    sums = found.groupBy(*two, axis).agg(F.sum("jac").alias("jac"), F.avg("tp").alias("tp"))
    mean = F.round(F.coalesce("jac", F.lit(0.0)) / F.lit(n_ref), 6) if n_ref else F.lit(None).cast("double")
    return top.join(sums, [*two, axis], "left").select(*rows.columns, mean.alias("jaccard"), F.round("tp", 6).alias("tp"))


def grid_gap_local(occ: DataFrame, ref: DataFrame, ordinals: DataFrame | None, sups: list[int], gaps: tuple[int, int, int], durs: tuple[int, int, int]) -> tuple[DataFrame, DataFrame]:
    """(all, top): F1 of every (local_sup, max_gap, min_dur), and the settings of the highest F1 with Jaccard and temporal precision.

    One pass over a pattern's times makes its sessions for all gaps; what leaves a worker is a longest session or a score by setting. Without
    ``ordinals`` (t, ord) times are ranks without holes.
    """
    occ = occ.select("pattern", "t") if ordinals is None else occ.select("pattern", "t").join(ordinals, "t")
    limits = range(gaps[0], gaps[1] + 1, gaps[2])

    def sessions(times: np.ndarray, at: np.ndarray | None, limit: int, low: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        i, j = _gap_runs(times, limit)
        long = times[j] - times[i] >= low
        i, j = i[long], j[long]
        places = times if at is None else at
        return times[i], times[j], j - i + 1, places[j] - places[i] + 1

    def longest(times: np.ndarray, at: np.ndarray | None, _: _Reference) -> tuple:
        rows = []
        for limit in limits:
            s, e, n, n_tx = sessions(times, at, limit, durs[0])
            for x in sups:
                full = n * 100 >= x * n_tx
                if full.any():
                    rows.append((x, limit, int((e - s)[full].max())))
        return tuple(zip(*rows, strict=True)) if rows else ((), (), ())

    def collect(times: np.ndarray, at: np.ndarray | None, known: _Reference, pairs: np.ndarray, low: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for limit in np.unique(pairs[:, 1]).tolist():
            mine = np.flatnonzero(pairs[:, 1] == limit)
            s, e, n, n_tx = sessions(times, at, limit, int(low[mine].min()))
            d, o = e - s, known.inside(s, e)
            for k in mine.tolist():
                full = (n * 100 >= pairs[k, 0] * n_tx) & (d >= low[k])
                yield np.full(int(full.sum()), k), d[full], o[full]

    found = _per_pattern(occ, ref, longest, "local_sup long, max_gap long, pattern string, d long")
    grid = values(occ, "max_gap", *gaps).withColumn("local_sup", F.explode(F.array(*(F.lit(x).cast("long") for x in sups))))
    params = ["local_sup", "max_gap", "min_dur"]
    rows = checkpointed(_counted(checkpointed(found), ref, params[:2], "min_dur", *durs, grid))
    return rows, _score_top(occ, ref, rows, params[:2], "min_dur", collect)


def _surplus_intervals(times: np.ndarray, per: np.ndarray, so: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
    """(settings, starts, end) as intervals of sorted times close, for all settings (per, so) at once.

    An interval opens at the first of two occurrences at most ``per`` apart and closes at the last one before the summed surplus of gaps passes ``so``.
    """
    start, surplus, inside = np.full(len(per), -1, np.int64), np.zeros(len(per), np.int64), np.zeros(len(per), bool)
    over, ends = np.empty_like(surplus), np.empty_like(inside)
    widest = int(per.max()) if len(per) else -1
    for before, t in zip(times[:-1].tolist(), times[1:].tolist(), strict=True):
        gap = t - before
        fresh = ~inside & (per >= gap) if gap <= widest else None
        np.subtract(gap, per, out=over)
        surplus += over  # of settings without an open interval it is not read
        np.maximum(surplus, 0, out=surplus)
        np.greater(surplus, so, out=ends)
        ends &= inside
        if ends.any():
            at = np.flatnonzero(ends)
            yield at, start[at], before
            start[at], inside[at] = -1, False
        if fresh is not None:
            start[fresh], surplus[fresh] = before, 0
            inside |= fresh
    at = np.flatnonzero(start >= 0)
    if len(at):
        yield at, start[at], int(times[-1])


def grid_surplus_local(occ: DataFrame, ref: DataFrame, pers: tuple[int, int, int], durs: tuple[int, int, int], sos: tuple[int, int, int]) -> tuple[DataFrame, DataFrame]:
    """(all, top) for every (max_per, min_dur, max_so_per), as ``grid_gap_local``.

    One pass over a pattern's times moves the states of all (max_per, max_so_per) together. A pattern's times must fit one worker.
    """
    axis = lambda x: np.arange(x[0], x[1] + 1, x[2])
    per, so = (x.ravel().astype(np.int64) for x in np.meshgrid(axis(pers), axis(sos), indexing="ij"))

    def longest(times: np.ndarray, _, __: _Reference) -> tuple:
        d = np.full(len(per), -1, np.int64)
        for at, start, end in _surplus_intervals(times, per, so):
            d[at] = np.maximum(d[at], end - start)
        kept = d >= durs[0]
        return per[kept], so[kept], d[kept]

    def collect(times: np.ndarray, _, known: _Reference, pairs: np.ndarray, low: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        held, n = [], 0

        def given() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            which, s, e = (np.concatenate(x) for x in zip(*held, strict=True))
            return which, e - s, known.inside(s, e)

        for at, start, end in _surplus_intervals(times, pairs[:, 0], pairs[:, 1]):
            long = end - start >= low[at]
            if long.any():
                held.append((at[long], start[long], np.full(int(long.sum()), end)))
                n += len(held[-1][0])
                if n > 1 << 18:
                    yield given()
                    held, n = [], 0
        if held:
            yield given()

    params, two = ["max_per", "min_dur", "max_so_per"], ["max_per", "max_so_per"]
    found = _per_pattern(occ, ref, longest, "max_per long, max_so_per long, pattern string, d long")
    grid = values(occ, "max_per", *pers).crossJoin(F.broadcast(values(occ, "max_so_per", *sos)))
    rows = checkpointed(_counted(checkpointed(found), ref, two, "min_dur", *durs, grid))
    return rows, _score_top(occ, ref, rows, two, "min_dur", collect).select(*params, "n_pred", "n_common", "f1", "jaccard", "tp")
