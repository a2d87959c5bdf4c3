"""Queries of baselines, accuracy measures, grids and promotions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators import detect, metrics, promo
from localfreq.operators.baskets import to_occurrences
from localfreq.plans import baselines, grid, miner, sharded
from localfreq.registry.sqltext import CAMPAIGNS, PAIRS, base, brute, islands, merged, runs
from localfreq.session import checkpointed
from localfreq.sources.tables import DAY_ZERO, occurrences, table, transactions
from localfreq.workloads import reference

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


#: All singles and pairs with their length, for definitions without pruning.
_ALL = f"{base()}, {PAIRS}, alls as (select pattern, 1 as len, t from occ union all select pattern, 2 as len, t from pairs)"


def _two(spark: SparkSession, d: str, view: str = "brand") -> tuple[DataFrame, int]:
    """(pattern, t) of all pairs of items with an occurrence, and the last time."""
    occ, t_max = occurrences(spark, d, view)
    a, b = occ.select(F.col("pattern").alias("a"), "t"), occ.select(F.col("pattern").alias("b"), "t")
    return a.join(b, "t").where("a < b").select(F.concat("a", F.lit("|"), "b").alias("pattern"), "t"), t_max


# --- baselines

@query(f"{_ALL} select pattern, count(*) as sup, len from alls group by pattern, len having count(*) >= 210")
def frequent_itemsets(spark, d):
    return baselines.mine_frequent(transactions(spark, d, "brand"), 210, k_max=2)


@query(f"{_ALL} select pattern, count(*) as sup, len from alls group by pattern, len having count(*) >= 210")
def frequent_fpgrowth(spark, d):
    return baselines.fpgrowth(transactions(spark, d, "brand"), 210, k_max=2)


_GAPS = f"{_ALL}, g as (select pattern, len, t, t - lag(t) over (partition by pattern order by t) as gap from alls), st as (select pattern, len, count(*) as sup, greatest(coalesce(max(gap), 0), min(t), max(tmax) - max(t)) as max_gap, min(t) as first, max(t) as last from g, tm group by 1, 2)"


@query(f"{_GAPS} select pattern, sup, cast(max_gap as bigint) as max_gap, first, last from st where len = 1")
def gap_stats(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    return baselines.gap_stats(occ, t_max)


@query(f"{_GAPS} select pattern, sup, cast(max_gap as bigint) as max_gap, len from st where sup >= 14 and max_gap <= 300")
def periodic_patterns(spark, d):
    return baselines.mine_periodic(transactions(spark, d, "brand"), 300, 14, k_max=2)


@query(f"{_ALL}, g as (select pattern, len, t - coalesce(lag(t) over w, 0) as gap from alls window w as (partition by pattern order by t) union all select pattern, len, max(tmax) - max(t) from alls, tm group by 1, 2), st as (select pattern, len, count(*) - 1 as sup, cast(sum(case when gap <= 55 then 1 else 0 end) as bigint) as short from g group by 1, 2) select pattern, sup, short, len from st where sup >= 14 and short * 100 >= 70 * (sup + 1)")
def partial_periodic_patterns(spark, d):
    return baselines.mine_partial_periodic(transactions(spark, d, "brand"), 55, 70, 14, k_max=2)


_RUNS = lambda gap: f"{_ALL}, {runs('r', 'alls', gap, 'pattern, len')}"


@query(f"{_RUNS(85)} select pattern, len, s, e, n as n_occ from r where e - s >= 370 and n * 100 >= 4 * (select count(*) from tx where t between s and e)")
def gap_local_patterns(spark, d):
    return baselines.mine_gap_local(transactions(spark, d, "brand"), 4, 85, 370, k_max=2)


@query(f"{_RUNS(85)} select pattern, len, s, e, n as n_occ from r where e - s >= 370 and n * 100 >= 4 * (select count(*) from tx where t between s and e)")
def gap_local_plain_pruning(spark, d):
    """Plain level-wise pruning, not complete in general; on these data it finds the same patterns."""
    return baselines.mine_gap_local(transactions(spark, d, "brand"), 4, 85, 370, k_max=2, complete=False)


def _surplus_sql(max_per: int, min_dur: int, max_so_per: int) -> str:
    """Occurrence by occurrence, as the definition reads: the open interval's start, the surplus so far, and the interval that closes here, if any."""
    over = f"greatest(0, fold.surplus + m.t - fold.t - {max_per})"
    closes = f"fold.s is not null and {over} > {max_so_per}"
    return f"""{_ALL.replace('with ', 'with recursive ', 1)}, m as materialized (select pattern, len, t, row_number() over (partition by pattern order by t) as i, count(*) over (partition by pattern) as n from alls),
 fold as (select pattern, len, i, n, t, cast(null as bigint) as s, cast(0 as bigint) as surplus, cast(null as bigint) as from_t, cast(null as bigint) as to_t from m where i = 1
  union all select m.pattern, m.len, m.i, m.n, m.t, case when fold.s is null then case when m.t - fold.t <= {max_per} then fold.t end when {closes} then null else fold.s end,
   case when fold.s is null or {closes} then 0 else {over} end, case when {closes} then fold.s end, case when {closes} then fold.t end from fold join m on m.pattern = fold.pattern and m.i = fold.i + 1),
 found as (select pattern, len, from_t as s, to_t as e from fold where from_t is not null union all select pattern, len, s, t from fold where i = n and s is not null)
 select pattern, len, s, e from found where e - s >= {min_dur}"""


@query(_surplus_sql(50, 400, 60))
def surplus_local_patterns(spark, d):
    return baselines.mine_surplus_local(transactions(spark, d, "brand"), 50, 400, 60, k_max=2)


@query(f"{_RUNS(50)}, k as (select *, count(*) over (partition by pattern) as rec from r where n >= 14) select pattern, len, s, e, n as n_occ, rec from k where rec >= 1")
def recurring_patterns(spark, d):
    return baselines.mine_recurring(transactions(spark, d, "brand"), 50, 14, k_max=2)


@query(f"{_RUNS(60)}, k as (select *, count(*) over (partition by pattern) as rec from r where n >= 8) select pattern, len, s, e, n as n_occ, rec from k where rec >= 3")
def recurring_patterns_three(spark, d):
    return baselines.mine_recurring(transactions(spark, d, "brand"), 60, 8, min_rec=3, k_max=2)


_REF = f"{base()}, {PAIRS}, {brute('ref', 'pairs', 250, 14)}"


@query(f"{_REF} select pairs.pattern, 2 as len, min(t) as s, max(t) as e from pairs where pattern in (select pattern from ref) group by 1")
def span_intervals(spark, d):
    return baselines.span_intervals(_two(spark, d)[0], reference(spark, d, "brand", 250, 14))


# --- measures: recurring against the exact reference

_PRED = f"{_REF}, {runs('rr', 'pairs', 50)}, pred as (select pattern, s, e from rr where n >= 14)"
_F1 = "f as (select (select count(distinct pattern) from pred) as n_pred, (select count(distinct pattern) from ref) as n_ref, (select count(*) from (select pattern from pred intersect select pattern from ref) q) as n_common)"
_COVER = f"{merged('mp', 'pred')}, {merged('mr', 'ref')}, ov as (select mp.pattern, sum(least(mp.e, mr.e) - greatest(mp.s, mr.s)) as inter from mp join mr on mp.pattern = mr.pattern and mp.s < mr.e and mr.s < mp.e group by 1), lp as (select pattern, sum(e - s) as len_p from mp group by 1), lr as (select pattern, sum(e - s) as len_r from mr group by 1), j as (select lr.pattern, coalesce(inter, 0) as inter, coalesce(len_p, 0) as len_p, len_r, len_p is not null as both_in from lr left join lp using (pattern) left join ov using (pattern))"
_SCORES = "s as (select round(avg(case when len_p + len_r - inter > 0 then inter / (len_p + len_r - inter) else 0.0 end), 6) as jaccard, round(avg(case when len_p > 0 then inter / len_p else 0.0 end) filter (both_in), 6) as tp from j)"
_F1_ROW = "n_pred, n_ref, n_common, round(case when n_pred + n_ref > 0 then 2 * n_common / (n_pred + n_ref) else 1.0 end, 6) as f1, round(case when n_pred > 0 then n_common / n_pred else 0.0 end, 6) as precision, round(case when n_ref > 0 then n_common / n_ref else 0.0 end, 6) as recall"


def _pred_and_ref(spark, d) -> tuple[DataFrame, DataFrame]:
    """Recurring pairs and the exact reference, from one timeline."""
    tx = checkpointed(transactions(spark, d, "brand"))
    return baselines.mine_recurring(tx, 50, 14, k_max=2).where("len = 2"), miner.mine_dense(tx, 250, 14, k_max=2, min_len=2)


@query(f"{_PRED}, {_F1} select {_F1_ROW} from f")
def metric_f1(spark, d):
    return metrics.pattern_f1(*_pred_and_ref(spark, d))


@query(f"{_PRED}, {_COVER}, {_SCORES} select jaccard from s")
def metric_jaccard(spark, d):
    return metrics.interval_scores(*_pred_and_ref(spark, d)).select("jaccard")


@query(f"{_PRED}, {_COVER}, {_SCORES} select tp from s")
def metric_temporal_precision(spark, d):
    return metrics.interval_scores(*_pred_and_ref(spark, d)).select("tp")


@query(f"{_PRED}, {_F1}, {_COVER}, {_SCORES} select {_F1_ROW}, jaccard, tp from f, s")
def scorecard(spark, d):
    return metrics.score(*_pred_and_ref(spark, d))


@query("select n as n_pred, n as n_ref, n as n_common, 1.0::double as f1, 1.0::double as precision, 1.0::double as recall, 1.0::double as jaccard, 1.0::double as tp from (" + f"{_REF} select count(distinct pattern) as n from ref" + ") q")
def exactness_scorecard(spark, d):
    """The sharded miner against the level-wise one: both exact, so every measure is 1."""
    tx = checkpointed(transactions(spark, d, "brand"))
    return metrics.score(sharded.mine_dense_sharded(tx, 250, 14, shard_width=3000, k_max=2, min_len=2), miner.mine_dense(tx, 250, 14, k_max=2, min_len=2))


_SPAN = f"{_REF}, pred as (select pattern, min(t) as s, max(t) as e from pairs where pattern in (select pattern from ref) group by 1)"


@query(f"{_SPAN}, {_COVER}, {_SCORES} select jaccard, tp from s")
def span_scores(spark, d):
    ref = reference(spark, d, "brand", 250, 14)
    return metrics.interval_scores(baselines.span_intervals(_two(spark, d)[0], ref), ref)


@query(f"{_REF}, pred as (select pattern from pairs group by 1 having count(*) >= 14), {_F1} select {_F1_ROW}, cast(null as double) as jaccard, cast(null as double) as tp from f")
def frequent_scores(spark, d):
    pred = baselines.mine_frequent(transactions(spark, d, "brand"), 14, k_max=2).where("len = 2")
    return metrics.score(pred, reference(spark, d, "brand", 250, 14), intervals=False)


# --- grids

_HIT = "hit as (select distinct pattern from ref), nr as (select count(*) as n_ref from hit)"


@query(f"{_REF}, {_HIT}, g as (select pattern, t, t - lag(t) over (partition by pattern order by t) as gap from pairs), st as (select pattern, count(*) as sup, greatest(coalesce(max(gap), 0), min(t), max(tmax) - max(t)) as max_gap from g, tm group by 1), k as (select p.max_per, count(*) as n_pred, count(hit.pattern) as n_common from (select unnest(range(5, 901, 5)) as max_per) p join st on st.max_gap <= p.max_per and st.sup >= 14 left join hit on hit.pattern = st.pattern group by 1) select max_per, n_pred, n_common, round(2 * n_common / (n_pred + n_ref), 6) as f1 from k, nr")
def grid_periodic(spark, d):
    occ, t_max = _two(spark, d)
    return grid.grid_periodic(occ, reference(spark, d, "brand", 250, 14), t_max, 14, 900).select("max_per", F.col("n_pred").cast("long").alias("n_pred"), F.col("n_common").cast("long").alias("n_common"), "f1")


@query(f"{_REF}, {_HIT}, g as (select pattern, t - coalesce(lag(t) over w, 0) as gap, 1 as o from pairs window w as (partition by pattern order by t) union all select pattern, max(tmax) - max(t), 0 from pairs, tm group by 1), st as (select p.max_per, pattern, sum(o) as sup, sum(case when gap <= p.max_per then 1 else 0 end) as short from g cross join (select unnest(range(5, 121, 5)) as max_per) p group by 1, 2 having sum(o) >= 14), k as (select max_per, q.min_pr, count(*) as n_pred, count(hit.pattern) as n_common from st join (select unnest(range(5, 96, 5)) as min_pr) q on st.short * 100 >= q.min_pr * (st.sup + 1) left join hit on hit.pattern = st.pattern group by 1, 2) select max_per, min_pr, n_pred, n_common, round(2 * n_common / (n_pred + n_ref), 6) as f1 from k, nr")
def grid_partial(spark, d):
    occ, t_max = _two(spark, d)
    return grid.grid_partial(occ, reference(spark, d, "brand", 250, 14), t_max, 14, 120)


def _grid_sql(spread: str, where: str, params: str) -> str:
    """Scores per setting of predictions (params, pattern, s, e) against the reference."""
    return f"""{_REF}, {_HIT}, {spread}, pred as (select {params}, pattern, s, e from rr where {where}),
 c as (select {params}, count(distinct pred.pattern) as n_pred, count(distinct hit.pattern) as n_common from pred left join hit on hit.pattern = pred.pattern group by all),
 {merged('mp', 'pred', f'{params}, pattern')}, {merged('mr', 'ref')},
 lp as (select {params}, pattern, sum(e - s) as len_p from mp group by all), lr as (select pattern, sum(e - s) as len_r from mr group by 1),
 ov as (select {', '.join('mp.' + x for x in params.split(', '))}, mp.pattern, sum(least(mp.e, mr.e) - greatest(mp.s, mr.s)) as inter from mp join mr on mp.pattern = mr.pattern and mp.s < mr.e and mr.s < mp.e group by all),
 j as (select {', '.join('c.' + x for x in params.split(', '))}, lr.pattern, len_r, coalesce(len_p, 0) as len_p, coalesce(inter, 0) as inter, len_p is not null as both_in from c cross join lr left join lp on {' and '.join(f'lp.{x} = c.{x}' for x in params.split(', '))} and lp.pattern = lr.pattern left join ov on {' and '.join(f'ov.{x} = c.{x}' for x in params.split(', '))} and ov.pattern = lr.pattern),
 sc as (select {params}, round(avg(case when len_p + len_r - inter > 0 then inter / (len_p + len_r - inter) else 0.0 end), 6) as jaccard, round(avg(case when len_p > 0 then inter / len_p else 0.0 end) filter (both_in), 6) as tp from j group by all),
 res as (select c.*, round(2 * n_common / (n_pred + n_ref), 6) as f1, jaccard, tp from c join sc using ({params}) cross join nr)"""


_RECUR = _grid_sql(f"sp as (select max_per, pattern, t from pairs cross join (select unnest(range(5, 251, 5)) as max_per) p), {runs('rr', 'sp', 'max_per', 'max_per, pattern')}", "n >= 14", "max_per")


def _grid_recurring(spark, d):
    return grid.grid_recurring(_two(spark, d)[0], reference(spark, d, "brand", 250, 14), 14, 250)


@query(f"{_RECUR} select max_per, n_pred, n_common, f1, jaccard, tp from res order by f1 desc, jaccard desc, max_per limit 1")
def grid_recurring(spark, d):
    return grid.best(_grid_recurring(spark, d), ["max_per"])


@query(f"{_RECUR} select max_per, f1, tp from res")
def sweep_recurring(spark, d):
    """F1 and temporal precision as the gap parameter moves: a loose gap keeps F1 and loses precision."""
    return _grid_recurring(spark, d).select("max_per", "f1", "tp")


#: Axes of the searches: 19,000 settings, and 200,000.
_LOCAL_AXES = ([1, 2, 3, 4, 5, 10, 15, 20, 25, 30], (10, 100, 5), (10, 1000, 10))
_SURPLUS_AXES = ((5, 50, 5), (5, 1000, 5), (5, 500, 5))

#: Ranks are 1, 2, ..., so a run has e - s + 1 transactions. A pattern's longest run that meets a support level tells at which durations it counts.
_LOCAL = _grid_sql(f"""sp as (select max_gap, pattern, t from pairs cross join (select unnest(range(10, 101, 5)) as max_gap) p), {runs('r0', 'sp', 'max_gap', 'max_gap, pattern')},
 rs as (select a.local_sup, max_gap, pattern, s, e from r0 join (select cast(unnest({_LOCAL_AXES[0]}) as bigint) as local_sup) a on n * 100 >= a.local_sup * (e - s + 1)),
 ld as (select local_sup, max_gap, pattern, max(e - s) as d from rs group by all),
 ct as (select local_sup, max_gap, b.min_dur, count(*) as np, count(hit.pattern) as nc from ld join (select unnest(range(10, 1001, 10)) as min_dur) b on d >= b.min_dur left join hit on hit.pattern = ld.pattern group by all),
 fs as (select *, round(2 * nc / (np + (select n_ref from nr)), 6) as f from ct), tops as (select local_sup, max_gap, min_dur from fs where f = (select max(f) from fs)),
 rr as (select local_sup, max_gap, min_dur, pattern, s, e from rs join tops using (local_sup, max_gap) where e - s >= min_dur)""", "1 = 1", "local_sup, max_gap, min_dur")


def _grid_gap_local(spark, d):
    return grid.grid_gap_local(checkpointed(_two(spark, d)[0]), reference(spark, d, "brand", 250, 14), None, *_LOCAL_AXES)


@query(f"{_LOCAL} select local_sup, max_gap, min_dur, n_pred, n_common, f1, jaccard, tp from res order by f1 desc, jaccard desc, local_sup, max_gap, min_dur limit 1")
def grid_gap_local(spark, d):
    return grid.best(_grid_gap_local(spark, d)[1], ["local_sup", "max_gap", "min_dur"])


@query(f"{_LOCAL} select max_gap, max(f) as f1 from fs group by 1")
def sweep_gap_local(spark, d):
    """Best F1 of each gap parameter over all support levels and durations."""
    return _grid_gap_local(spark, d)[0].groupBy("max_gap").agg(F.max("f1").alias("f1"))


def _grid_surplus_local(spark, d):
    return grid.grid_surplus_local(checkpointed(_two(spark, d)[0]), reference(spark, d, "brand", 250, 14), *_SURPLUS_AXES)


@query()
def grid_surplus_local(spark, d):
    return grid.best(_grid_surplus_local(spark, d)[1], ["max_per", "min_dur", "max_so_per"])


@query()
def sweep_surplus_local(spark, d):
    """Best F1 of each period over all durations and surplus limits."""
    return _grid_surplus_local(spark, d)[0].groupBy("max_per").agg(F.max("f1").alias("f1"))


# --- promotions: brands on day slots, windows of 47 and 141 days

def _five_levels(x: str, width: int, sigma: int) -> str:
    """``x``1 to ``x``5: dense intervals by length. From triples on, occurrences come from dense patterns of one item less whose pairs are dense."""
    dense = lambda k: f"(select pattern from {x}{k})"
    parts = [islands(f"{x}1", "occ", width, sigma), islands(f"{x}2", "pairs", width, sigma), f"{x}o2 as (select a.pattern || '|' || b.pattern as pattern, a.t, b.pattern as last from occ a join occ b on a.t = b.t and a.pattern < b.pattern)"]
    for k in (3, 4, 5):
        parts += [f"{x}o{k} as (select o.pattern || '|' || i.pattern as pattern, o.t, i.pattern as last from {x}o{k - 1} o join occ i on i.t = o.t and i.pattern > o.last where o.pattern in {dense(k - 1)} and o.last || '|' || i.pattern in {dense(2)})", islands(f"{x}{k}", f"{x}o{k}", width, sigma)]
    return ", ".join(parts)


def _levels_sql(x: str, columns: str) -> str:
    return " union all ".join(f"select {columns.format(k=k)} from {x}{k}" for k in range(1, 6))


_DAYS = f"{base(days=True)}, {PAIRS}, {_five_levels('n', 47_000, 15)}, {_five_levels('w', 141_000, 32)}"
_NARROW = f"nar as ({_levels_sql('n', 'pattern, s // 1000 as s, e // 1000 as e')})"
_WIDE = f"wid as ({_levels_sql('w', 'pattern, s // 1000 as s, e // 1000 as e')})"
_CAMP = f"{CAMPAIGNS}, pc as (select distinct pattern, campaign_id, c.s, c.e from (select distinct pattern from nar) p join camp_items c on list_contains(string_split(p.pattern, '|'), c.item)), {merged('mc', 'pc')}"
_RATIO = "inside as (select nar.pattern, sum(least(nar.e, mc.e) - greatest(nar.s, mc.s)) as x from nar join mc on mc.pattern = nar.pattern and nar.s < mc.e and mc.s < nar.e group by 1), rat as (select nar.pattern, round(coalesce(max(x), 0) / sum(e - s), 6) as ratio from nar left join inside on inside.pattern = nar.pattern group by 1)"
_COUNTS = "cnt as (select k.pattern, k.s, k.e, count(distinct campaign_id) as n from (select distinct pattern, s, e from nar) k left join pc on pc.pattern = k.pattern and pc.s < k.e and k.s < pc.e group by 1, 2, 3)"
_PROMO = f"{_DAYS}, {_NARROW}, {_WIDE}, {_CAMP}, {_RATIO}, {_COUNTS}"


#: Every set of items of a slot, of any length, and its dense intervals.
_ALL_SETS = f"{base(days=True).replace('with ', 'with recursive ', 1)}, sets as (select pattern, pattern as last, t from occ union all select x.pattern || '|' || i.pattern, i.pattern, x.t from sets x join occ i on i.t = x.t and i.pattern > x.last), {islands('n', 'sets', 47_000, 15)}, nar as (select pattern, s // 1000 as s, e // 1000 as e from n)"

#: Longest patterns of the promotion experiment; the summary has those of every length.
_DAYS_K_MAX = 5


def _mine_days(spark, d, width: int, sigma: int) -> DataFrame:
    """By time shards: full slots hold most brands, and the level-wise search would make a row of every set of five in every slot."""
    tx = checkpointed(transactions(spark, d, "brand", days=True))
    return checkpointed(sharded.mine_dense_sharded(tx, width, sigma, shard_width=width, k_max=_DAYS_K_MAX))


def _mine_all_days(spark, d, width: int, sigma: int) -> DataFrame:
    """Patterns of every length, for one reader. Full slots make millions that are dense in most shards, so patterns are dealt instead of times."""
    return sharded.mine_dense_by_pairs(checkpointed(transactions(spark, d, "brand", days=True)), width, sigma)


def _day_result(spark, d, width: int, sigma: int) -> DataFrame:
    return promo.in_days(_mine_days(spark, d, width, sigma))


def _narrow(spark, d):
    return _day_result(spark, d, 47_000, 15)


@query(f"{_DAYS} {_levels_sql('n', 'pattern, {k} as len, s, e')}")
def mine_dense_days_47(spark, d):
    return _mine_days(spark, d, 47_000, 15)


@query(f"{_DAYS} {_levels_sql('w', 'pattern, {k} as len, s, e')}")
def mine_dense_days_141(spark, d):
    return _mine_days(spark, d, 141_000, 32)


@query(f"{_PROMO} select pattern, ratio from rat")
def promo_ratio(spark, d):
    return promo.promo_overlap_ratio(_narrow(spark, d), promo.campaigns(spark))


@query(f"{_PROMO} select pattern, s, e, n from cnt")
def promo_overlap_counts(spark, d):
    return promo.campaigns_per_interval(_narrow(spark, d), promo.campaigns(spark))


@query(f"{_PROMO} select count(*) as n_intervals, round(avg(case when n <= 1 then 1.0 else 0.0 end), 6) as share_le1, round(avg(case when n >= 2 then 1.0 else 0.0 end), 6) as share_ge2, round(avg(n), 6) as mean_campaigns from cnt")
def promo_overlap_distribution(spark, d):
    return promo.overlap_distribution(promo.campaigns_per_interval(_narrow(spark, d), promo.campaigns(spark)))


@query(f"{_ALL_SETS}, p as (select pattern, count(*) as k, avg(e - s) as m, sum(e - s) as x from nar group by 1) select count(*) as n_patterns, round(avg(k), 6) as intervals_per_pattern, round(sum(x) / sum(k), 6) as mean_len_intervals, round(avg(m), 6) as mean_len_patterns from p")
def window_summary(spark, d):
    return promo.window_summary(promo.in_days(_mine_all_days(spark, d, 47_000, 15)))


@query(f"{_PROMO} select case when rat.pattern in (select pattern from wid) then 'common' else 'only_narrow' end as part, count(*) as n_patterns, round(avg(ratio), 6) as mean_ratio from rat group by 1")
def window_exclusive_patterns(spark, d):
    narrow, wide = _narrow(spark, d), _day_result(spark, d, 141_000, 32)
    return promo.compare_windows(narrow, wide, promo.promo_overlap_ratio(narrow, promo.campaigns(spark)))


@query(f"{_DAYS}, {_NARROW}, {merged('mn', 'nar')} select pattern, cast(sum(e - s) as bigint) as covered from mn group by 1")
def pattern_coverage_days(spark, d):
    return promo.pattern_days(_narrow(spark, d))


@query(f"{_PROMO}, h as (select 'high' as side, row_number() over (order by ratio desc, pattern) as r, pattern, ratio from rat union all select 'low', row_number() over (order by ratio, pattern), pattern, ratio from rat) select side, cast(r as integer) as rank, pattern, ratio from h where r <= 5")
def promo_extremes(spark, d):
    return promo.promo_examples(promo.promo_overlap_ratio(_narrow(spark, d), promo.campaigns(spark)), 5)


_DISCOUNTS = "camps as (select l_partkey as campaign_id, p_type as kind, min(date_diff('day', date '1995-01-01', cast(l_shipdate as date))) as start_day, max(date_diff('day', date '1995-01-01', cast(l_shipdate as date))) as end_day from lineitem join part on p_partkey = l_partkey where l_discount > 0 group by 1, 2)"


@query(f"with {_DISCOUNTS} select kind, count(*) as n, cast(min(end_day - start_day) as bigint) as min_days, cast(max(end_day - start_day) as bigint) as max_days, round(avg(end_day - start_day), 6) as mean_days from camps group by 1")
def campaign_profile(spark, d):
    """Campaigns as the lines' discounts show them."""
    camps = promo.discount_campaigns(table(spark, d, "lineitem", "l_partkey", "l_shipdate", "l_discount"), table(spark, d, "part", "p_partkey", "p_type"), DAY_ZERO)
    return promo.campaign_profile(camps)
