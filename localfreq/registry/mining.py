"""Queries of timelines, detection and the dense miner."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.operators import baskets, candidates, detect, intervals, kernels, timeline
from localfreq.plans import cost, miner, sharded, synth
from localfreq.registry.sqltext import LAST, PAIRS, RANKS, TRIPLES, base, brute, islands, merged
from localfreq.sources.tables import DAY_ZERO, event_occurrences, item_column, occurrences, order_days, order_ranks, order_rows, table, token_rows, transactions
from localfreq.workloads import dense_intervals_items

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a query under its function's name."""
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


# --- timelines and baskets

@query(f"with {RANKS} select o_orderkey, t from tx")
def timeline_rank(spark: SparkSession, d: str) -> DataFrame:
    return order_ranks(spark, d)


@query(f"{base(days=True).split(', tm as')[0]} select o_orderkey, t from tx")
def timeline_day_slot(spark, d):
    return order_days(spark, d)


@query(f"{base(days=True).split(', tm as')[0]} select t // 1000 as day, count(*) as n from tx group by 1")
def timeline_slot_day(spark, d):
    return order_days(spark, d).groupBy(timeline.slot_day(F.col("t")).alias("day")).agg(F.count(F.lit(1)).alias("n"))


@query("select event_id, epoch_us(ts) // 3600000000 as t from events")
def timeline_bucket(spark, d):
    return timeline.bucket_timeline(table(spark, d, "events", "event_id", "ts"), "ts", 3600).select("event_id", "t")


@query("select l_orderkey as t, array_to_string(list_sort(list(distinct cast(l_suppkey as varchar))), '|') as items from lineitem group by l_orderkey")
def baskets_union_duplicates(spark, d):
    lines = table(spark, d, "lineitem", "l_orderkey", "l_suppkey")
    tx = lines.select(F.col("l_orderkey").alias("t"), F.array(F.col("l_suppkey").cast("string")).alias("items"))
    return baskets.resolve_duplicates(tx).select("t", F.array_join("items", "|").alias("items"))


@query("select o_orderkey as t, coalesce(array_to_string(list_sort(list(distinct p_brand) filter (p_brand is not null)), '|'), '') as items from orders left join lineitem on l_orderkey = o_orderkey left join part on p_partkey = l_partkey group by 1")
def baskets_orders_brand(spark, d):
    lines = table(spark, d, "lineitem", "l_orderkey", "l_partkey").join(table(spark, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    rows = table(spark, d, "orders", "o_orderkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    return baskets.to_baskets(rows, "o_orderkey", "p_brand").select("t", F.array_join("items", "|").alias("items"))


@query(f"{base()} select pattern, t from occ")
def occurrences_items(spark, d):
    return occurrences(spark, d, "brand")[0]


@query(f"{base()}, w as (select pattern, row_number() over (order by pattern) - 1 as code from (select distinct pattern from occ) q) select code as item, t from occ join w using (pattern)")
def occurrences_coded(spark, d):
    return baskets.encode_items(occurrences(spark, d, "brand")[0])[0]


@query(f"{base()} select t from occ where pattern in ('Brand#1', 'Brand#2') group by t having count(*) = 2")
def occurrences_itemset(spark, d):
    return baskets.occurrences_of(transactions(spark, d, "brand"), ["Brand#1", "Brand#2"])


@query(f"{base()}, k as (select tx.t, count(pattern) as c from tx left join occ on occ.t = tx.t group by tx.t) select count(*) as n_tx, max(t) as t_max, round(avg(c), 6) as mean_len, cast(sum(c) as bigint) as n_pairs, (select count(distinct pattern) from occ) as n_items from k")
def profile_dataset(spark, d):
    return baskets.profile(transactions(spark, d, "brand"))


# --- support and detection

@query(f"{base()}, w as (select pattern, l from (select distinct pattern from occ) p cross join (select unnest(range(0, tmax + 1, 250)) as l from tm) g) select w.pattern, w.l, count(occ.t) as sup from w left join occ on occ.pattern = w.pattern and occ.t between w.l and w.l + 250 group by 1, 2")
def interval_support(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    windows = occ.select("pattern").distinct().crossJoin(F.broadcast(spark.range(0, t_max + 1, 250).select(F.col("id").alias("l"))))
    return detect.interval_support(occ, windows, 250)


@query(f"{base()}, c as (select pattern, t as l, count(*) over (partition by pattern order by t range between current row and 250 following) as sup from occ) select pattern, l, sup, cast(sup >= 38 as integer) as is_dense from c")
def dense_windows(spark, d):
    """The windows at every occurrence."""
    occ, _ = occurrences(spark, d, "brand")
    return detect.dense_windows(occ, occ.select("pattern", F.col("t").alias("l")), 250, 38)


@query(f"{base()} select a.pattern, a.t, count(*) as sup from occ a join occ b on b.pattern = a.pattern and b.t between a.t and a.t + 250 group by 1, 2")
def support_curve(spark, d):
    return detect.support_curve(occurrences(spark, d, "brand")[0], 250)


def _items_sql(width: int, sigma: int, view: str = "brand") -> str:
    return f"{base(view)}, {brute('r', 'occ', width, sigma)} select pattern, s, e from r"


QUERIES["dense_intervals_items"] = lambda spark, d: dense_intervals_items(spark, d, width=250, sigma=55)
ORACLES["dense_intervals_items"] = _items_sql(250, 55)


@query(f"{base()}, {brute('r', 'occ', 250, 55)}, i as (select r.*, count(occ.t) as n_occ from r join occ on occ.pattern = r.pattern and occ.t between s and e group by all), k as (select r.pattern, r.s, r.e, max(c.sup) as peak_sup from r join r_c c on c.pattern = r.pattern and c.l between r.s and r.e - 250 group by all) select i.pattern, i.s, i.e, n_occ, cast(peak_sup as bigint) as peak_sup from i join k using (pattern, s, e)")
def dense_intervals_support(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    return detect.with_support(detect.dense_intervals(occ, 250, 55, t_max=t_max), occ, 250)


@query(_items_sql(100, 21))
def dense_intervals_sharded(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    return detect.dense_intervals(occ, 100, 21, t_max=t_max, shard_width=1500)


@query(f"{base()}, {islands('r', 'occ', 100, 21, clip=False)} select pattern, s, e from r")
def dense_intervals_unclipped(spark, d):
    return detect.dense_intervals(occurrences(spark, d, "brand")[0], 100, 21, clip_end=False)


def _kernel(spark, d, kernel: str, width: int, sigma: int, view: str = "brand") -> DataFrame:
    occ, t_max = occurrences(spark, d, view)
    return kernels.scan_by_pattern(occ, width, sigma, t_max=t_max, kernel=kernel).where("s is not null").select("pattern", "s", (F.col("d") + width).alias("e"))


@query(_items_sql(250, 55))
def dense_intervals_skip(spark, d):
    return _kernel(spark, d, "skip", 250, 55)


@query(_items_sql(250, 55))
def dense_intervals_every(spark, d):
    return _kernel(spark, d, "every", 250, 55)


@query(_items_sql(250, 100, "type"))
def dense_intervals_type(spark, d):
    occ, t_max = occurrences(spark, d, "type")
    return detect.dense_intervals(occ, 250, 100, t_max=t_max)


@query(f"{base('brandtype')}, {islands('r', 'occ', 250, 16)} select pattern, s, e from r")
def dense_intervals_brandtype(spark, d):
    occ, t_max = occurrences(spark, d, "brandtype")
    return detect.dense_intervals(occ, 250, 16, t_max=t_max, prefilter=True)


_EVENTS = "ev as (select epoch_us(ts) // {us} as b, {item} as item from events), tx as (select b - (select min(b) from ev) as t from ev), tm as (select max(t) as tmax from tx), occ as (select distinct item as pattern, b - (select min(b) from ev) as t from ev)"


@query(f"with {_EVENTS.format(us=60_000_000, item='event_type')}, {brute('r', 'occ', 60, 6)} select pattern, s, e from r")
def dense_intervals_events(spark, d):
    occ = event_occurrences(spark, d, "event_type", 60)
    return detect.dense_intervals(occ, 60, 6)


@query(f"with {_EVENTS.format(us=60_000_000, item='event_type')}, {brute('r', 'occ', 60, 10)} select pattern, s, e from r")
def dense_intervals_events_60_10(spark, d):
    return detect.dense_intervals(event_occurrences(spark, d, "event_type", 60), 60, 10)


@query(f"with {_EVENTS.format(us=3_600_000_000, item='cast(user_id as varchar)')}, {brute('r', 'occ', 24, 5)} select pattern, s, e from r")
def dense_intervals_users(spark, d):
    return detect.dense_intervals(event_occurrences(spark, d, "user_id", 3600), 24, 5)


@query(f"{base()}, n as (select pattern, t, count(*) over (partition by pattern order by t range between current row and 250 following) as c from occ), k as (select pattern, t, c, lead(t, greatest(c - 55, 0)) over (partition by pattern order by t) as keep from n) select pattern, t, keep from k where c >= 55")
def stride_skip_positions(spark, d):
    return kernels.skip_positions(occurrences(spark, d, "brand")[0], 250, 55).select("pattern", "t", "keep")


@query(f"{base()}, n as (select pattern, t, row_number() over (partition by pattern order by t) as i, count(*) over (partition by pattern order by t range between current row and 250 following) as c from occ) select n.pattern, count(*) as n_dense, round(avg(n.c - 45), 6) as mean_surplus, round(avg(m.t + 1 - n.t), 6) as mean_stride from n join n m on m.pattern = n.pattern and m.i = n.i + n.c - 45 where n.c >= 45 group by 1")
def skip_profile(spark, d):
    return kernels.skip_profile(occurrences(spark, d, "brand")[0], 250, 45)


# --- the miner

def _mine_sql(view: str, width: int, sigma: int, form=brute, k: int = 3) -> str:
    parts = [form("r1", "occ", width, sigma), PAIRS, form("r2", "pairs", width, sigma)] + ([TRIPLES, form("r3", "triples", width, sigma)] if k > 2 else [])
    rows = " union all ".join(f"select pattern, {i} as len, s, e from r{i}" for i in range(1, k + 1))
    return f"{base(view)}, {', '.join(parts)} {rows}"


@query(_mine_sql("brand", 250, 14))
def mine_dense_brand_k3(spark, d):
    return miner.mine_dense(transactions(spark, d, "brand"), 250, 14, k_max=3)


@query(_mine_sql("brand", 250, 10, k=2))
def mine_dense_brand_250_10(spark, d):
    return miner.mine_dense(transactions(spark, d, "brand"), 250, 10, k_max=2)


@query(_mine_sql("brand", 500, 24, k=2))
def mine_dense_brand_500(spark, d):
    return miner.mine_dense(transactions(spark, d, "brand"), 500, 24, k_max=2)


@query(_mine_sql("brand", 1000, 40, k=2))
def mine_dense_brand_1000(spark, d):
    return miner.mine_dense(transactions(spark, d, "brand"), 1000, 40, k_max=2)


@query(_mine_sql("supp", 100, 3, islands))
def mine_dense_supp_k3(spark, d):
    return miner.mine_dense(transactions(spark, d, "supp"), 100, 3, k_max=3)


@query(_mine_sql("brandtype", 250, 4, islands, 2))
def mine_dense_brandtype(spark, d):
    return miner.mine_dense(transactions(spark, d, "brandtype"), 250, 4, k_max=2)


@query(_mine_sql("type", 250, 60, k=2))
def mine_dense_items_restricted(spark, d):
    return miner.mine_dense(transactions(spark, d, "type"), 250, 60, k_max=2, restrict="items")


@query(_mine_sql("type", 250, 60, k=2))
def mine_dense_unrestricted(spark, d):
    return miner.mine_dense(transactions(spark, d, "type"), 250, 60, k_max=2, restrict="none")


@query(f"{base('supp')}, {islands('r', 'occ', 250, 5)} select pattern, 1 as len, s, e from r")
def dense_items(spark, d):
    occ, t_max = occurrences(spark, d, "supp")
    return miner.dense_items(occ, 250, 5, t_max=t_max)


def _dense_shape(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    found = detect.dense_intervals(occ, 250, 55, t_max=t_max)
    return occ, found, found.select(F.lit("").alias("prefix"), F.col("pattern").alias("last")).distinct()


@query(f"{base()}, {brute('r', 'occ', 250, 55)}, p as (select distinct pattern from r) select a.pattern || '|' || b.pattern as pattern from p a join p b on a.pattern < b.pattern")
def candidate_join(spark, d):
    return candidates.join_candidates(_dense_shape(spark, d)[2]).select("pattern")


@query(f"{base()}, {PAIRS}, f as (select pattern, split_part(pattern, '|', 1) as x, split_part(pattern, '|', 2) as y from pairs group by pattern having count(*) >= 205) select a.pattern || '|' || b.y as pattern from f a join f b on a.x = b.x and a.y < b.y join f c on c.x = a.y and c.y = b.y")
def candidate_prune(spark, d):
    occ, _ = occurrences(spark, d, "brand")
    a, b = occ.select(F.col("pattern").alias("prefix"), "t"), occ.select(F.col("pattern").alias("last"), "t")
    level = a.join(b, "t").where("prefix < last").groupBy("prefix", "last").agg(F.count(F.lit(1)).alias("n")).where("n >= 205").select("prefix", "last")
    return candidates.prune_by_subsets(candidates.join_candidates(level), level, 3).select("pattern")


@query(f"{base()}, {PAIRS} select pattern, count(*) as n, min(t) as first, max(t) as last from pairs group by 1")
def occurrence_intersection(spark, d):
    occ, _ = occurrences(spark, d, "brand")
    level = occ.select(F.lit("").alias("prefix"), F.col("pattern").alias("last"), "t")
    found = candidates.extend_occurrences(level, candidates.join_candidates(level.select("prefix", "last").distinct()))
    return found.groupBy("pattern").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("first"), F.max("t").alias("last"))


@query(f"{base()}, {brute('r', 'occ', 250, 55)}, k as (select a.pattern || '|' || b.pattern as pattern, x.l from (select distinct pattern from r) a join (select distinct pattern from r) b on a.pattern < b.pattern join r_d x on x.pattern = a.pattern join r_d y on y.pattern = b.pattern and y.l = x.l), i as (select pattern, l, l - row_number() over (partition by pattern order by l) as grp from k) select pattern, min(l) as s, max(l) + 250 as e from i group by pattern, grp")
def candidate_ranges(spark, d):
    _, found, shape = _dense_shape(spark, d)
    return candidates.candidate_ranges(candidates.join_candidates(shape), found, 250, 2)


_COUNTERS = f"""{base()}, {PAIRS}, {TRIPLES}, {brute('r1', 'occ', 250, 14)}, {brute('r2', 'pairs', 250, 14)}, {brute('r3', 'triples', 250, 14)},
 l1 as (select distinct pattern from r1), l2 as (select distinct pattern, split_part(pattern, '|', 1) as x, split_part(pattern, '|', 2) as y from r2),
 c2 as (select a.pattern || '|' || b.pattern as pattern, a.pattern as x, b.pattern as y from l1 a join l1 b on a.pattern < b.pattern), o2 as (select * from c2 where pattern in (select pattern from pairs)),
 g2 as (select distinct o2.pattern from o2 join r1_d p on p.pattern = x join r1_d q on q.pattern = y and q.l = p.l),
 j3 as (select a.pattern || '|' || b.y as pattern, a.x, a.y, b.y as z from l2 a join l2 b on a.x = b.x and a.y < b.y), c3 as (select * from j3 where y || '|' || z in (select pattern from l2)), o3 as (select * from c3 where pattern in (select pattern from triples)),
 g3 as (select distinct o3.pattern from o3 join r1_d p on p.pattern = x join r1_d q on q.pattern = y and q.l = p.l join r1_d r on r.pattern = z and r.l = p.l)"""
_N = lambda x: f"(select count(*) from {x})"


@query(f"""{_COUNTERS}, i as (select distinct pattern from occ), u as (
 select 1 as level, {_N('i')} as generated, 0 as pruned_subset, 0 as empty_occurrences, 0 as empty_ranges, {_N('i')} as scanned, {_N('l1')} as dense
 union all select 2, {_N('c2')}, 0, {_N('c2')} - {_N('o2')}, {_N('o2')} - {_N('g2')}, {_N('g2')}, {_N('l2')}
 union all select 3, {_N('j3')}, {_N('j3')} - {_N('c3')}, {_N('c3')} - {_N('o3')}, {_N('o3')} - {_N('g3')}, {_N('g3')}, (select count(distinct pattern) from r3))
 select cast(level as integer) as level, generated, cast(pruned_subset as bigint) as pruned_subset, cast(empty_occurrences as bigint) as empty_occurrences, cast(empty_ranges as bigint) as empty_ranges, scanned, dense from u""")
def prune_counters(spark, d):
    return miner.prune_counters(transactions(spark, d, "brand"), 250, 14, 3)


@query(_mine_sql("brand", 250, 14))
def mine_dense_sharded(spark, d):
    return sharded.mine_dense_sharded(transactions(spark, d, "brand"), 250, 14, shard_width=2000, k_max=3)


@query(f"{base()}, {brute('r', 'occ', 250, 55)} select distinct occ.pattern, occ.t from occ join r on r.pattern = occ.pattern and occ.t between s and e")
def trim_occurrences(spark, d):
    occ, found, _ = _dense_shape(spark, d)
    return miner.trim_occurrences(occ, found)


@query(f"{base()}, {brute('r', 'occ', 250, 55)} select pattern, count(*) as n, string_agg('[' || s || ',' || e || ']', '' order by s) as intervals from r group by 1")
def dense_patterns_nested(spark, d):
    rows = miner.nested(dense_intervals_items(spark, d, width=250, sigma=55))
    text = F.array_join(F.transform("intervals", lambda i: F.concat(F.lit("["), i["s"].cast("string"), F.lit(","), i["e"].cast("string"), F.lit("]"))), "")
    return rows.select("pattern", F.size("intervals").cast("long").alias("n"), text.alias("intervals"))


@query(f"{base('supp')}, {islands('r1', 'occ', 250, 5)}, {PAIRS}, {islands('r2', 'pairs', 250, 5)}, p as (select distinct pattern from r2) select pattern, 2 as len from p union all select pattern, 1 as len from (select distinct pattern from r1) q where not exists (select 1 from p where split_part(p.pattern, '|', 1) = q.pattern or split_part(p.pattern, '|', 2) = q.pattern)")
def maximal_dense_patterns(spark, d):
    return miner.maximal_patterns(miner.mine_dense(transactions(spark, d, "supp"), 250, 5, k_max=2))


@query(f"{_mine_sql('brand', 500, 24, k=2).replace(' select pattern, 1 as len', ', u as (select pattern, 1 as len', 1)}), k as (select len, pattern, cast(sum(e - s) as bigint) as duration from u group by 1, 2), n as (select len, cast(row_number() over (partition by len order by duration desc, pattern) as integer) as rank, pattern, duration from k) select len, rank, pattern, duration from n where rank <= 10")
def topk_dense(spark, d):
    return miner.topk_patterns(miner.mine_dense(transactions(spark, d, "brand"), 500, 24, k_max=2), 10)


@query(f"{_mine_sql('supp', 250, 5, islands, 2).replace(' select pattern, 1 as len', ', u as (select pattern, 1 as len', 1)}), k as (select pattern, len, string_agg(s || '-' || e, ',' order by s) as h from u group by 1, 2) select pattern, len from k where not exists (select 1 from k b where b.len = k.len + 1 and b.h = k.h and (split_part(b.pattern, '|', 1) = k.pattern or split_part(b.pattern, '|', 2) = k.pattern))")
def closed_dense_patterns(spark, d):
    return miner.closed_patterns(miner.mine_dense(transactions(spark, d, "supp"), 250, 5, k_max=2))


@query(f"{base()}, {brute('r', 'occ', 250, 55)}, k as (select r.pattern, cast(max(c.sup) as bigint) as peak_sup from r join r_c c on c.pattern = r.pattern and c.l between r.s and r.e - 250 group by 1), n as (select 1 as len, cast(row_number() over (order by peak_sup desc, pattern) as integer) as rank, pattern, peak_sup from k) select len, rank, pattern, peak_sup from n where rank <= 10")
def topk_dense_by_peak(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    found = detect.with_support(detect.dense_intervals(occ, 250, 55, t_max=t_max), occ, 250)
    return miner.topk_patterns(found.withColumn("len", F.lit(1)), 10, by="peak_sup")


@query("select cast(null as varchar) as pattern, cast(null as varchar) as subset, cast(null as bigint) as s, cast(null as bigint) as e where 1 = 0")
def containment_violations(spark, d):
    return miner.check_monotone(miner.mine_dense(transactions(spark, d, "brand"), 250, 14, k_max=2))


@query(f"{base('type')}, {PAIRS}, {brute('a1', 'occ', 250, 100)}, {brute('a2', 'pairs', 250, 100)}, {brute('b1', 'occ', 250, 60)}, {brute('b2', 'pairs', 250, 60)}, {brute('c1', 'occ', 500, 100)}, {brute('c2', 'pairs', 500, 100)} " + " union all ".join(f"select cast({w} as bigint) as width, cast({s} as bigint) as sigma, pattern, {k} as len, s, e from {n}{k}" for n, w, s in (("a", 250, 100), ("b", 250, 60), ("c", 500, 100)) for k in (1, 2)))
def mine_many_settings(spark, d):
    return miner.mine_dense_many(transactions(spark, d, "type"), [(250, 100), (250, 60), (500, 100)])


# --- interval algebra, on dense intervals of brands (a) and types (b) under one key

def _ab(spark, d):
    a = dense_intervals_items(spark, d, width=250, sigma=55).select(F.lit("k").alias("k"), "s", "e")
    b = dense_intervals_items(spark, d, view="type", width=250, sigma=112).select(F.lit("k").alias("k"), "s", "e")
    return a, b


_AB = f"{base()}, {brute('ra', 'occ', 250, 55)}, occ2 as (select distinct p_type as pattern, t from tx join lineitem on l_orderkey = o_orderkey join part on p_partkey = l_partkey), {brute('rb', 'occ2', 250, 112)}, a as (select 'k' as k, s, e from ra), b as (select 'k' as k, s, e from rb), {merged('ma', 'a', 'k')}, {merged('mb', 'b', 'k')}"
_AND = "x as (select ma.k, greatest(ma.s, mb.s) as s, least(ma.e, mb.e) as e from ma join mb on ma.k = mb.k and ma.s < mb.e and mb.s < ma.e)"


@query(f"{_AB} select k, s, e from ma")
def interval_union(spark, d):
    return intervals.merge_intervals(_ab(spark, d)[0], ["k"])


@query(f"{_AB}, {_AND} select k, s, e from x where e - s >= 50")
def interval_intersection(spark, d):
    return intervals.intersect_intervals(*_ab(spark, d), ["k"], min_len=50)


@query(f"{_AB} select k, cast(sum(e - s) as bigint) as covered from ma group by k")
def interval_coverage(spark, d):
    return intervals.coverage(_ab(spark, d)[0], ["k"])


@query(f"{_AB}, {_AND} select k.k, cast(coalesce((select sum(e - s) from x), 0) as bigint) as overlap from (select k from a union select k from b) k")
def interval_overlap(spark, d):
    return intervals.overlap_length(*_ab(spark, d), ["k"])


@query(f"{_AB}, u as (select unnest(range(s, e)) as p from mb), v as (select unnest(range(s, e)) as p from ma), w as (select p, p - row_number() over (order by p) as g from (select p from u except select p from v)) select 'k' as k, min(p) as s, max(p) + 1 as e from w group by g")
def interval_difference(spark, d):
    a, b = _ab(spark, d)
    return intervals.subtract_intervals(b, a, ["k"])


@query(f"{_AB} select distinct 'k' as k, tx.t from tx join a on tx.t between a.s and a.e")
def point_in_interval(spark, d):
    points = order_ranks(spark, d).select(F.lit("k").alias("k"), "t")
    return intervals.covers(points, _ab(spark, d)[0], ["k"])


@query(f"{_AB}, c as (select row_number() over (order by s, e) as id, k, s, e from b), d as (select distinct k, s, e from a) select d.k, d.s, d.e, count(distinct c.s * 1000000 + c.e) as n from d left join c on c.s < d.e and d.s < c.e group by 1, 2, 3")
def interval_overlap_count(spark, d):
    a, b = _ab(spark, d)
    return intervals.count_overlaps(a, b.withColumn("id", F.col("s") * 1_000_000 + F.col("e")), ["k"], b_id="id", bucket=500)


# --- cost and generators

def _ablation_sql(width: int, sigma: int) -> str:
    """Windows and runs of brands and their pairs. The jumps of the skipping scan are a recursive query with one row an evaluated window."""
    end = f"len(list_filter(ts, lambda x: x <= l + {width}))"
    return f"""{base().replace('with ', 'with recursive ', 1)}, {PAIRS}, alls as materialized (select pattern, t from occ union all select pattern, t from pairs),
 {brute('r1', 'occ', width, sigma)}, {brute('ra', 'alls', width, sigma)},
 items as (select distinct pattern from occ),
 spans as (select pattern, 0 as lo, tmax - {width} as hi from items, tm union all select a.pattern || '|' || b.pattern, greatest(a.s, b.s), least(a.e, b.e) - {width} from r1 a join r1 b on a.pattern < b.pattern where greatest(a.s, b.s) <= least(a.e, b.e) - {width}),
 lists as materialized (select pattern, list(t order by t) as ts from alls group by 1),
 met as (select pattern, lo, hi, ts, len(list_filter(ts, lambda x: x < lo)) + {sigma} as nth from spans join lists using (pattern)),
 scan as (select pattern, lo, hi, greatest(lo, ts[nth] - {width}) as l from met where nth <= len(ts) and greatest(lo, ts[nth] - {width}) <= hi
  union all select pattern, lo, hi, upto from (select pattern, lo, hi, case when c >= {sigma} then ts[n - {sigma} + 1] + 1 when n < len(ts) then greatest(l + 1, ts[n + 1] - {width}) end as upto
   from (select pattern, lo, hi, l, ts, {end} as n, {end} - len(list_filter(ts, lambda x: x < l)) as c from scan join lists using (pattern)) q) w where upto <= hi),
 total as (select count(*) as runs from ra)
 select 'every' as strategy, cast(count(*) * (max(tmax) - {width} + 1) as bigint) as windows, max(runs) as runs from lists, tm, total
 union all select 'every_ranges', cast(sum(hi - lo + 1) as bigint), max(runs) from spans, total
 union all select 'skip_ranges', count(*), (select runs from total) from scan"""


@query(_ablation_sql(250, 14))
def ablation_windows(spark, d):
    """Windows of single brands and all their pairs under the three strategies."""
    occ, t_max = occurrences(spark, d, "brand")
    level = occ.select(F.lit("").alias("prefix"), F.col("pattern").alias("last"), "t")
    shape = candidates.join_candidates(level.select("prefix", "last").distinct())
    pairs = candidates.extend_occurrences(level, shape).select("pattern", "t")
    singles = detect.dense_intervals(occ, 250, 14, t_max=t_max)
    whole = occ.select("pattern").distinct().select("pattern", F.lit(0).cast("long").alias("s"), F.lit(t_max).cast("long").alias("e"))
    ranges = whole.unionByName(candidates.candidate_ranges(shape, singles, 250, 2))
    return cost.ablation(occ.unionByName(pairs), ranges, 250, 14, t_max)


@query(f"{_mine_sql('brand', 250, 14, k=2).replace(' select pattern, 1 as len', ', u as (select pattern, 1 as len', 1)}) select len, count(distinct pattern) as n_patterns, count(*) as n_intervals from u group by 1")
def pattern_counts_by_length(spark, d):
    return cost.pattern_counts(miner.mine_dense(transactions(spark, d, "brand"), 250, 14, k_max=2))


@query(f"{base()}, {brute('r', 'occ', 250, 55)} select pattern, cast(sum(e - 250 - s + 1) as bigint) as starts, round(sum(e - 250 - s + 1) / (max(tmax) - 250 + 1), 6) as share from r, tm group by 1")
def range_reduction(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    return cost.range_reduction(detect.dense_intervals(occ, 250, 55, t_max=t_max), 250, t_max)


_PLANT = "tx as (select o_orderkey, row_number() over (order by o_orderdate, o_orderkey) as t from orders), tm as (select max(t) as tmax from tx), occ as (select 'X' || ((t - 1000) // 1300) || '_' || j as pattern, t from tx cross join range(1, 6) r(j) where t >= 1000 and (t - 1000) // 1300 < 10 and (t - 1000) % 1300 < 1000 and (t - 1000) % 10 = 0)"


@query(f"with {_PLANT}, {brute('r1', 'occ', 250, 20)}, {PAIRS}, {brute('r2', 'pairs', 250, 20)}, {TRIPLES}, {brute('r3', 'triples', 250, 20)} " + " union all ".join(f"select pattern, {k} as len, s, e from r{k}" for k in (1, 2, 3)))
def planted_patterns(spark, d):
    times = order_ranks(spark, d).select("t", F.array().cast("array<string>").alias("items"))
    return miner.mine_dense(synth.plant(times), 250, 20, k_max=3)


_SUBSETS = f"with {_PLANT}, sets as (select m, j from range(1, 32) a(m) cross join range(1, 6) b(j) where (m >> (j - 1)) & 1 = 1), subs as (select split_part(pattern, '_', 1) || ':' || m as pattern, t from occ join sets on split_part(pattern, '_', 2) = cast(j as varchar) group by split_part(pattern, '_', 1), m, t having count(*) = bit_count(m)), {islands('r', 'subs', 250, 20)}, f as (select distinct pattern, bit_count(cast(split_part(pattern, ':', 2) as integer)) as len from r)"


@query(f"{_SUBSETS} select count(*) // 10 as per_pattern, count(*) as n_patterns, count(*) filter (len >= 2) as n_of_two_or_more from f")
def generated_counts(spark, d):
    """Orders with planted patterns hold exactly these of the planted items: 31 subsets of five items each, whatever the orders' own brands."""
    found = sharded.mine_dense_sharded(synth.plant(transactions(spark, d, "brand")), 250, 20, shard_width=8_000)
    planted = found.select("pattern", "len").distinct().where(F.col("pattern").startswith("X"))
    return planted.agg((F.count(F.lit(1)) / 10).cast("long").alias("per_pattern"), F.count(F.lit(1)).alias("n_patterns"), F.count(F.when(F.col("len") >= 2, 1)).alias("n_of_two_or_more"))


@query("select doc_id as t, word as item, count(*) as n from (select doc_id, unnest(regexp_split_to_array(lower(text), '[^\\p{L}]+')) as word from documents) where length(word) > 3 group by 1, 2 having count(*) >= 12")
def long_baskets(spark, d):
    return token_rows(spark, d).groupBy("t", "item").agg(F.count(F.lit(1)).alias("n")).where("n >= 12")


_TOKENS = "occ as (select distinct word as pattern, doc_id as t from (select doc_id, unnest(regexp_split_to_array(lower(text), '[^\\p{L}]+')) as word from documents) where length(word) > 3), tx as (select distinct doc_id as t from documents), tm as (select max(t) as tmax from tx)"


@query(f"with {_TOKENS}, {islands('r', 'occ', 60, 30)} select pattern, s, e from r")
def dense_words(spark, d):
    """A large vocabulary: words that are dense over stretches of documents, rare words dropped before the large exchange."""
    occ = baskets.occurrences_from_rows(token_rows(spark, d), "t", "item")
    t_max = table(spark, d, "documents", "doc_id").agg(F.max("doc_id")).first()[0]
    return detect.dense_intervals(occ, 60, 30, t_max=t_max if t_max is not None else -1, prefilter=True)
