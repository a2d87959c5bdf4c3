"""Pieces of the SQL that queries are compared with. Detection is brute force over window starts where the timeline is short."""

from __future__ import annotations

ITEMS = {"brand": "p_brand", "type": "p_type", "brandtype": "p_brand || p_type", "supp": "cast(l_suppkey as varchar)", "pname": "p_name"}

RANKS = "tx as (select o_orderkey, row_number() over (order by o_orderdate, o_orderkey) as t from orders)"
DAYS = """days as (select o_orderkey, date_diff('day', date '1995-01-01', cast(o_orderdate as date)) as day from orders),
 tx as (select o_orderkey, cast(day * 1000 + ((row_number() over (partition by day order by o_orderkey) - 1) * 1000) // count(*) over (partition by day) as bigint) as t from days)"""
LAST = "tm as (select max(t) as tmax from tx)"


def base(view: str = "brand", *, days: bool = False) -> str:
    """with tx, tm, occ: order times, the last time, and occurrences of single items."""
    part = "" if view == "supp" else " join part on p_partkey = l_partkey"
    return f"with {DAYS if days else RANKS}, {LAST}, occ as (select distinct {ITEMS[view]} as pattern, t from tx join lineitem on l_orderkey = o_orderkey{part})"


PAIRS = "pairs as (select a.pattern || '|' || b.pattern as pattern, a.t from occ a join occ b on a.t = b.t and a.pattern < b.pattern)"
TRIPLES = "triples as (select a.pattern || '|' || b.pattern || '|' || c.pattern as pattern, a.t from occ a join occ b on a.t = b.t and a.pattern < b.pattern join occ c on a.t = c.t and b.pattern < c.pattern)"


def brute(name: str, source: str, width: int, sigma: int, *, last: str = "tmax") -> str:
    """``name`` (pattern, s, e): every start counted, then runs of dense starts."""
    return f"""{name}_o as (select pattern from {source} group by pattern having count(*) >= {sigma}),
 {name}_g as (select o.pattern, g.l, case when x.t is null then 0 else 1 end as m from {name}_o o cross join (select unnest(range(0, {last} + 1)) as l from tm) g left join {source} x on x.pattern = o.pattern and x.t = g.l),
 {name}_c as (select pattern, l, sum(m) over (partition by pattern order by l rows between current row and {width} following) as sup from {name}_g),
 {name}_d as (select pattern, l, l - row_number() over (partition by pattern order by l) as grp from {name}_c, tm where sup >= {sigma} and l <= {last} - {width}),
 {name} as (select pattern, min(l) as s, max(l) + {width} as e from {name}_d group by pattern, grp)"""


def islands(name: str, source: str, width: int, sigma: int, *, clip: bool = True) -> str:
    """``name`` (pattern, s, e) where timelines are too long to count every start: covered starts from every group of sigma occurrences, joined by a running maximum."""
    b = f"least(x.t, tmax - {width})" if clip else "x.t"
    return f"""{name}_n as (select pattern, t, row_number() over (partition by pattern order by t) as i from {source}),
 {name}_s as (select x.pattern, greatest(0, y.t - {width}) as a, {b} as b from {name}_n x join {name}_n y on y.pattern = x.pattern and y.i = x.i + {sigma} - 1 cross join tm where y.t - x.t <= {width}),
 {name}_m as (select pattern, a, b, max(b) over (partition by pattern order by a, b rows between unbounded preceding and 1 preceding) as top from {name}_s where a <= b),
 {name}_r as (select pattern, a, b, sum(case when top is null or a > top + 1 then 1 else 0 end) over (partition by pattern order by a, b rows unbounded preceding) as run from {name}_m),
 {name} as (select pattern, min(a) as s, max(b) + {width} as e from {name}_r group by pattern, run)"""


def merged(name: str, source: str, keys: str = "pattern") -> str:
    """``name``: union coverage of ``source`` (keys, s, e)."""
    return f"""{name}_m as (select {keys}, s, e, max(e) over (partition by {keys} order by s, e rows between unbounded preceding and 1 preceding) as top from {source}),
 {name}_r as (select {keys}, s, e, sum(case when top is null or s > top then 1 else 0 end) over (partition by {keys} order by s, e rows unbounded preceding) as run from {name}_m),
 {name} as (select {keys}, min(s) as s, max(e) as e from {name}_r group by {keys}, run)"""


def runs(name: str, source: str, gap: str, keys: str = "pattern") -> str:
    """``name`` (keys, s, e, n): maximal runs of occurrences whose gaps are at most ``gap``."""
    return f"""{name}_l as (select *, lag(t) over (partition by {keys} order by t) as before from {source}),
 {name}_r as (select *, sum(case when t - before <= {gap} then 0 else 1 end) over (partition by {keys} order by t rows unbounded preceding) as run from {name}_l),
 {name} as (select {keys}, min(t) as s, max(t) as e, count(*) as n, min(t) as t1 from {name}_r group by {keys}, run)"""


CAMPAIGNS = """camps as (select cast(id as integer) as campaign_id, ['A', 'B', 'C'][id % 3 + 1] as kind, (id * 79) % 2240 as start_day,
 (id * 79) % 2240 + case when id = 15 then 161 when id = 30 then 96 else 32 + 3 * (id % 8) end as end_day from range(1, 31) r(id)),
 camp_items as (select campaign_id, 'Brand#' || b as item, start_day as s, end_day as e from camps cross join range(1, 26) q(b) where (b + campaign_id) % 5 = 0)"""
