"""Queries of surrounding operators: sources, sinks, joins, aggregates, windows, set operations, functions, SQL surface."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.functions import sql as own
from localfreq.operators import detect, intervals, kernels
from localfreq.operators.timeline import column_timeline
from localfreq.plans import miner
from localfreq.registry.sqltext import base, brute, islands
from localfreq.session import shared_folder
from localfreq.sources import formats
from localfreq.sources.tables import occurrences, order_ranks, table, transactions
from localfreq.workloads import dense_intervals_items

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def _folder(spark) -> str:
    return f"{shared_folder(spark)}/files-{uuid.uuid4().hex}"


_ITEMS = f"{base()}, {brute('r', 'occ', 250, 55)}"


def _found(spark, d) -> DataFrame:
    return dense_intervals_items(spark, d, width=250, sigma=55)


# --- sources and sinks

@query("select l_returnflag, count(*) as n, cast(sum(l_linenumber) as bigint) as lines from lineitem where l_shipdate >= timestamp '1996-01-01' group by 1")
def src_parquet_profile(spark, d):
    rows = table(spark, d, "lineitem", "l_returnflag", "l_linenumber", "l_shipdate").where(F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz"))
    return rows.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum("l_linenumber").alias("lines"))


def _trip(kind: str):
    def run(spark, d):
        return formats.round_trip(_found(spark, d), _folder(spark), kind)

    return run


for _k in ("csv", "json", "orc"):
    QUERIES[f"src_{_k}_roundtrip"] = _trip(_k)
    ORACLES[f"src_{_k}_roundtrip"] = f"{_ITEMS} select pattern, s, e from r"


@query(f"{base()} select tx.t, coalesce(string_agg(pattern, '|' order by pattern), '') as items from tx left join occ on occ.t = tx.t group by 1")
def src_basket_lines(spark, d):
    path = _folder(spark)
    formats.write_basket_lines(transactions(spark, d, "brand"), path)
    return formats.read_timed_lines(spark, path).select("t", F.array_join("items", "|").alias("items"))


@query(f"{base('type')}, p as (select a.pattern || '|' || b.pattern as pattern, a.t from occ a join occ b on a.t = b.t and a.pattern < b.pattern), {brute('r1', 'occ', 250, 100)}, {brute('r2', 'p', 250, 60)}, u as (select 1 as len, * from r1 union all select 2, * from r2) select len, count(*) as n, count(distinct pattern) as n_patterns from u group by 1")
def sink_partitioned(spark, d):
    path = _folder(spark)
    tx = transactions(spark, d, "type")
    both = miner.mine_dense(tx, 250, 100, k_max=1).unionByName(miner.mine_dense(tx, 250, 60, k_max=2, min_len=2))
    formats.write_intervals(both, path)
    return spark.read.parquet(path).groupBy("len").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("pattern").alias("n_patterns"))


# --- projection, joins

@query("select event_id, event_type, cast(value as bigint) as v from events where event_type in ('click', 'view') and value between 10 and 60 and props like '%k%' and user_id is not distinct from user_id and try_cast(value as bigint) is not null")
def op_filter_project(spark, d):
    e = table(spark, d, "events", "event_id", "event_type", "value", "props", "user_id")
    kept = e.where(F.col("event_type").isin("click", "view") & F.col("value").between(10, 60) & F.col("props").like("%k%") & F.col("user_id").eqNullSafe(F.col("user_id")) & F.expr("try_cast(value as bigint)").isNotNull())
    return kept.select("event_id", "event_type", F.rint("value").cast("bigint").alias("v"))


@query("select o_orderpriority, count(*) as n from orders join lineitem on l_orderkey = o_orderkey group by 1")
def join_inner(spark, d):
    return table(spark, d, "orders", "o_orderkey", "o_orderpriority").join(table(spark, d, "lineitem", "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("select r_name, n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2")
def join_broadcast(spark, d):
    places = table(spark, d, "nation", "n_nationkey", "n_name", "n_regionkey").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer", "c_nationkey").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query("select o_orderkey, count(l_orderkey) as n from orders left join lineitem on l_orderkey = o_orderkey group by 1")
def join_left_outer(spark, d):
    return table(spark, d, "orders", "o_orderkey").join(table(spark, d, "lineitem", "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left").groupBy("o_orderkey").agg(F.count("l_orderkey").alias("n"))


@query("select coalesce(doc_id, vec_id) as id, doc_id is not null as in_docs, vec_id is not null as in_vecs from (select doc_id from labels) full outer join (select vec_id from embeddings) on doc_id = vec_id")
def join_full_outer(spark, d):
    both = table(spark, d, "labels", "doc_id").join(table(spark, d, "embeddings", "vec_id"), F.col("doc_id") == F.col("vec_id"), "full_outer")
    return both.select(F.coalesce("doc_id", "vec_id").alias("id"), F.col("doc_id").isNotNull().alias("in_docs"), F.col("vec_id").isNotNull().alias("in_vecs"))


@query("select p_partkey, p_brand from part where exists (select 1 from lineitem where l_partkey = p_partkey and l_quantity >= 49)")
def join_semi(spark, d):
    return table(spark, d, "part", "p_partkey", "p_brand").join(table(spark, d, "lineitem", "l_partkey", "l_quantity").where("l_quantity >= 49"), F.col("p_partkey") == F.col("l_partkey"), "left_semi")


@query("select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")
def join_anti(spark, d):
    return table(spark, d, "orders", "o_orderkey").join(table(spark, d, "lineitem", "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("select a.w, b.s from (select distinct p_size as w from part) a cross join (select distinct l_linenumber as s from lineitem) b")
def join_cross_grid(spark, d):
    """Every pair of values of two axes that the tables hold."""
    widths, levels = table(spark, d, "part", "p_size").distinct(), table(spark, d, "lineitem", "l_linenumber").distinct()
    return widths.select(F.col("p_size").alias("w")).crossJoin(F.broadcast(levels.select(F.col("l_linenumber").alias("s"))))


@query(f"{_ITEMS} select r.pattern, r.s, count(occ.t) as n from r left join occ on occ.pattern = r.pattern and occ.t between r.s and r.e group by 1, 2")
def join_range_bucketed(spark, d):
    found, (occ, _) = _found(spark, d), occurrences(spark, d, "brand")
    place = lambda c: F.floor(c / 512)
    spread = found.withColumn("b", F.explode(F.sequence(place(F.col("s")), place(F.col("e")))))
    return spread.join(occ.withColumn("b", place(F.col("t"))), ["pattern", "b"]).where("t between s and e").groupBy("pattern", "s").agg(F.count(F.lit(1)).alias("n"))


@query("with h as (select user_id, ts, event_id, max(case when event_type = 'purchase' then event_id end) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as x, event_type from events) select event_id, user_id, (select max(p.ts) from events p where p.user_id = h.user_id and p.event_type = 'purchase' and (p.ts < h.ts or (p.ts = h.ts and p.event_id < h.event_id))) as last_buy from h where event_type = 'click'")
def join_asof(spark, d):
    e = table(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    by = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("last_buy", F.last(F.when(F.col("event_type") == "purchase", F.col("ts")), ignorenulls=True).over(by)).where("event_type = 'click'").select("event_id", "user_id", "last_buy")


@query(f"{_ITEMS} select a.pattern as a, b.pattern as b, count(*) as n from r a join r b on a.pattern < b.pattern and a.s < b.e and b.s < a.e group by 1, 2")
def join_interval_overlap(spark, d):
    spread = _found(spark, d).withColumn("k", F.explode(F.sequence(F.floor(F.col("s") / 1024), F.floor(F.col("e") / 1024))))
    a, b = (spread.select(F.col("pattern").alias(x), F.col("s").alias(f"s{x}"), F.col("e").alias(f"e{x}"), "k") for x in "ab")
    met = a.join(b, "k").where("a < b and sa < eb and sb < ea").select("a", "b", "sa", "ea", "sb", "eb").distinct()
    return met.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


# --- aggregates

_BY = "select {c}, {g} as g, count(*) as n from lineitem join part on p_partkey = l_partkey group by {by}"


def _lines(spark, d) -> DataFrame:
    return table(spark, d, "lineitem", "l_partkey", "l_returnflag", "l_linestatus", "l_quantity").join(table(spark, d, "part", "p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey"))


@query(_BY.format(c="p_type, l_returnflag", g="cast(grouping_id(p_type, l_returnflag) as bigint)", by="rollup (p_type, l_returnflag)"))
def agg_rollup(spark, d):
    return _lines(spark, d).rollup("p_type", "l_returnflag").agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"))


@query(_BY.format(c="p_type, l_returnflag", g="cast(grouping_id(p_type, l_returnflag) as bigint)", by="cube (p_type, l_returnflag)"))
def agg_cube(spark, d):
    return _lines(spark, d).cube("p_type", "l_returnflag").agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"))


@query("select p_type, l_linestatus, count(*) as n from lineitem join part on p_partkey = l_partkey group by grouping sets ((p_type), (l_linestatus), ())")
def agg_grouping_sets(spark, d):
    return _lines(spark, d).groupingSets([["p_type"], ["l_linestatus"], []], "p_type", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@query("select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_quantity) as quantities from lineitem group by 1")
def agg_distinct(spark, d):
    return table(spark, d, "lineitem", "l_returnflag", "l_partkey", "l_quantity").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_quantity").alias("quantities"))


@query("select p_type, count(*) filter (l_returnflag = 'A') as a, count(*) filter (l_returnflag = 'N') as n, count(*) filter (l_returnflag = 'R') as r from lineitem join part on p_partkey = l_partkey group by 1")
def agg_pivot(spark, d):
    wide = _lines(spark, d).groupBy("p_type").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1)))
    return wide.select("p_type", *(F.coalesce(x, F.lit(0)).alias(x.lower()) for x in "ANR"))


@query("select event_type, round(quantile_cont(value, 0.5), 6) as p50, round(quantile_cont(value, 0.9), 6) as p90 from events group by 1")
def agg_percentile(spark, d):
    return table(spark, d, "events", "event_type", "value").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("p50"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


@query("select event_type, count(*) filter (value > 50) as high, count(*) as n from events group by 1")
def agg_filter_clause(spark, d):
    table(spark, d, "events", "event_type", "value").createOrReplaceTempView("events_v")
    return spark.sql("select event_type, count(*) filter (where value > 50) as high, count(*) as n from events_v group by event_type")


@query("select user_id, arg_max(event_id, cast(epoch_us(ts) as hugeint) * 1000000 + event_id) as last_event from events group by 1")
def agg_max_by(spark, d):
    return table(spark, d, "events", "user_id", "event_id", "ts").groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("last_event"))


@query()
def agg_approx_distinct(spark, d):
    return table(spark, d, "lineitem", "l_returnflag", "l_partkey").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("select t.l_returnflag, string_agg(t.p_type, ',' order by t.p_type) as types from (select distinct l_returnflag, p_type from lineitem join part on p_partkey = l_partkey) t group by 1")
def agg_listagg(spark, d):
    return _lines(spark, d).select("l_returnflag", "p_type").distinct().groupBy("l_returnflag").agg(F.array_join(F.array_sort(F.collect_list("p_type")), ",").alias("types"))


# --- windows, sorting, sets

@query("select p_partkey, cast(rank() over w as integer) as r, cast(dense_rank() over w as integer) as dr, round(percent_rank() over w, 6) as pr from part window w as (partition by p_type order by p_size)")
def win_rank(spark, d):
    w = Window.partitionBy("p_type").orderBy("p_size")
    return table(spark, d, "part", "p_partkey", "p_type", "p_size").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query(f"{base()} select pattern, t, t - lag(t) over (partition by pattern order by t) as gap from occ")
def win_lag_gap(spark, d):
    return occurrences(spark, d, "brand")[0].select("pattern", "t", (F.col("t") - F.lag("t").over(Window.partitionBy("pattern").orderBy("t"))).alias("gap"))


@query("select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 4) as s3 from events")
def win_rows_frame(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return table(spark, d, "events", "event_id", "user_id", "ts", "value").select("event_id", F.round(F.sum("value").over(w), 4).alias("s3"))


@query(f"{base()} select pattern, t, count(*) over (partition by pattern order by t range between current row and 100 following) as sup from occ")
def win_range_frame(spark, d):
    return detect.support_curve(occurrences(spark, d, "brand")[0], 100)


@query("select c_custkey, cast(ntile(10) over (partition by c_mktsegment order by c_acctbal, c_custkey) as integer) as tile from customer")
def win_ntile(spark, d):
    return table(spark, d, "customer", "c_custkey", "c_mktsegment", "c_acctbal").select("c_custkey", F.ntile(10).over(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).alias("tile"))


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25 offset 5")
def sort_topk(spark, d):
    return table(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(25)


@query("select c_mktsegment, c_custkey, c_acctbal from customer qualify row_number() over (partition by c_mktsegment order by c_acctbal desc, c_custkey) <= 3")
def topk_per_group(spark, d):
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, d, "customer", "c_mktsegment", "c_custkey", "c_acctbal").withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


_SETS = "(select c_nationkey as k from customer where c_acctbal > 5000) {op} (select s_nationkey as k from supplier)"


def _two_sides(spark, d):
    return table(spark, d, "customer", "c_nationkey", "c_acctbal").where("c_acctbal > 5000").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier", "s_nationkey").select(F.col("s_nationkey").alias("k"))


@query(_SETS.format(op="union"))
def set_union(spark, d):
    a, b = _two_sides(spark, d)
    return a.unionByName(b).distinct()


@query(_SETS.format(op="intersect"))
def set_intersect(spark, d):
    a, b = _two_sides(spark, d)
    return a.intersect(b)


@query(_SETS.format(op="except"))
def set_except(spark, d):
    a, b = _two_sides(spark, d)
    return a.subtract(b)


@query(_SETS.format(op="except all"))
def set_except_all(spark, d):
    a, b = _two_sides(spark, d)
    return a.exceptAll(b)


@query(_SETS.format(op="intersect all"))
def set_intersect_all(spark, d):
    a, b = _two_sides(spark, d)
    return a.intersectAll(b)


# --- functions

@query("select lang, count(*) as n, count(distinct w) as words from (select lang, unnest(regexp_split_to_array(lower(text), '[^\\p{L}]+')) as w from documents) where length(w) > 3 group by 1")
def fn_string_tokens(spark, d):
    words = table(spark, d, "documents", "lang", "text").select("lang", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("w")).where(F.length("w") > 3)
    return words.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("w").alias("words"))


@query("select regexp_extract(url, '://([^/?#]*)', 1) as host, count(*) as n from pages group by 1")
def fn_url_host(spark, d):
    return table(spark, d, "pages", "url").groupBy(F.expr("try_parse_url(url, 'HOST')").alias("host")).agg(F.count(F.lit(1)).alias("n"))


@query("select cast(year(o_orderdate) as integer) as y, cast(month(o_orderdate) as integer) as m, cast(isodow(o_orderdate) as integer) as dow, count(*) as n, cast(min(date_diff('day', date '1995-01-01', cast(o_orderdate as date))) as integer) as first_day from orders group by 1, 2, 3")
def fn_date_parts(spark, d):
    o = table(spark, d, "orders", "o_orderdate")
    iso = F.weekday("o_orderdate") + 1
    return o.groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), iso.alias("dow")).agg(F.count(F.lit(1)).alias("n"), F.min(F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))).alias("first_day"))


@query("select o_orderkey, o_orderkey // 7 as a, o_orderkey % 7 as b, round(ln(o_totalprice), 6) as l, greatest(o_custkey, o_orderkey) as g, cast(floor(o_totalprice / 1000) as bigint) as f from orders")
def fn_math_slots(spark, d):
    k = F.col("o_orderkey")
    return table(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").select("o_orderkey", F.expr("o_orderkey div 7").alias("a"), F.pmod(k, F.lit(7)).alias("b"), F.round(F.log("o_totalprice"), 6).alias("l"), F.greatest("o_custkey", "o_orderkey").alias("g"), F.floor(F.col("o_totalprice") / 1000).alias("f"))


@query(f"{base('type')}, b as (select t, list_sort(list(pattern)) as items from occ group by t) select t, array_to_string(list_transform(range(1, len(items) + 1), lambda i: array_to_string(list_filter(items, lambda x: x <> items[i]), '+')), ';') as subsets from b where len(items) >= 2")
def fn_array_subsets(spark, d):
    tx = transactions(spark, d, "type").where(F.size("items") >= 2)
    less = F.transform("items", lambda x: F.array_join(F.filter("items", lambda y: y != x), "+"))
    return tx.select("t", F.array_join(less, ";").alias("subsets"))


@query(f"{base('type')}, b as (select t, list_sort(list(pattern)) as items from occ group by t), n as (select t, items, lead(items) over (order by t) as nxt, lead(t) over (order by t) as t2 from b) select t, len(list_intersect(items, nxt)) as common, len(list_filter(items, lambda x: not list_contains(nxt, x))) as gone from n where t2 = t + 1")
def fn_array_setops(spark, d):
    tx = transactions(spark, d, "type").where(F.size("items") > 0)
    nxt = tx.select((F.col("t") - 1).alias("t"), F.col("items").alias("nxt"))
    return tx.join(nxt, "t").select("t", F.size(F.array_intersect("items", "nxt")).cast("long").alias("common"), F.size(F.array_except("items", "nxt")).cast("long").alias("gone"))


@query(f"{base()}, g as (select pattern, t - lag(t) over (partition by pattern order by t) as gap from occ) select pattern, cast(sum(greatest(gap - 5, 0)) as bigint) as surplus from g group by 1")
def fn_array_fold(spark, d):
    times = occurrences(spark, d, "brand")[0].groupBy("pattern").agg(F.array_sort(F.collect_list("t")).alias("t"))
    gaps = F.zip_with(F.slice("t", 2, F.size("t")), F.slice("t", 1, F.greatest(F.size("t") - 1, F.lit(0))), lambda a, b: F.greatest(a - b - 5, F.lit(0).cast("long")))
    return times.select("pattern", F.aggregate(gaps, F.lit(0).cast("long"), lambda s, x: s + x).alias("surplus"))


@query(f"{_ITEMS} select pattern, count(*) as n, cast(max(e - s) as bigint) as longest from r group by 1 having count(*) > 5")
def fn_map_intervals(spark, d):
    one = miner.as_map(_found(spark, d))
    kept = F.map_filter("patterns", lambda k, v: F.size(v) > 5)
    longest = F.transform_values(kept, lambda k, v: F.struct(F.size(v).cast("long").alias("n"), F.array_max(F.transform(v, lambda i: i["e"] - i["s"])).alias("longest")))
    return one.select(F.explode(F.map_entries(longest)).alias("x")).select(F.col("x.key").alias("pattern"), "x.value.n", "x.value.longest")


@query("select cast(json_extract_string(props, '$.k') as bigint) as k, count(*) as n from events group by 1")
def fn_json_props(spark, d):
    return table(spark, d, "events", "props").select(F.from_json("props", "k string")["k"].cast("bigint").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("select doc_id, measure, v from (select doc_id, cast(quality as bigint) as quality, cast(toxic as bigint) as toxic from labels) unpivot (v for measure in (quality, toxic))")
def fn_unpivot_scores(spark, d):
    wide = table(spark, d, "labels").select("doc_id", F.col("quality").cast("bigint").alias("quality"), F.col("toxic").cast("bigint").alias("toxic"))
    return wide.unpivot("doc_id", ["quality", "toxic"], "measure", "v")


@query()
def op_sample(spark, d):
    return table(spark, d, "orders", "o_orderkey").sample(0.1, seed=3)


@query("select event_id as t, event_type from events")
def timeline_column(spark, d):
    return column_timeline(table(spark, d, "events", "event_id", "event_type"), "event_id").select("t", "event_type")


# --- SQL surface, own functions

def _times_view(spark, d) -> int:
    occ, t_max = occurrences(spark, d, "brand")
    occ.groupBy("pattern").agg(F.collect_list("t").alias("times")).createOrReplaceTempView("brand_times")
    occ.createOrReplaceTempView("brand_occ")
    own.register(spark)
    return t_max


@query(f"{_ITEMS} select pattern, s, e from r where s > 0")
def sql_lateral_intervals(spark, d):
    t_max = _times_view(spark, d)
    return spark.sql(f"select pattern, x.s, x.e from brand_times, lateral dense_intervals_of(times, 250, 55, {t_max}) x where x.s > 0")


@query(f"{_ITEMS} select p_partkey from part where exists (select 1 from r where r.pattern = p_brand)")
def sql_exists_dense(spark, d):
    _found(spark, d).createOrReplaceTempView("dense_brands")
    table(spark, d, "part", "p_partkey", "p_brand").createOrReplaceTempView("part_v")
    return spark.sql("select p_partkey from part_v where exists (select 1 from dense_brands b where b.pattern = p_brand)")


@query(f"{_ITEMS} select pattern, s, e from r")
def sql_dense_text(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    occ.createOrReplaceTempView("brand_occ")
    return spark.sql(detect.dense_intervals_sql("brand_occ", 250, 55, t_max))


@query(f"{_ITEMS} select pattern, s, e from r")
def sql_dense_udtf(spark, d):
    t_max = _times_view(spark, d)
    return spark.sql(f"select pattern, x.s, x.e from brand_times, lateral dense_intervals_of(times, 250, 55, {t_max}) x")


@query(f"{base()}, {brute('r', 'occ', 250, 55)} select o.pattern, count(r.s) as n from (select distinct pattern from occ) o left join r on r.pattern = o.pattern group by 1")
def udf_scalar_dense(spark, d):
    t_max = _times_view(spark, d)
    return spark.table("brand_times").select("pattern", own.dense_run_count("times", F.lit(250), F.lit(55), F.lit(t_max)).alias("n"))


@query(f"{base()}, c as (select a.pattern, a.t, count(*) as sup from occ a join occ b on b.pattern = a.pattern and b.t between a.t and a.t + 250 group by 1, 2) select pattern, max(sup) as peak from c group by 1")
def udaf_peak_support(spark, d):
    occ, _ = occurrences(spark, d, "brand")
    return occ.withColumn("w", F.lit(250)).groupBy("pattern").agg(own.peak_support("t", "w").alias("peak"))


@query(f"{base('supp')}, {islands('r', 'occ', 250, 12)} select pattern, s, e from r")
def udtf_intervals(spark, d):
    occ, t_max = occurrences(spark, d, "supp")
    own.register(spark)
    occ.groupBy("pattern").agg(F.collect_list("t").alias("times")).createOrReplaceTempView("supp_times")
    return spark.sql(f"select pattern, x.s, x.e from supp_times, lateral dense_intervals_of(times, 250, 12, {t_max}) x")


@query(f"{_ITEMS} select pattern, s, e from r")
def grouped_map_scan(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    return kernels.scan_by_pattern(occ, 250, 55, t_max=t_max).where("s is not null").select("pattern", "s", (F.col("d") + 250).alias("e"))


@query(f"{_ITEMS} select pattern, s, e from r")
def cogroup_scan_ranges(spark, d):
    occ, t_max = occurrences(spark, d, "brand")
    ranges = intervals.merge_intervals(detect.dense_intervals(occ, 250, 50, t_max=t_max), ["pattern"])
    return kernels.scan_by_pattern(occ, 250, 55, t_max=t_max, ranges=ranges).where("s is not null").select("pattern", "s", (F.col("d") + 250).alias("e"))
