"""Registered queries on small tables made so that a job done in part would show."""

from datetime import datetime, timedelta
from itertools import combinations

import pytest

from localfreq.registry import accuracy, mining, streams, surround
from localfreq.sources.tables import transactions


def order_tables(spark, folder, orders):
    """orders, lineitem and part of (day, items) rows; an item is both brand and type of its part."""
    items = sorted({x for _, basket in orders for x in basket})
    key = {x: i for i, x in enumerate(items)}
    spark.createDataFrame([(i, datetime(1995, 1, 1) + timedelta(days=day)) for i, (day, _) in enumerate(orders)], "o_orderkey long, o_orderdate timestamp_ntz").write.parquet(f"{folder}/orders.parquet")
    spark.createDataFrame([(i, key[x], 0) for i, (_, basket) in enumerate(orders) for x in basket], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{folder}/lineitem.parquet")
    spark.createDataFrame([(i, x, x, x) for x, i in key.items()], "p_partkey long, p_brand string, p_type string, p_name string").write.parquet(f"{folder}/part.parquet")
    return str(folder)


@pytest.fixture(scope="module")
def days(spark, tmp_path_factory):
    """An order a day with the same six brands: every set of them is dense."""
    return order_tables(spark, tmp_path_factory.mktemp("days"), [(day, [f"Brand#{b}" for b in range(1, 7)]) for day in range(200)])


SETS = {"|".join(c) for k in range(1, 6) for c in combinations([f"Brand#{b}" for b in range(1, 7)], k)}


@pytest.mark.parametrize("name", ["mine_dense_days_47", "mine_dense_days_141"])
def test_day_patterns_have_up_to_five_items(spark, days, name):
    assert {r["pattern"] for r in accuracy.QUERIES[name](spark, days).collect()} == SETS


def test_day_measures_count_larger_patterns(spark, days):
    assert {r["part"]: r["n_patterns"] for r in accuracy.QUERIES["window_exclusive_patterns"](spark, days).collect()} == {"common": len(SETS)}


def test_window_summary_counts_sets_of_every_length(spark, days, tmp_path):
    """All six brands together are a pattern as well; of nine items, all 511 sets are, and the SQL says so too."""
    import duckdb

    assert accuracy.QUERIES["window_summary"](spark, days).first()["n_patterns"] == 63
    d = order_tables(spark, tmp_path, [(day, [f"Brand#{b}" for b in range(1, 10)] if day < 80 or day % 9 == 0 else ["Brand#1", "Brand#7"]) for day in range(220)])
    con = duckdb.connect()
    for t in ("orders", "lineitem", "part"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet/*.parquet'")
    row = accuracy.QUERIES["window_summary"](spark, d).first()
    assert row["n_patterns"] == 511
    assert tuple(row) == pytest.approx(con.execute(f"select {', '.join(row.asDict())} from ({accuracy.ORACLES['window_summary']}) q").fetchone(), abs=1e-5)


def test_streamed_itemsets_of_every_length(spark, tmp_path):
    d = order_tables(spark, tmp_path, [(day, ["a", "b", "c"]) for day in range(400)])
    assert {r["pattern"] for r in streams.QUERIES["stream_dense_itemsets"](spark, d).collect()} == {"a", "b", "c", "a|b", "a|c", "b|c", "a|b|c"}


def test_orders_of_a_full_day_share_slots(spark, tmp_path):
    """1,500 orders a day over 1,000 slots: orders 0 and 1 of a day share its first slot, as integer division has it."""
    d = order_tables(spark, tmp_path, [(day, ["a"] if i % 2 else ["b"]) for day in range(2) for i in range(1500)])
    want = {(day * 1500 + i, day * 1000 + i * 1000 // 1500) for day in range(2) for i in range(1500)}
    assert {tuple(r) for r in mining.QUERIES["timeline_day_slot"](spark, d).select("o_orderkey", "t").collect()} == want
    assert {tuple(r) for r in mining.QUERIES["timeline_slot_day"](spark, d).select("day", "n").collect()} == {(0, 1500), (1, 1500)}
    tx = transactions(spark, d, "brand", days=True).collect()
    assert len(tx) == 2000 and {r["t"]: r["items"] for r in tx}[0] == ["a", "b"]


def test_full_days_are_mined_by_bitmaps_of_shards(spark, tmp_path):
    """Days of more orders than slots: the union of orders in a slot is what is mined, and the level-wise search agrees."""
    import random

    from localfreq.plans.miner import mine_dense
    from localfreq.plans.sharded import mine_dense_sharded

    rng = random.Random(4)
    d = order_tables(spark, tmp_path, [(day, [x for x in "abcdef" if rng.random() < (0.8 if day == 1 else 0.2)]) for day in range(3) for _ in range(1300)])
    tx = transactions(spark, d, "brand", days=True).cache()
    for width, sigma in ((500, 260), (300, 40), (1000, 15)):
        want = {tuple(r) for r in mine_dense(tx, width, sigma, k_max=5).select("pattern", "len", "s", "e").collect()}
        assert len(want) > 20 and {tuple(r) for r in mine_dense_sharded(tx, width, sigma, shard_width=700, k_max=5).select("pattern", "len", "s", "e").collect()} == want


def test_patterns_dealt_by_pairs_are_those_of_the_shards(spark, tmp_path):
    """Shared slots, items whose text needs escapes, and every length: the level-wise search agrees."""
    import random

    from localfreq.plans.miner import mine_dense
    from localfreq.plans.sharded import mine_dense_by_pairs

    rng = random.Random(6)
    items = ["a", "b|c", "d\\", "e", "Brand#1", "Brand#10", "f"]
    d = order_tables(spark, tmp_path, [(day, [x for x in items if rng.random() < (0.7 if day == 1 else 0.3)]) for day in range(3) for _ in range(1300)])
    tx = transactions(spark, d, "brand", days=True).cache()
    for width, sigma, k_max in ((500, 120, None), (300, 30, None), (1000, 40, 3)):
        want = {tuple(r) for r in mine_dense(tx, width, sigma, k_max=k_max).select("pattern", "len", "s", "e").collect()}
        got = [tuple(r) for r in mine_dense_by_pairs(tx, width, sigma, k_max=k_max).select("pattern", "len", "s", "e").collect()]
        assert len(want) > 20 and len(got) == len(want) and set(got) == want


@pytest.mark.parametrize("piece, together", [(3, 1), (40, 9), (1_000_000, 100_000)])
def test_pairs_in_any_pieces_and_portions_are_searched_whole(monkeypatch, piece, together):
    """Any batches, pieces of them and portions of what is found; also more items than a word has bits."""
    import random

    import pyarrow as pa

    from localfreq.plans import sharded

    monkeypatch.setattr(sharded, "_PIECE", piece)
    monkeypatch.setattr(sharded, "_TOGETHER", together)
    rng = random.Random(7)
    for n_items, share, width, sigma in ((6, 0.6, 9, 4), (7, 0.8, 20, 11), (90, 0.05, 30, 2), (3, 0.5, 1, 1)):
        tx = [(t, s) for t in range(80) if (s := [f"i{x}" for x in range(n_items) if rng.random() < share])]
        want = [("|".join(p), len(p), s, d + width) for p, s, d in sharded.mine_shard(tx, width, sigma, 0, 79 - width, None)]
        rows = {}
        for b in (tx[30:], tx[:30]):
            batch = pa.RecordBatch.from_pydict({"t": pa.array([t for t, _ in b], pa.int64()), "items": pa.array([s for _, s in b], pa.list_(pa.string()))})
            for r in sharded._deal(batch, "u4"):
                for i in range(r.num_rows):
                    rows.setdefault((r["a"][i].as_py(), r["b"][i].as_py()), []).append(r.slice(i, 1))
        got = [tuple(x.values()) for (a, b), r in rows.items() for o in sharded._in_batches(sharded._mine_pair(a, b, pa.Table.from_batches(r), "u4", width, sigma, 79 - width, None), width, each=50) for x in o.to_pylist()]
        assert sorted(got) == sorted(want)


def test_day_transactions_are_made_in_pieces_of_bounded_rows(spark, tmp_path):
    """420,000 lines are joined and grouped in five pieces; coalesced by their compressed size, they were one or few, too much for a small heap at size."""
    spark.range(60_000).selectExpr("id as o_orderkey", "if(id = 7, null, date_add(date'1995-01-01', cast(id % 100 as int))) as o_orderdate").write.parquet(f"{tmp_path}/orders.parquet")
    spark.range(420_000).selectExpr("id % 59999 as l_orderkey", "(id * 7) % 40 as l_partkey", "0L as l_suppkey").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.range(39).selectExpr("id as p_partkey", "concat('Brand#', id % 25) as p_brand", "'x' as p_type", "'x' as p_name").write.parquet(f"{tmp_path}/part.parquet")
    tx = transactions(spark, str(tmp_path), "brand", days=True)
    assert tx.rdd.getNumPartitions() == 5
    got = {r["t"]: set(r["items"]) for r in tx.collect()}
    want, nth = {}, {}
    for i in range(60_000):
        nth[i % 100] = nth.get(i % 100, 0) + (i != 7)
        t = None if i == 7 else i % 100 * 1000 + (nth[i % 100] - 1) * 1000 // (600 - (i % 100 == 7))
        want.setdefault(t, set()).update(f"Brand#{p % 25}" for p in ((x * 7) % 40 for x in range(i, 420_000, 59_999)) if p < 39 and i < 59_999 and t is not None)
    assert got == want


def test_transactions_cut_into_shards_come_together_again():
    """Any batches of transactions, few or many items, give each shard the rows that a plain copy of them gives."""
    import random

    import pyarrow as pa

    from localfreq.plans.sharded import _cut, _joined, _span

    rng = random.Random(5)
    for width, c, n_items, n_shards in ((10, 7, 5, 12), (0, 1, 3, 40), (90, 40, 700, 2), (1 << 33, 1 << 34, 4, 1)):
        tx = [(rng.randrange(80), rng.sample(range(n_items), rng.randint(1, n_items))) for _ in range(40)]
        batches = [pa.RecordBatch.from_pydict({"t": pa.array([t for t, _ in b], pa.int64()), "items": pa.array([[f"i{x}" for x in s] for _, s in b], pa.list_(pa.string()))}) for b in (tx[:3], tx[3:])]
        rows = pa.Table.from_batches([_cut(b, width, c, n_shards) for b in batches])
        want = {}
        for t, s in tx:
            for k in range(max(0, t - width) // c, min(t // c, n_shards - 1) + 1):
                want.setdefault(k, []).extend((t, f"i{x}") for x in s)
        assert set(rows.column("shard").to_pylist()) == set(want)
        for k, pairs in want.items():
            codes, times, names = _joined(rows.filter(pa.array([x == k for x in rows.column("shard").to_pylist()])), _span(width, c), k * c)
            assert sorted(zip(times.tolist(), (names[x] for x in codes), strict=True)) == sorted(pairs)


@pytest.mark.parametrize("name", ["promo_ratio", "promo_overlap_counts", "promo_overlap_distribution", "window_summary", "window_exclusive_patterns", "pattern_coverage_days", "promo_extremes"])
def test_promotions_over_full_days_agree_with_their_sql(spark, tmp_path, name):
    import duckdb

    d = order_tables(spark, tmp_path, [(day, ["Brand#1", "Brand#2"] if day < 60 or i % 40 else []) for day in range(0, 160, 4) for i in range(1001 if day == 8 else 9)])
    con = duckdb.connect()
    for t in ("orders", "lineitem", "part"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet/*.parquet'")
    df = accuracy.QUERIES[name](spark, d)
    tidy = lambda rows: sorted(tuple(round(v, 5) if isinstance(v, float) else v for v in r) for r in rows)
    got = tidy(df.collect())
    assert got and got == tidy(con.execute(f"select {', '.join(df.columns)} from ({accuracy.ORACLES[name]}) q").fetchall())


@pytest.mark.parametrize("name", ["campaign_profile", "generated_counts", "join_cross_grid"])
def test_jobs_read_given_tables(spark, name):
    d = "/root/testdata/sf0.001"
    files = (accuracy.QUERIES | mining.QUERIES | surround.QUERIES)[name](spark, d).inputFiles()
    assert any("lineitem" in f for f in files), files
