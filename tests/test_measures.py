"""Hand cases of measures, timelines, sources, generator, promotions and streams."""

import pytest
from pyspark.sql import functions as F

from localfreq.operators import metrics, promo, timeline
from localfreq.operators.baskets import resolve_duplicates, to_baskets
from localfreq.plans import baselines, cost, miner, synth
from localfreq.sources import formats
from localfreq.streaming.dense import ShardedTimeline, late_counts, latest, online_dense_items
from localfreq.streaming.windows import run_to_table

SCHEMA = "pattern string, s long, e long"


def test_scores(spark):
    ref = spark.createDataFrame([("a", 0, 15), ("a", 15, 25), ("b", 0, 10), ("c", 5, 9)], SCHEMA)
    pred = spark.createDataFrame([("a", 0, 25), ("b", 20, 30), ("z", 0, 5)], SCHEMA)
    r = metrics.score(pred, ref).first()
    assert (r["n_pred"], r["n_ref"], r["n_common"]) == (3, 3, 2)
    assert r["f1"] == pytest.approx(2 / 3, abs=1e-6) and r["jaccard"] == pytest.approx(1 / 3, abs=1e-6) and r["tp"] == pytest.approx(0.5)
    point = spark.createDataFrame([("c", 7, 7)], SCHEMA)
    assert metrics.interval_scores(point, ref).first()["tp"] == 0.0
    assert metrics.interval_scores(point, ref, measure="points").first()["tp"] == 1.0
    assert metrics.score(ref, ref).first()["jaccard"] == 1.0
    assert metrics.pattern_f1(ref.limit(0), ref).first()["f1"] == 0.0


def test_gap_miners_at_their_limits(spark):
    tx = spark.createDataFrame([(t, ["x"]) for t in (0, 5, 10, 30, 35)] + [(40, [])], "t long, items array<string>")
    rec = sorted((r["s"], r["e"], r["n_occ"]) for r in baselines.mine_recurring(tx, 5, 2).collect())
    assert rec == [(0, 10, 3), (30, 35, 2)]
    assert baselines.mine_periodic(tx, 20, 5).count() == 1 and baselines.mine_periodic(tx, 19, 5).count() == 0
    local = [(r["s"], r["e"]) for r in baselines.mine_gap_local(tx, 100, 5, 10).collect()]
    assert local == [(0, 10)]
    surplus = sorted((r["s"], r["e"]) for r in baselines.mine_surplus_local(tx, 5, 5, 15).collect())
    assert surplus == [(0, 35)]
    assert sorted((r["s"], r["e"]) for r in baselines.mine_surplus_local(tx, 5, 5, 14).collect()) == [(0, 10), (30, 35)]


def test_timelines(spark):
    rows = spark.createDataFrame([(3, "b"), (1, "z"), (3, "a"), (2, "c")], "k int, v string")
    got = {(r["k"], r["v"]): r["t"] for r in timeline.rank_timeline(rows, ["k", "v"]).collect()}
    assert got == {(1, "z"): 1, (2, "c"): 2, (3, "a"): 3, (3, "b"): 4}
    slots = {(r["k"], r["v"]): r["t"] for r in timeline.day_slot_timeline(rows, "k", ["v"], slots=10).collect()}
    assert slots == {(1, "z"): 10, (2, "c"): 20, (3, "a"): 30, (3, "b"): 35}
    with pytest.raises(Exception, match="more rows than slots"):
        timeline.day_slot_timeline(rows, "k", ["v"], slots=1).collect()
    with pytest.raises(Exception, match="at least 0"):
        timeline.column_timeline(spark.createDataFrame([(-1,)], "x int"), "x").collect()


def test_duplicates_and_dirt(spark):
    rows = spark.createDataFrame([(1, "a"), (1, "a"), (1, None), (1, " "), (2, None)], "t int, x string")
    assert {r["t"]: r["items"] for r in to_baskets(rows, "t", "x").collect()} == {1: ["a"], 2: []}
    tx = spark.createDataFrame([(1, ["b"]), (1, ["a"]), (4, ["c"])], "t long, items array<string>")
    assert {r["t"]: r["items"] for r in resolve_duplicates(tx).collect()} == {1: ["a", "b"], 4: ["c"]}
    assert {r["t"]: r["items"] for r in resolve_duplicates(tx, "rank").collect()} == {1: ["a"], 2: ["b"], 3: ["c"]}
    assert {r["t"]: r["items"] for r in resolve_duplicates(tx, "slot", slots=10).collect()} == {10: ["a"], 15: ["b"], 40: ["c"]}
    with pytest.raises(Exception, match="several transactions"):
        resolve_duplicates(tx, "error").collect()


def test_basket_files(spark, tmp_path):
    (tmp_path / "x.txt").write_text("# note\n3 1 2\n\n5 5\n")
    got = {r["t"]: r["items"] for r in formats.read_basket_lines(spark, f"file://{tmp_path}/x.txt").collect()}
    assert got == {1: ["1", "2", "3"], 2: [], 3: ["5"]}
    (tmp_path / "bad.txt").write_text("x|1 2\n")
    with pytest.raises(Exception, match="no valid time"):
        formats.read_timed_lines(spark, f"file://{tmp_path}/bad.txt").collect()


def test_generator(spark):
    a = synth.generate(spark, 3000, 500, 5, patterns=2, occurrences=50, duration=600, parts=3)
    b = synth.generate(spark, 3000, 500, 5, patterns=2, occurrences=50, duration=600, parts=7)
    assert a.exceptAll(b).count() == 0 and a.count() == 3000
    row = a.agg(F.avg(F.size(F.filter("items", lambda x: x.startswith("i")))).alias("m"), F.countDistinct("t").alias("n")).first()
    assert 4.7 < row["m"] < 5.3 and row["n"] == 3000
    found = miner.mine_dense(a, 200, 15).where(F.col("pattern").startswith("P"))
    assert found.select("pattern").distinct().count() == 2 * 31
    assert synth.background_rate(10**6, 10_000, 5, 1000, 10)["item_over_sigma"] < 0.1


def test_promotions(spark):
    camps = spark.createDataFrame([(1, "A", 0, 10, ["x"]), (2, "B", 5, 20, ["x", "y"])], "campaign_id int, kind string, start_day int, end_day int, items array<string>")
    res = spark.createDataFrame([("x", 1, 0, 20), ("y", 1, 0, 10), ("z", 1, 0, 10)], "pattern string, len int, s long, e long")
    got = {r["pattern"]: r["ratio"] for r in promo.promo_overlap_ratio(res, camps).collect()}
    assert got == {"x": 1.0, "y": 0.5, "z": 0.0}
    assert {r["pattern"]: r["n"] for r in promo.campaigns_per_interval(res, camps).collect()} == {"x": 2, "y": 1, "z": 0}


def test_growth(spark):
    rows = spark.createDataFrame([(float(i), 3.0 * i + 1) for i in range(5)], "x double, y double")
    r = cost.growth(rows, "x", "y").first()
    assert (round(r["slope"], 6), round(r["intercept"], 6), round(r["r2"], 6)) == (3.0, 1.0, 1.0)


def test_stream_in_batches_equals_batch(spark, tmp_path):
    times = [1, 3, 7, 9, 20, 25, 26, 27, 60, 61, 62, 63, 64]
    for i in range(0, len(times), 4):
        spark.createDataFrame([("x", t) for t in times[i:i + 4]], "pattern string, t long").coalesce(1).write.parquet(f"{tmp_path}/in/batch={i:03d}")
    stream = spark.readStream.schema("pattern string, t long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/batch=*")
    from localfreq.operators.detect import dense_intervals

    got = sorted((r["s"], r["e"]) for r in latest(run_to_table(online_dense_items(stream, 10, 3)), 10).collect())
    want = sorted((r["s"], r["e"]) for r in dense_intervals(spark.createDataFrame([("x", t) for t in times], "pattern string, t long"), 10, 3, clip_end=False).collect())
    assert got == want


def test_sharded_timeline_mines_only_what_changes(spark, tmp_path):
    m = ShardedTimeline(spark, f"file://{tmp_path}/tl", 10, 2, shard_width=20)
    first = spark.createDataFrame([(t, ["a", "b"]) for t in (1, 4, 30)], "t long, items array<string>")
    second = spark.createDataFrame([(t, ["a"]) for t in (95, 99)], "t long, items array<string>")
    m.add(first, 0)
    before = list(m.mined)
    m.add(second, 1)
    assert m.mined[len(before):] == [4]
    got = sorted((r["pattern"], r["s"], r["e"]) for r in m.intervals().collect())
    assert got == [("a", 0, 11), ("a", 89, 105), ("a|b", 0, 11), ("b", 0, 11)]


def test_stream_takes_times_out_of_order_and_counts_late_ones(spark, tmp_path):
    batches = [[1, 9, 30], [5, 7, 33, 28], [31, 2, 60], [3, 29, 61, 62, 55]]  # after 33, times below 13 are late; after 60, those below 40
    for i, times in enumerate(batches):
        spark.createDataFrame([("x", t) for t in times], "pattern string, t long").coalesce(1).write.parquet(f"{tmp_path}/in/batch={i:03d}")
    stream = spark.readStream.schema("pattern string, t long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/batch=*")
    from localfreq.operators.detect import dense_intervals

    log = run_to_table(online_dense_items(stream, 10, 3, delay=20)).cache()
    late = {5, 7, 2, 3, 29}
    kept = [t for b in batches for t in b if t not in late]
    got = sorted((r["s"], r["e"]) for r in latest(log, 10).collect())
    assert got == sorted((r["s"], r["e"]) for r in dense_intervals(spark.createDataFrame([("x", t) for t in kept], "pattern string, t long"), 10, 3, clip_end=False).collect())
    assert [(r["pattern"], r["late"]) for r in late_counts(log).collect()] == [("x", len(late))]


def test_surplus_grid_against_the_miner(spark):
    import random

    from localfreq.plans import baselines, grid
    from localfreq.plans.miner import mine_dense

    rng = random.Random(3)
    tx = spark.createDataFrame([(t, sorted(x for x in "abcd" if rng.random() < (0.7 if t // 25 % 2 else 0.25))) for t in range(1, 150)], "t long, items array<string>").cache()
    ref = mine_dense(tx, 20, 8, k_max=2, min_len=2).cache()
    occ = tx.selectExpr("t", "explode(items) a").alias("l").join(tx.selectExpr("t", "explode(items) b"), "t").where("a < b").selectExpr("concat(a, '|', b) as pattern", "t").cache()
    rows, top = grid.grid_surplus_local(occ, ref, (1, 4, 1), (3, 24, 7), (1, 7, 3))
    names = {r["pattern"] for r in ref.select("pattern").collect()}
    got = {(r["max_per"], r["min_dur"], r["max_so_per"]): (r["n_pred"], r["n_common"]) for r in rows.collect()}
    best = {(r["max_per"], r["min_dur"], r["max_so_per"]): (r["f1"], r["jaccard"]) for r in top.collect()}
    assert best and {k for k in got} >= set(best)
    for per, dur, so in [(1, 3, 1), (2, 10, 4), (3, 17, 1), (4, 24, 7), (2, 3, 7)]:
        found = {r["pattern"] for r in baselines.mine_surplus_local(tx, per, dur, so, k_max=2).where("len = 2").collect()}
        assert got.get((per, dur, so), (0, 0)) == (len(found), len(found & names)), (per, dur, so)
    (per, dur, so), (f1, jaccard) = sorted(best.items())[0]
    from localfreq.operators import metrics

    score = metrics.score(baselines.mine_surplus_local(tx, per, dur, so, k_max=2).where("len = 2"), ref).first()
    assert (round(score["f1"], 6), round(score["jaccard"], 6)) == (round(f1, 6), round(jaccard, 6))


def test_baskets_have_their_lengths_when_items_are_few(spark):
    from pyspark.sql import functions as F

    from localfreq.plans import synth

    rows = synth.generate(spark, 4000, 12, 10, patterns=0)
    assert rows.where(F.size("items") != F.size(F.array_distinct("items"))).count() == 0
    # lengths are normal around 10 with deviation 10 / 3, cut at 0 and 12
    assert abs(rows.agg(F.avg(F.size("items"))).first()[0] - 9.46) < 0.2


def test_stage_costs_from_an_event_log(spark, tmp_path):
    import json

    from localfreq.plans import cost

    def task(stage, finish, ms, written=0, spilled=0, read=0):
        return {"Event": "SparkListenerTaskEnd", "Stage ID": stage, "Task Info": {"Launch Time": finish - ms, "Finish Time": finish}, "Task Metrics": {
            "Executor Run Time": ms, "Disk Bytes Spilled": spilled, "Shuffle Write Metrics": {"Shuffle Bytes Written": written},
            "Shuffle Read Metrics": {"Remote Bytes Read": read, "Local Bytes Read": 1}}}

    lost = {"Event": "SparkListenerTaskEnd", "Stage ID": 2, "Task Info": {"Launch Time": 1, "Finish Time": 50}}
    events = [{"Event": "SparkListenerApplicationStart", "App Name": "x"}, task(1, 10, 1000, written=5), task(1, 20, 2000, written=7, spilled=3), task(1, 30, 6000, read=4), lost, task(3, 99, 1)]
    (tmp_path / "log").write_text("\n".join(map(json.dumps, events)))
    got = sorted(map(tuple, cost.stage_costs(spark, str(tmp_path / "log"), until=60).collect()))
    assert got == [(1, 3, 12, 7, 3, 9.0, 2.0, 6.0, 3.0), (2, 1, 0, 0, 0, 0.0, 0.0, 0.0, None)]


def test_grids_hand_on_no_copy_a_setting(spark):
    """What leaves a pattern's pass is at most a row a setting, however many occurrences and runs there are, and equals one run a setting."""
    from localfreq.operators import metrics
    from localfreq.plans import baselines, grid

    rows = [(p, t) for p, step in (("a|b", 3), ("a|c", 7), ("b|c", 40)) for t in range(1, 3000, step) if t // 90 % 3 != len(p + str(step)) % 3]
    occ = spark.createDataFrame(rows, "pattern string, t long")
    ref = spark.createDataFrame([("a|b", 2, 1, 700), ("a|b", 2, 500, 900), ("a|c", 2, 40, 50), ("x|y", 2, 1, 9)], "pattern string, len int, s long, e long")
    recurring = grid.grid_recurring(occ, ref, 5, 50)
    found, top = grid.grid_gap_local(occ, ref, None, [1, 10, 30], (5, 50, 5), (10, 100, 10))
    for df in (recurring, found, top):
        assert "CartesianProduct" not in df._jdf.queryExecution().toString()
    got = {r["max_per"]: tuple(r) for r in recurring.collect()}
    ordinals = spark.range(1, 3000).selectExpr("id as t", "id as ord")
    for per in range(5, 51, 5):
        pred = baselines.gap_runs(occ, per).where("n >= 5")
        want = metrics.score(pred, ref).first()
        if want["n_pred"]:
            assert got[per] == (per, want["n_pred"], want["n_common"], want["f1"], want["jaccard"], want["tp"])
    names = [c for c in top.columns]
    assert names == ["local_sup", "max_gap", "min_dur", "n_pred", "n_common", "f1", "jaccard", "tp"]
    best = top.orderBy("local_sup", "max_gap", "min_dur").collect()
    for r in (best[0], best[-1]):
        pred = baselines.gap_runs(occ, r["max_gap"], ordinals=ordinals).where(f"e - s >= {r['min_dur']} and n * 100 >= {r['local_sup']} * n_tx")
        want = metrics.score(pred, ref).first()
        assert tuple(r)[3:] == (want["n_pred"], want["n_common"], want["f1"], want["jaccard"], want["tp"])
