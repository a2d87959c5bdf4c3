"""Random cases against brute force, and the shapes of plans."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from localfreq.operators import detect, intervals, kernels
from localfreq.plans import baselines, sharded
from localfreq.schema import OCC, pattern_len, require


def brute(times, width, sigma, t_max):
    dense = [s for s in range(0, t_max - width + 1) if sum(s <= t <= s + width for t in times) >= sigma]
    out = []
    for s in dense:
        if out and out[-1][1] == s - 1:
            out[-1][1] = s
        else:
            out.append([s, s])
    return [tuple(x) for x in out]


def cases(n, seed):
    rng = random.Random(seed)
    for _ in range(n):
        t_max = rng.randint(1, 80)
        yield sorted(rng.sample(range(t_max + 1), rng.randint(1, min(40, t_max + 1)))), t_max


@pytest.mark.parametrize("width,sigma,shard", [(1, 1, 3), (5, 2, 4), (9, 3, 20), (20, 6, 7), (13, 4, None)])
def test_detection_is_brute_force(spark, width, sigma, shard):
    data = list(cases(60, width * 100 + sigma))
    for t_max in {m for _, m in data[:4]}:
        rows = [(str(i), t) for i, (x, _) in enumerate(data) for t in x if t <= t_max]
        occ = spark.createDataFrame(rows, "pattern string, t long")
        got: dict = {}
        for r in detect.dense_runs(occ, width, sigma, t_max=t_max, shard_width=shard).collect():
            got.setdefault(r["pattern"], []).append((r["s"], r["d"]))
        for i, (x, _) in enumerate(data):
            assert sorted(got.get(str(i), [])) == brute([t for t in x if t <= t_max], width, sigma, t_max)


def test_kernels_agree_and_visits_are_bounded():
    rng = random.Random(5)
    for times, t_max in cases(400, 9):
        width, sigma = rng.randint(1, 20), rng.randint(1, 6)
        if t_max < width:
            continue
        ranges = [(0, t_max - width)]
        every, n_every = kernels.scan_every(np.array(times), width, sigma, ranges)
        skip, n_skip = kernels.scan_skip(np.array(times), width, sigma, ranges)
        assert every == skip == brute(times, width, sigma, t_max)
        assert n_skip <= min(n_every, 2 * len(times) + 1)
        for start in range(t_max - width + 1):
            kept = kernels.keep_position(np.array(times), start, width, sigma)
            if kept is not None:
                assert all(sum(x <= t <= x + width for t in times) >= sigma for x in range(start, kept + 1))


def test_shard_miner_matches_brute_force():
    rng = random.Random(3)
    for _ in range(40):
        baskets = [(t, rng.sample("abcd", rng.randint(0, 4))) for t in sorted(rng.sample(range(60), 25))]
        width, sigma, t_max = rng.randint(2, 12), rng.randint(1, 4), 59
        got: dict = {}
        for p, s, d in sharded.mine_shard(baskets, width, sigma, 0, t_max - width, None):
            got.setdefault(p, []).append((s, d))
        from itertools import combinations

        for k in (1, 2, 3, 4):
            for p in combinations("abcd", k):
                times = [t for t, x in baskets if set(p) <= set(x)]
                assert got.get(p, []) == brute(times, width, sigma, t_max)


def test_point_look_up_with_nested_intervals(spark):
    ivs = spark.createDataFrame([("k", 0, 100), ("k", 5, 10), ("k", 120, 130)], "k string, s long, e long")
    points = spark.createDataFrame([("k", t) for t in (0, 50, 100, 101, 119, 120, 130, 131)], "k string, t long")
    assert sorted(r["t"] for r in intervals.covers(points, ivs, ["k"]).collect()) == [0, 50, 100, 120, 130]


def test_unsafe_criteria_keep_supersets(spark):
    """A superset that meets a criterion which one of its items fails must be found."""
    rows = [(t, ["x", "y"]) for t in (10, 11, 12, 13)] + [(t, ["x"]) for t in range(100, 400, 60)] + [(500, [])]
    tx = spark.createDataFrame(rows, "t long, items array<string>")
    found = {r["pattern"] for r in baselines.mine_partial_periodic(tx, 10, 60, 3).collect()}
    assert found == {"y", "x|y"}
    split = [(t, ["x", "y"]) for t in (0, 1, 2, 20, 21, 22)] + [(t, ["x"]) for t in range(3, 20)]
    tx = spark.createDataFrame(split, "t long, items array<string>")
    rec = {r["pattern"] for r in baselines.mine_recurring(tx, 2, 3, min_rec=2).collect()}
    assert rec == {"y", "x|y"}


def test_plans(spark):
    occ = spark.range(1000).select((F.col("id") % 7).cast("string").alias("pattern"), F.col("id").alias("t"))
    plan = detect.dense_runs(occ, 50, 3, t_max=999)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and plan.count("Sort [") <= 2
    ivs = detect.dense_intervals(occ, 50, 3, t_max=999)
    for df in (intervals.covers(occ, ivs, ["pattern"]), intervals.overlap_table(ivs, ivs, ["pattern"]), detect.interval_support(occ, occ.select("pattern", F.col("t").alias("l")), 50)):
        text = df._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in text and "CartesianProduct" not in text and "SinglePartition" not in text


def test_schema(spark):
    good = spark.createDataFrame([("a", 1)], "pattern string, t long")
    assert require(good, OCC) is good
    with pytest.raises(ValueError):
        require(good.drop("t"), OCC)
    with pytest.raises(TypeError):
        require(good.withColumn("t", F.col("t").cast("int")), OCC)
    rows = spark.createDataFrame([("a",), ("a|b",), ("x\\|y|z",), ("q\\\\|w",)], "p string")
    assert [r[0] for r in rows.select(pattern_len(F.col("p"))).collect()] == [1, 2, 2, 2]
