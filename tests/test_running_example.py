"""The worked example of ten-wide windows, three occurrences and 25 as the last time."""

import pytest
from pyspark.sql import functions as F

from localfreq.operators import baskets, detect, kernels
from localfreq.plans import miner, sharded

ROWS = [(1, "ab"), (3, "abc"), (5, "bc"), (7, "abc"), (9, "ab"), (20, "abc"), (22, "bc"), (25, "abc")]
W, S, LAST = 10, 3, 25
DENSE = {"a": [(0, 13)], "b": [(0, 15), (15, 25)], "c": [(0, 13), (15, 25)], "a|b": [(0, 13)], "b|c": [(0, 13), (15, 25)]}


@pytest.fixture(scope="module")
def tx(spark):
    return spark.createDataFrame([(t, list(x)) for t, x in ROWS], "t long, items array<string>")


def as_dict(df):
    out = {}
    for r in df.collect():
        out.setdefault(r["pattern"], []).append((r["s"], r["e"]))
    return {k: sorted(v) for k, v in out.items()}


@pytest.mark.parametrize("restrict", ["none", "items", "parents"])
def test_level_wise(tx, restrict):
    assert as_dict(miner.mine_dense(tx, W, S, restrict=restrict)) == DENSE


def test_sharded(tx):
    for c in (3, 7, 50):
        assert as_dict(sharded.mine_dense_sharded(tx, W, S, shard_width=c)) == DENSE


def test_ends_not_cut(tx):
    found = as_dict(detect.dense_intervals(baskets.to_occurrences(tx), W, S, clip_end=False))
    assert found == {"a": [(0, 13)], "b": [(0, 15), (15, 30)], "c": [(0, 13), (15, 30)]}


def test_supports(spark, tx):
    pairs = baskets.occurrences_of(tx, ["a", "b"]).select(F.lit("a|b").alias("pattern"), "t")
    assert sorted(r["t"] for r in pairs.collect()) == [1, 3, 7, 9, 20, 25]
    asked = spark.createDataFrame([("a|b", 1), ("a|b", 4), ("a|b", 15)], "pattern string, l long")
    got = {r["l"]: (r["sup"], r["is_dense"]) for r in detect.dense_windows(pairs, asked, W, S).collect()}
    assert got == {1: (4, 1), 4: (2, 0), 15: (2, 0)}


def test_kernels(tx):
    occ = baskets.to_occurrences(tx)
    for kernel in ("every", "skip"):
        rows = kernels.scan_by_pattern(occ, W, S, t_max=LAST, kernel=kernel).where("s is not null").withColumn("e", F.col("d") + W)
        assert as_dict(rows) == {k: v for k, v in DENSE.items() if "|" not in k}


def test_checks_and_shapes(tx):
    res = miner.mine_dense(tx, W, S)
    assert miner.check_monotone(res).count() == 0
    assert {r["pattern"] for r in miner.maximal_patterns(res).collect()} == {"a|b", "b|c"}
    assert {k: [(x["s"], x["e"]) for x in v] for k, v in miner.as_map(res).first()["patterns"].items()} == DENSE


def test_edges(spark):
    empty = spark.createDataFrame([], "t long, items array<string>")
    assert miner.mine_dense(empty, W, S).count() == 0
    short = spark.createDataFrame([(0, ["x"]), (3, ["x"])], "t long, items array<string>")
    assert miner.mine_dense(short, 10, 1).count() == 0  # the last time is less than the width
    assert as_dict(miner.mine_dense(short, 3, 2)) == {"x": [(0, 3)]}
    assert as_dict(miner.mine_dense(short, 1, 1)) == {"x": [(0, 1), (2, 3)]}
    hollow = spark.createDataFrame([(0, []), (5, ["x|y", "z"]), (9, [])], "t long, items array<string>")
    assert as_dict(miner.mine_dense(hollow, 2, 1)) == {"x\\|y": [(3, 7)], "x\\|y|z": [(3, 7)], "z": [(3, 7)]}
    with pytest.raises(ValueError):
        detect.dense_runs(baskets.to_occurrences(short), 0, 1)
