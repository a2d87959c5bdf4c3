"""Every registered query of the engine against its SQL, on the smallest tables."""

import os

import duckdb
import pytest

from localfreq.registry import accuracy, mining, streams, surround

DATA = "/root/testdata/sf0.001"
QUERIES = {k: f for m in (mining, accuracy, surround, streams) for k, f in m.QUERIES.items()}
ORACLES = {k: s for m in (mining, accuracy, surround, streams) for k, s in m.ORACLES.items()}
#: Long searches; the driver compares them as well.
LONG = {"grid_surplus_local", "sweep_surplus_local", "sweep_gap_local", "grid_gap_local", "mine_dense_supp_k3", "mine_dense_brand_1000", "metric_jaccard", "metric_temporal_precision", "sweep_recurring"}


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for f in os.listdir(DATA):
        if f.endswith(".parquet"):
            con.execute(f"create view {f[:-8]} as select * from '{DATA}/{f}'")
    return con


def tidy(v):
    return round(v, 5) if isinstance(v, float) else v


@pytest.mark.parametrize("name", sorted(set(QUERIES) - LONG))
def test_query(spark, db, name):
    df = QUERIES[name](spark, DATA)
    rows = sorted(repr(tuple(map(tidy, r))) for r in df.collect())
    if name not in ORACLES:
        return
    got = db.execute(ORACLES[name])
    names = [c[0] for c in got.description]
    assert sorted(names) == sorted(df.columns)
    order = [names.index(c) for c in df.columns]
    assert rows == sorted(repr(tuple(tidy(r[i]) for i in order)) for r in got.fetchall())


def test_the_rest_stands_alone():
    """Nothing outside the training-data subpackage imports it."""
    root = os.path.join(os.path.dirname(__file__), "..", "localfreq")
    for folder, _, files in os.walk(root):
        if os.path.basename(folder) != "llm":
            for f in files:
                if f.endswith(".py"):
                    with open(os.path.join(folder, f)) as text:
                        assert "localfreq.llm" not in text.read(), f
