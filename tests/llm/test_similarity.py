"""Similarity join, fingerprints and top-k against brute force."""

import random
import re
from unittest.mock import Mock

import numpy as np
import pytest
from pyspark.sql import functions as F

from localfreq.llm import common, fingerprint, simjoin, topk

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text, width):
    w = WORD.findall((text or "").translate(LOWER))
    return {tuple(w[i:i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())


def brute(rows, width, percent):
    sets = [shingles(t, width) for _, t in rows]
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                parent[find(i)] = find(j)
    least: dict = {}
    for i, (d, _) in enumerate(rows):
        least.setdefault(find(i), []).append(d)
    return sorted((d, len(sets[i]), min(least[find(i)])) for i, (d, _) in enumerate(rows))


def corpus(seed, n=140):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(60)] + ["É", "Ünd", "THE"]
    rows, texts = [], []
    for i in range(n):
        if texts and rng.random() < 0.7:
            w = rng.choice(texts[-20:]).split()
            for _ in range(rng.choice([0, 1, 1, 2, 3, 8])):
                if w:
                    w[rng.randrange(len(w))] = rng.choice(vocabulary)
            if rng.random() < 0.3:
                w = w[: len(w) - rng.randint(0, 6)]
        else:
            w = [rng.choice(vocabulary) for _ in range(rng.choice([0, 1, 2, 3, 5, 12, 60, 150]))]
        texts.append(" ".join(w))
        rows.append((i * 3, rng.choice([str.upper, str])(texts[-1]) if rng.random() < 0.2 and "É" not in texts[-1] else texts[-1]))
    return rows


def test_join_is_exact(spark):
    for seed, width, percent in ((1, 4, 85), (2, 5, 80), (3, 2, 60)):
        rows = corpus(seed) + [(1000, ""), (1001, " \t\n"), (1002, None)]
        got = simjoin.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), width=width, percent=percent)
        assert sorted(map(tuple, got.collect())) == brute(rows, width, percent)


def test_join_edges(spark):
    schema = "doc_id long, text string, node string, label string"
    rows = [(7, "a b c d e f", "x", "y"), (7, "a b c d e f", "x", "y"), (None, "a b c d e f", None, None), (9, "z", "", ""), (11, None, None, None)]
    df = spark.createDataFrame(rows, schema)
    got = sorted(map(tuple, simjoin.jaccard_components(df).collect()), key=str)
    assert got == sorted([(7, 2, 7), (7, 2, 7), (None, 2, 7), (9, 1, 9), (11, 0, 11)], key=str)
    kept = simjoin.keep_one(df).collect()
    assert sorted((r["doc_id"] for r in kept), key=str) == sorted([7, 9, 11], key=str)
    assert simjoin.jaccard_components(df.limit(0)).count() == 0
    assert simjoin.keep_one(df.limit(0)).count() == 0


def test_join_with_hot_signatures_and_long_buckets(spark):
    """Parts of a signature dealt over many keys, and buckets read in pieces, lose no link."""
    rows = corpus(4, 220)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute(rows, 4, 80)
    for sizes in ({"hot": 3, "held": 40}, {"long": 2}, {"hot": 3, "held": 40, "long": 2}):
        assert sorted(map(tuple, simjoin.jaccard_components(df, width=4, percent=80, **sizes).collect())) == want


def test_join_with_buckets_of_many_blocks(spark, monkeypatch):
    """Buckets too large for one block, whose blocks meet by joins, lose no link."""
    monkeypatch.setattr(simjoin, "_BLOCK", 2)
    rows = corpus(5, 160)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(map(tuple, simjoin.jaccard_components(df, width=2, percent=60).collect())) == brute(rows, 2, 60)


def test_keep_one_judges_rows(spark):
    """Repeated ids of different texts are judged each on its own; equal rows leave one; clashing columns stay as they are."""
    text = " ".join(f"w{i}" for i in range(40))
    rows = [(1, text, "a"), (5, text, "b"), (5, "quite another text of nine words stands here alone", "c"), (6, "one two three four five six", "d"), (6, "one two three four five six", "d"), (None, text.upper(), "e"), (None, None, "f"), (None, "", "f"), (8, "short", "g"), (9, "SHORT", "h")]
    df = spark.createDataFrame(rows, "doc_id long, text string, node string")
    got = sorted(map(tuple, simjoin.keep_one(df).collect()), key=str)
    assert got == sorted([rows[0], rows[2], rows[3], rows[6], rows[7], rows[8]], key=str)


@pytest.mark.parametrize("bits", [0, 1 << 28])
def test_keep_one_agrees_with_brute_force_with_and_without_its_filter(spark, monkeypatch, bits):
    monkeypatch.setattr(simjoin, "_FILTER", bits)
    rows = corpus(23)
    rows += [(None, rows[5][1]), (None, "a text of its own without any id"), (6, "another text under an id that is there"), (-(1 << 63), "the least id")]
    kept = {(r["doc_id"], r["text"]) for r in simjoin.keep_one(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()}
    told = brute([(i, t) for i, (_, t) in enumerate(rows)], 5, 80)
    first: dict = {}
    for i, n, c in told:
        if n:
            first.setdefault(c, []).append((rows[i][0] is None, rows[i][0] or 0, i))
    assert kept == {rows[min(x)[2]] for x in first.values()} | {rows[i] for i, n, _ in told if not n}


def test_id_filter_passes_all_ids_and_few_others(spark):
    ids = spark.range(-3_000, 3_000, 3).selectExpr("id * 7919 as k")
    passed = lambda bitmap, df: sum(simjoin._may_be(bitmap, df.select(simjoin._id_hash(F.col(df.columns[0])).alias("h")).toArrow().column(0).combine_chunks()).to_pylist())
    bitmap = simjoin._id_filter(ids)
    assert passed(bitmap, ids) == ids.count()
    assert passed(bitmap, spark.range(10_000_000, 10_020_000)) < 2_000
    assert passed(simjoin._id_filter(ids.where("k is null")), spark.range(100)) == 0


def test_near_copies_leave_most_texts_where_they_are(spark):
    """2 MB of texts, 6 of them copies: before, a plan without broadcasts exchanged all texts twice."""
    rng = random.Random(8)
    rows = [(i, " ".join(f"{rng.getrandbits(40):x}" for _ in range(900))) for i in range(200)]
    rows += [(1000 + i, rows[i][1] + " more") for i in range(6)]
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway

    def exchanged() -> int:
        stages = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
        return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))

    before, limit = exchanged(), spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        signatures = simjoin._signatures(spark.createDataFrame(rows, "doc_id long, text string"), 5, 80).count()
        assert simjoin.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).count() == 200
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    assert exchanged() - before - 20 * signatures < 1_000_000


@pytest.mark.parametrize(("heap", "collections"), [(400, 0), (600, 1)])
def test_a_grown_driver_collects_its_garbage_between_steps(spark, monkeypatch, heap, collections):
    runtime = Mock(**{"totalMemory.return_value": heap, "maxMemory.return_value": 1000})
    driver = Mock(**{"sparkContext._jvm.java.lang.Runtime.getRuntime.return_value": runtime})
    collect = common.collect_garbage
    monkeypatch.setattr(common, "collect_garbage", lambda session: collect(driver))
    for n, step in enumerate((common.Scratch(spark).keep, common.checkpointed), 1):
        assert step(spark.range(10)).count() == 10
        assert runtime.gc.call_count == n * collections


def test_buckets_of_two_are_not_gathered_where_sketches_decide(spark):
    """Two unlike texts share a part: their bucket is decided by the sketches of the first step."""
    rows = spark.createDataFrame([(0, 1, 10, 10), (0, 1, 11, 10)] + [(1, 2, n, 20) for n in (20, 21, 22)], "home int, sig long, node long, lead long")
    shared = simjoin._shared(rows.select("sig", "node", F.lit(None).cast("long").alias("home")))
    assert {(r["node"], r["two"]) for r in shared.collect()} == {(10, True), (11, True), (20, False), (21, False), (22, False)}


def test_join_on_a_whole_table(spark):
    """All of the documents of a given table against all pairs of them."""
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()]
    got = simjoin.op2_ngram_jaccard_join(spark, "/root/testdata/sf0.01")
    assert sorted(map(tuple, got.collect())) == brute(rows, 4, 85)


def test_similar_sets_share_a_signature():
    rng = np.random.default_rng(2)
    for percent in (60, 80, 85, 95):
        bands = simjoin.Bands(percent)
        for _ in range(200):
            n = int(rng.integers(1, 300))
            a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
            drop = int(len(a) * (1 - percent / 100) * rng.random())
            extra = int((len(a) - drop) * (100 - percent) / percent) if rng.random() < 0.5 else 0
            b = np.unique(np.concatenate([rng.permutation(a)[drop:], rng.integers(0, 2**63, max(0, extra - drop)).astype(np.uint64)]))
            both = len(np.intersect1d(a, b))
            if 100 * both >= percent * (len(a) + len(b) - both) and not np.array_equal(a, b):
                sa, sb = ({int(y) for part in bands.signatures(x) for y in part} for x in (a, b))
                assert sa & sb
            apart = np.bitwise_count(np.bitwise_xor(*(simjoin._folded([s], 8)[0] for s in map(simjoin.sketch, (a, b))))).sum()
            assert apart <= len(np.setxor1d(a, b))


def test_words_as_by_pattern():
    import pyarrow as pa

    texts = ["A b\x0bc d", "", "É É", None, "x" * 5000, "a\x1fb c", " lead trail "]
    raw, starts = simjoin.string_bytes(pa.array(texts))
    s, e = simjoin.word_spans(raw, starts)
    assert [bytes(raw[a:b]).decode() for a, b in zip(s, e, strict=True)] == [w for t in texts for w in WORD.findall(t or "")]


def test_fingerprints(spark, tmp_path):
    folder = str(tmp_path)
    a, b = "One is.\nTwo was. Three!\n" * 30 + "End.", "Other text.\nWith lines. Of its own!\n" * 30
    rows = [(5, a), (3, b), (8, a), (1, None), (9, "Two was. One is."), (10, "One is. Two was."), (11, ""), (None, "x")]
    spark.createDataFrame(rows, "doc_id long, text string").write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    got = {r["doc_id"]: r for r in fingerprint.op4_document_fingerprints(spark, folder).collect()}
    assert len(got) == len(rows)
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0)))
    import hashlib

    for i, (d, t) in enumerate(order):
        t, nxt = t or "", order[(i + 1) % len(order)][1] or ""
        k = len(t) // 3
        edited = t[:len(t) - k] + nxt[:k] if k else t
        assert got[d]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest() and got[d]["n_chars"] == len(t)
    assert got[5]["fingerprint"] == got[8]["fingerprint"] != got[3]["fingerprint"]
    assert got[9]["fingerprint"] == got[10]["fingerprint"]
    assert got[1]["fingerprint"] == got[11]["fingerprint"] and got[11]["near_edited"] == 1.0
    assert got[8]["near_next"] == 1.0 and got[5]["near_next"] < 0.4 and 0.4 < got[5]["near_edited"] < 0.95


def test_topk_is_exact(spark):
    rng = np.random.default_rng(7)
    vecs = [(int(i), [float(x) for x in rng.normal(0, 0.3, 16).astype(np.float32)]) for i in range(90)]
    vecs += [(201, vecs[3][1])] * 30 + [(400, []), (401, [1.0]), (402, [])] + [(200 + i, vecs[3][1]) for i in range(8)] + [(300, [0.1, None]), (301, [float("nan")] * 16), (302, None), (303, [float("inf")] * 16), (None, vecs[0][1]), (20, vecs[5][1])]
    df = spark.createDataFrame(vecs, "vec_id long, embedding array<float>")
    rows = topk.quantised(df)
    queries = rows.where(F.pmod("vec_id", F.lit(20)) == 0).groupBy("vec_id").agg(F.min("code").alias("code"))
    got = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in topk.topk_inner(rows, queries, 20, block=40).collect())
    ok = [(i, np.floor(64 * np.array(v, np.float64)).astype(int)) for i, v in vecs if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    ok = [(i, np.pad(c, (0, 16 - len(c)))) for i, c in ok]
    want = []
    for q in sorted({i for i, _ in ok if i % 20 == 0}):
        code = min(tuple(c) for i, c in ok if i == q)
        best = sorted((-int(np.dot(c, code)), i) for i, c in ok if i != q)[:20]
        want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(best)]
    assert got == sorted(want)
    assert topk.topk_inner(rows.limit(0), queries.limit(0), 20).count() == 0


def test_topk_of_large_components(spark):
    rows = [(20, [1e6, 1.0]), (1, [1e6, 0.0]), (2, [5e5, 0.0]), (3, [-1e6, 2.0])]
    code = topk.quantised(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    got = topk.topk_inner(code, code.where("vec_id = 20"), 20).orderBy("rank").collect()
    assert [(r["vec_id"], r["score"]) for r in got] == [(1, 4096000000000000), (2, 2048000000000000), (3, -4096000000000000 + 64 * 128)]
    with pytest.raises(Exception, match="too long"):
        topk.quantised(spark.createDataFrame([(1, [1e300])], "vec_id long, embedding array<double>")).collect()


def test_topk_query_on_a_whole_table(spark):
    rows = [(r["vec_id"], np.floor(64 * np.array(r["embedding"], float)).astype(int)) for r in spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").collect()]
    got = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in topk.op7_exact_topk(spark, "/root/testdata/sf0.001").collect())
    want = []
    for q, code in rows:
        if q % 20 == 0:
            best = sorted((-int(np.dot(c, code)), i) for i, c in rows if i != q)[:20]
            want += [(q, r + 1, i, -x) for r, (x, i) in enumerate(best)]
    assert got == sorted(want)


def test_fingerprints_of_a_hot_id(spark, tmp_path):
    """An id that holds most rows is cut by its texts' hashes: every row is there once, with one next text each."""
    from collections import Counter

    rows = [(7, f"text {i}. Of one id.") for i in range(60)] + [(i, f"other {i}. Text.") for i in range(100, 110)] + [(None, "null one"), (None, "null two")] + [(7, "text 3. Of one id.")]
    spark.createDataFrame(rows, "doc_id long, text string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    paired = fingerprint.with_next(spark.read.parquet(f"{tmp_path}/documents.parquet"), 16).where("ghost = 0").collect()
    assert Counter((r["doc_id"], r["text"]) for r in paired) == Counter(rows)
    assert Counter(r["next_text"] for r in paired) == Counter(t for _, t in rows)
    assert len({r["bucket"] for r in paired if r["doc_id"] == 7}) > 4
    assert fingerprint.op4_document_fingerprints(spark, str(tmp_path)).count() == len(rows)
    spark.createDataFrame([], "doc_id long, text string").write.parquet(f"{tmp_path}/none/documents.parquet")
    assert fingerprint.op4_document_fingerprints(spark, f"{tmp_path}/none").count() == 0


def test_fingerprints_change_by_paragraphs(spark):
    """Inserting and deleting paragraphs gives the fingerprint of the changed document, without reading it again."""
    unit = lambda rows: fingerprint.fingerprint_sums(spark.createDataFrame(rows, "doc_id long, unit string"), ["doc_id"], "unit")
    before = [(1, u) for u in ("a", "b", "b", "c")] + [(2, "x")]
    now = fingerprint.changed_sums(unit(before), unit([(1, "d"), (3, "new")]), unit([(1, "b"), (1, "c")]), ["doc_id"])
    after = unit([(1, u) for u in ("d", "b", "a")] + [(2, "x"), (3, "new")])
    got, want = ({r["doc_id"]: r["f"] for r in x.select("doc_id", fingerprint.fingerprint_of().alias("f")).collect()} for x in (now, after))
    assert got == want and len(set(got.values())) == 3
