"""Encoding, packing and token counts against the tokenizers library and brute force."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from localfreq.llm import packing, tokencount
from localfreq.llm.bpe import ByteBpe, chunk_ends, encode_decode
from localfreq.llm.wordcache import WordIds, load_tokenizer

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
ODD = ["", " ", "  a  b", "a<|endoftext|>b", "x" * 3000, "\n\n \t foo\x1c bar\x85", "it's we'll 'S", "é ñ ß İ Σς", "１２ 3½", "日本 語" * 40, "no-break here", "ab " * 900]


@pytest.fixture(scope="module")
def bpe():
    return ByteBpe(BYTE, mean=64)


@pytest.fixture(scope="module")
def words():
    return WordIds(WORD, most=50)


def same_as_library(bpe, text):
    n, decimal, raw = bpe.encode(text)
    ids = load_or(BYTE).encode(text, add_special_tokens=False).ids
    assert decimal.decode() == "".join(f"{i}," for i in ids) and n == len(ids)
    assert raw.decode("utf-8", "replace") == load_or(BYTE).decode(ids, skip_special_tokens=False)


_LOADED = {}


def load_or(path):
    return _LOADED.setdefault(path, load_tokenizer(path))


@pytest.mark.parametrize("text", ODD)
def test_odd_texts(bpe, words, text):
    same_as_library(bpe, text)
    assert words.ids(text) == np.array(load_or(WORD).encode(text, add_special_tokens=False).ids, "<u4").tobytes()


@settings(max_examples=50, deadline=None)
@given(st.lists(st.sampled_from(["the ", "thes.\n", "ing ", "Straße, ", "'s ", "  ", "x", "12 ", "é", "日", "!!", "\t", "ontion", "\xa0"]), max_size=120).map("".join))
def test_any_text(bpe, words, text):
    same_as_library(bpe, text)
    assert words.ids(text) == np.array(load_or(WORD).encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def test_chunks_follow_content(bpe):
    rng = random.Random(1)
    shared = " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(400))
    a, b = (shared.encode(), ("quite another start " + shared).encode())
    assert len(set(bpe.cut(a)) & set(bpe.cut(b))) > 0.8 * len(bpe.cut(a)) > 5
    assert b"".join(bpe.cut(b)) == b
    assert len(chunk_ends(np.zeros(10, np.uint8))) == 0


def test_encode_decode_rows(spark):
    rows = [(1, "the cat", "x"), (2, None, "y"), (2, "", "z"), (None, "the cat", "w")]
    got = encode_decode(spark.createDataFrame(rows, "doc_id long, text string, n_tokens string"), BYTE).collect()
    assert [r["doc_id"] for r in got] == [1, 2, 2, None]
    assert got[1]["n_tokens"] == 0 and got[1]["ids_sha256"] == hashlib.sha256(b"").hexdigest() == got[2]["decoded_sha256"]
    assert got[0]["ids_sha256"] == got[3]["ids_sha256"] and got[0]["decoded_sha256"] == hashlib.sha256(b"the cat").hexdigest()
    assert encode_decode(spark.createDataFrame([], "doc_id long, text string"), BYTE).count() == 0


def naive_bfd(lengths, capacity):
    bins = []
    for n in sorted(lengths, reverse=True):
        fits = [i for i, r in enumerate(bins) if r >= n]
        if fits:
            i = min(fits, key=lambda i: bins[i])
            bins[i] -= n
        else:
            bins.append(capacity - n)
    return sorted(bins)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 30), max_size=80))
def test_best_fit_decreasing(lengths):
    placed = packing.best_fit_decreasing(lengths, 30)
    used: dict = {}
    for n, (b, o) in zip(lengths, placed, strict=True):
        used.setdefault(b, []).append((o, n))
    for parts in used.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 30
    assert sorted(30 - sum(n for _, n in p) for p in used.values()) == naive_bfd(lengths, 30)


def test_packing_rows(spark):
    rng = random.Random(4)
    rows = [(i, " ".join(rng.choice(["the", "of", "ation"]) for _ in range(rng.randint(0, 60)))) for i in range(60)] + [(60, None), (61, ""), (5, "again")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    pieces = packing.checkpointed(packing.token_pieces(df, WORD, capacity=32))
    got = packing.pack_pieces(pieces, 32).collect()
    tok, want = load_or(WORD), []
    for i, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
        for k, s in enumerate(range(0, len(ids), 32)):
            part = ids[s:s + 32]
            want.append((i, k, s, len(part), zlib.crc32(np.array(part, "<u4").tobytes())))
    assert sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == sorted(want)
    bins: dict = {}
    for r in got:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in bins.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 32
    assert len(bins) == len(naive_bfd([w[3] for w in want], 32))
    assert packing.pack_pieces(packing.checkpointed(packing.token_pieces(df.limit(0), WORD)), 2048).count() == 0


@pytest.mark.parametrize("step", [1, 3, 1000])
def test_separator_scan_of_files(spark, tmp_path, step):
    docs = [[[5, 6], [], [7] * 9, [1]], [[2]], []]
    (tmp_path / "f3.bin").write_bytes(b"")
    for i, d in enumerate(docs):
        flat = [x for doc in d for x in [*doc, 9]] + ([4, 4] if i == 1 else [])
        (tmp_path / f"f{i}.bin").write_bytes(np.array(flat, "<u2").tobytes())
    blocks = tokencount.file_blocks(spark, f"file://{tmp_path}", block_tokens=step)
    got: dict = {}
    for r in tokencount.scan_separators(blocks, end_id=9).collect():
        got.setdefault(r["file"][-6:], []).append((r["ordinal"], r["start"], r["n_tokens"], r["ended"]))
    assert {k: sorted(v) for k, v in got.items()} == {
        "f0.bin": [(0, 0, 2, True), (1, 3, 0, True), (2, 4, 9, True), (3, 14, 1, True)],
        "f1.bin": [(0, 0, 1, True), (1, 2, 2, False)],
    }


def test_counts_of_documents(spark):
    rows = spark.createDataFrame([(1, "the cat sat " * 50), (2, None), (3, "<|endoftext|> x"), (4, "é")], "doc_id long, text string").coalesce(1)
    blocks = tokencount.flat_blocks(rows, BYTE, end_id=50256, block_tokens=16)
    assert blocks.count() > 5
    tok = load_tokenizer(BYTE)
    tok.encode_special_tokens = True
    got = {r["ordinal"]: r["n_tokens"] for r in tokencount.scan_separators(blocks, end_id=50256).collect()}
    assert got == {i: len(tok.encode(r["text"] or "", add_special_tokens=False).ids) for i, r in enumerate(rows.collect())}


def test_token_count_query(spark):
    """The registered query on a whole table against the library, and its places against a running sum."""
    got = tokencount.op9_token_counts(spark, "/root/testdata/sf0.001").collect()
    tok = load_tokenizer(BYTE)
    tok.encode_special_tokens = True
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()
    assert sorted((r["doc_id"], r["n_tokens"]) for r in got) == sorted((r["doc_id"], len(tok.encode(r["text"] or "", add_special_tokens=False).ids)) for r in rows)
    for name in {r["file"] for r in got}:
        at = 0
        for i, r in enumerate(sorted((x for x in got if x["file"] == name), key=lambda x: x["ordinal"])):
            assert (r["ordinal"], r["start"]) == (i, at)
            at += r["n_tokens"] + 1


def test_token_counts_of_odd_tables(spark, tmp_path):
    rows = [(None, "a b", "x"), (3, None, "y"), (3, None, "y"), (4, "word " * 200_000, "z")]
    spark.createDataFrame(rows, "doc_id long, text string, file string").write.parquet(f"{tmp_path}/a/documents.parquet")
    got = tokencount.op9_token_counts(spark, f"{tmp_path}/a").collect()
    assert sorted(r["n_tokens"] for r in got)[:3] == [0, 0, 2] and max(r["n_tokens"] for r in got) >= 200_000
    spark.createDataFrame([], "doc_id long, text string").write.parquet(f"{tmp_path}/b/documents.parquet")
    assert tokencount.op9_token_counts(spark, f"{tmp_path}/b").count() == 0
