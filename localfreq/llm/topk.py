"""Exact top-k inner products with a bit-sliced index.

Every vector is quantised to integers. A block of candidates keeps, per attribute, one bitmap for each binary
digit (a *slice*). A query's scores over a whole block come from bitmap arithmetic alone: slices weighted by
the query's digits are summed by carry-save adders, all bitmaps of one weight at a time. The best rows are then
chosen from the most significant slice of the sum downward; rows that tie at the boundary are resolved exactly
by the smaller id.

Work is dealt out as (candidate block, group of queries) cells. A cell's candidates come first in its sorted rows, so one task
indexes a block once and streams queries past it; it holds one block and nothing that grows with the data is
broadcast. Each cell yields at most k rows per query, which one window per query merges.

Vectors that are null, or hold a null or non-finite component take no part, nor do rows without an id; an empty vector scores 0.
A vector the sum of whose squared codes reaches 2**62 is an error, since its products may not fit a long; all others are exact.
Vectors shorter than the longest of their block are padded by zeros, which leaves inner products as they are.
Rows that share the query's id never appear in its result.
Repeated rows of another id each take a place; of rows that share a query's id the smallest vector asks. An empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.llm.common import read_table

__all__ = ["BitSlicedIndex", "op7_exact_topk", "quantised", "topk_inner"]


class BitSlicedIndex:
    """Bit-sliced index of integer rows: ``slices[d][j]`` marks the rows whose shifted attribute d has digit j."""

    def __init__(self, rows: np.ndarray):
        self.n, self.dims = rows.shape
        self.low = rows.min(axis=0) if self.n else np.zeros(self.dims, np.int64)
        shifted = rows - self.low
        words = -(-max(self.n, 1) // 64)
        self.slices = []
        for d in range(self.dims):
            digits = max(1, int(shifted[:, d].max(initial=0)).bit_length())
            bits = (shifted[:, d][None, :] >> np.arange(digits)[:, None] & 1).astype(np.uint8)
            packed = np.zeros((digits, words * 8), np.uint8)
            p = np.packbits(bits, axis=1, bitorder="little")
            packed[:, :p.shape[1]] = p
            self.slices.append(packed.view(np.uint64))
        self.full = np.zeros(words * 8, np.uint8)
        p = np.packbits(np.ones(self.n, np.uint8), bitorder="little")
        self.full[:len(p)] = p
        self.full = self.full.view(np.uint64)
        self.digits = np.array([len(s) for s in self.slices])
        self.stacked = np.concatenate(self.slices) if self.slices else np.zeros((0, words), np.uint64)
        self.inverse = self.full & ~self.stacked
        self.starts = np.concatenate([[0], np.cumsum(self.digits)])
        #: Per attribute, what a complemented code stands for: (2**digits - 1) - code.
        self.top = (1 << self.digits.astype(object)) - 1

    def scores(self, query: np.ndarray) -> tuple[list[np.ndarray], int]:
        """(sum's slices from least to most significant, what to add to the coded sum)."""
        add = sum(int(q) * int(x) for q, x in zip(query, self.low, strict=True))
        piles: dict[int, list[int]] = {}
        for d in np.flatnonzero(query):
            q, at, width = int(query[d]), int(self.starts[d]), int(self.digits[d])
            shift = 0
            if q < 0:  # q * code = |q| * (complemented code) - |q| * top
                q, shift = -q, len(self.stacked)
                add -= q * int(self.top[d])
            b = 0
            while q:
                if q & 1:
                    for j in range(width):
                        piles.setdefault(b + j, []).append(shift + at + j)
                q, b = q >> 1, b + 1
        out: list[np.ndarray] = []
        carried: np.ndarray | None = None
        w = 0
        last = max(piles, default=-1)
        m = len(self.stacked)
        while w <= last or carried is not None:
            picks = piles.get(w, [])
            plain, turned = [i for i in picks if i < m], [i - m for i in picks if i >= m]
            parts = [x for x in (self.stacked[plain] if plain else None, self.inverse[turned] if turned else None, carried) if x is not None]
            pile = np.concatenate(parts) if parts else np.zeros((0, len(self.full)), np.uint64)
            carries = []
            while len(pile) > 1:  # carry-save: three bitmaps become a sum and a carry, all triples at once
                t = len(pile) // 3
                if t:
                    a, b, c = pile[:t], pile[t:2 * t], pile[2 * t:3 * t]
                    x = a ^ b
                    carries.append((a & b) | (c & x))
                    pile = np.concatenate([x ^ c, pile[3 * t:]])
                else:
                    carries.append((pile[0] & pile[1])[None])
                    pile = (pile[0] ^ pile[1])[None]
            out.append(pile[0] if len(pile) else np.zeros_like(self.full))
            carried = np.concatenate(carries) if carries else None
            w += 1
        return out, add

    def top_rows(self, slices: list[np.ndarray], k: int, allowed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rows surely in the top k, rows tied at the boundary), as row numbers."""
        sure, maybe = np.zeros_like(self.full), allowed.copy()
        for s in reversed(slices):
            with_digit = maybe & s
            n = int(np.bitwise_count(sure | with_digit).sum())
            if n > k:
                maybe = with_digit
            else:
                sure = sure | with_digit
                maybe = maybe & ~s
                if n == k:
                    maybe = np.zeros_like(maybe)
                    break
        return self.rows(sure), self.rows(maybe)

    def rows(self, bitmap: np.ndarray) -> np.ndarray:
        return np.flatnonzero(np.unpackbits(bitmap.view(np.uint8), bitorder="little")[:self.n])

    def values(self, slices: list[np.ndarray], rows: np.ndarray) -> np.ndarray:
        if not len(rows):
            return np.zeros(0, np.int64)
        word, bit = rows >> 6, (rows & 63).astype(np.uint64)
        kind = np.int64 if len(slices) < 63 else object  # coded sums may be wider than the scores
        return sum(((s[word] >> bit) & np.uint64(1)).astype(np.int64).astype(kind) << w for w, s in enumerate(slices)) + np.zeros(len(rows), kind)


def quantised(df: DataFrame, *, vec_id: str = "vec_id", embedding: str = "embedding", scale: int = 64) -> DataFrame:
    """(vec_id, code array<int>) of the vectors that take part."""
    x = F.col(embedding).cast("array<double>")
    finite = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    code = F.transform(x, lambda v: F.floor(v * scale).cast("long"))
    size = F.aggregate(x, F.lit(0.0), lambda s, v: s + F.pow(F.floor(v * scale).cast("double"), 2))
    wide = F.raise_error("a vector is too long for exact products in 64 bits").cast("array<bigint>")
    rows = df.where(F.col(vec_id).isNotNull() & F.col(embedding).isNotNull()).where(finite)
    return rows.select(F.col(vec_id).cast("long").alias("vec_id"), F.when(size < float(1 << 62), code).otherwise(wide).alias("code"))


def _matrix(codes: pa.Array, width: int) -> np.ndarray:
    """Rows of codes, padded by zeros."""
    many = np.diff(codes.offsets.to_numpy()) if len(codes) else np.zeros(0, np.int64)
    flat = codes.flatten().to_numpy(zero_copy_only=False)
    out = np.zeros((len(codes), max(width, int(many.max(initial=0)))), np.int64)
    place = np.arange(len(flat)) - np.repeat(np.cumsum(many) - many, many)
    out[np.repeat(np.arange(len(codes)), many), place] = flat
    return out


class _Cell:
    """The index of one block of candidates, in the order of their ids."""

    def __init__(self, parts: list[tuple[np.ndarray, pa.Array]]):
        self.ids = np.concatenate([i for i, _ in parts]) if parts else np.zeros(0, np.int64)
        rows = [_matrix(c, 0) for _, c in parts]
        self.width = max((r.shape[1] for r in rows), default=0)
        self.index = BitSlicedIndex(np.concatenate([np.pad(r, ((0, 0), (0, self.width - r.shape[1]))) for r in rows]) if rows else np.zeros((0, 0), np.int64))

    def best(self, mine: int, query: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of the k best rows of other ids."""
        index, ids = self.index, self.ids
        slices, add = index.scores(query[:self.width])
        allowed = index.full
        lo, hi = np.searchsorted(ids, mine, side="left"), np.searchsorted(ids, mine, side="right")
        if hi > lo:
            allowed = allowed.copy()
            own = np.arange(lo, hi)
            np.bitwise_and.at(allowed, own >> 6, ~(np.uint64(1) << (own & 63).astype(np.uint64)))
        sure, tied = index.top_rows(slices, k, allowed)
        rows = np.concatenate([sure, tied[:max(0, k - len(sure))]]).astype(np.int64)
        return ids[rows], (index.values(slices, rows) + add).astype(np.int64)


def topk_inner(candidates: DataFrame, queries: DataFrame, k: int = 20, *, block: int = 8192) -> DataFrame:
    """The k candidates of highest inner product for each query, both as (vec_id, code) frames; queries have one row an id.

    Blocks hold about ``block`` candidates, whatever their number. Equal rows, however many, are counted before they are dealt by
    their hash, and stand for at most k places. Few blocks are met by several groups of queries, so that all cores have work.
    """
    same = candidates.groupBy("vec_id", "code").agg(F.count(F.lit(1)).alias("n"))
    n = candidates.count()
    blocks = max(1, math.ceil(n / block))
    groups = max(1, math.ceil(2 * candidates.sparkSession.sparkContext.defaultParallelism / blocks))
    place = lambda seed, parts: F.pmod(F.xxhash64(F.lit(seed), "vec_id", "code"), F.lit(parts)).cast("int")
    times = F.explode(F.array_repeat(F.lit(0), F.least("n", F.lit(k)).cast("int")))
    left = same.select("vec_id", "code", place(1, blocks).alias("block"), times.alias("kind")).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    right = queries.select("vec_id", "code", place(2, groups).alias("part"), F.lit(1).alias("kind")).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    columns = ["block", "part", "kind", "vec_id", "code"]
    cells = left.select(*columns).unionByName(right.select(*columns)).repartition(blocks * groups, "block", "part").sortWithinPartitions("block", "part", "kind", "vec_id")

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, parts, cell = None, [], None
        for b in rows:
            block, part, kind, ids = (b.column(i).to_numpy() for i in range(4))
            cuts = np.flatnonzero((block[1:] != block[:-1]) | (part[1:] != part[:-1]) | (kind[1:] != kind[:-1])) + 1
            for i, j in zip([0, *cuts.tolist()], [*cuts.tolist(), b.num_rows], strict=True):
                if i == j:
                    continue
                if (block[i], part[i]) != at:
                    at, parts, cell = (block[i], part[i]), [], None
                if kind[i] == 0:
                    parts.append((ids[i:j].copy(), b.column(4).slice(i, j - i)))
                    continue
                if cell is None:
                    cell, parts = _Cell(parts), []
                found = [(q, *cell.best(int(q), code, k)) for q, code in zip(ids[i:j], _matrix(b.column(4).slice(i, j - i), cell.width), strict=True)]
                many = [len(x[1]) for x in found]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat([x[0] for x in found], many)), *(pa.array(np.concatenate([x[c] for x in found])) for c in (1, 2))], ["query_id", "vec_id", "score"])

    found = cells.mapInArrow(run, "query_id long, vec_id long, score long")
    by = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op7_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quantised(read_table(spark, sf_dir, "embeddings"))
    return topk_inner(rows, rows.where(F.pmod("vec_id", F.lit(20)) == 0).groupBy("vec_id").agg(F.min("code").alias("code")), 20)
