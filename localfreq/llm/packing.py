"""Best-fit-decreasing packing of token pieces into sequences.

Best fit decreasing takes pieces from long to short and puts each into the open bin that it fits most tightly.
Pieces of one length are alike to it, so the whole corpus is packed exactly from its histogram of lengths, which
never has more entries than a sequence has tokens. A segment tree over remaining capacities finds the tightest
capacity that has open bins in logarithmic time; bins of one capacity are kept as ranges of numbers, so that runs of
equal pieces are placed at once. The plan (blocks of equal pieces) is bounded by the capacity, not by the corpus,
and goes to the executors, where each piece finds its block by its length and its rank among pieces of that length.

Ranks need no shuffle of one length into one task: each input task counts lengths as it goes, and one small table
of (task, length) counts gives the offsets. The pieces' metadata is checkpointed, so that ranks stay the same when an executor is lost.

Empty and null texts are one piece of the end token. Repeated rows and ids are packed row by row. An empty
table gives an empty result. Only documents over the capacity are cut.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.llm.common import batches, checkpointed, read_table, texts_of, trim
from localfreq.llm.wordcache import WordIds

__all__ = ["BinTree", "best_fit_decreasing", "op3_best_fit_packing", "pack_pieces", "plan_blocks", "token_pieces"]


class BinTree:
    """Segment tree over remaining capacities 0..size: the least capacity of at least x that has open bins."""

    def __init__(self, size: int):
        self.leaves = 1 << size.bit_length()
        self.open = [0] * (2 * self.leaves)

    def add(self, capacity: int, n: int) -> None:
        i = self.leaves + capacity
        while i:
            self.open[i] += n
            i >>= 1

    def tightest(self, least: int) -> int | None:
        i = self.leaves + least
        if self.open[i]:
            return least
        while i > 1:
            if not i & 1 and self.open[i + 1]:
                i += 1
                while i < self.leaves:
                    i = 2 * i if self.open[2 * i] else 2 * i + 1
                return i - self.leaves
            i >>= 1
        return None


def plan_blocks(histogram: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int, int]]:
    """Blocks (length, first rank, pieces, first bin, pieces a bin, offset of a bin's first piece), best fit decreasing.

    Piece r of a block goes to bin ``first + (r - rank) // each`` at ``offset + (r - rank) % each * length``.
    """
    tree, ranges, bins, out = BinTree(capacity), {}, 0, []
    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            room = tree.tightest(length)
            if room is None:
                each = capacity // length
                n = -(-left // each)
                first, room, bins = bins, capacity, bins + n
                held = n
            else:
                first, held = ranges[room].popleft()
                tree.add(room, -held)
            each = room // length
            used = min(held, -(-left // each))
            if used < held:
                ranges.setdefault(room, deque()).appendleft((first + used, held - used))
                tree.add(room, held - used)
            taken = min(left, used * each)
            out.append((length, rank, taken, first, each, capacity - room))
            whole, part = divmod(taken, each)
            for start, n, rest in ((first, whole, room - each * length), (first + whole, 1 if part else 0, room - part * length)):
                if n and rest:
                    ranges.setdefault(rest, deque()).append((start, n))
                    tree.add(rest, n)
            left, rank = left - taken, rank + taken
    return out


def best_fit_decreasing(lengths: list[int], capacity: int) -> list[tuple[int, int]]:
    """(bin, offset) of each piece, on the driver; for small inputs and tests."""
    seen: dict[int, list[int]] = {}
    for i, n in enumerate(lengths):
        seen.setdefault(n, []).append(i)
    out = [(-1, -1)] * len(lengths)
    for length, rank, taken, first, each, offset in plan_blocks({n: len(v) for n, v in seen.items()}, capacity):
        for r in range(taken):
            out[seen[length][rank + r]] = (first + r // each, offset + r % each * length)
    return out


def token_pieces(df: DataFrame, path: str, *, capacity: int = 2048, end_id: int = 0, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, task, rank): pieces with their rank among the task's pieces of that length."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, task, counts = WordIds(path), TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        end = np.array([end_id], "<u4").tobytes()
        for b in batches(rows):
            owner, piece, start, length, crc = [], [], [], [], []
            for i, t in enumerate(texts_of(b.column(1))):
                raw = memoryview(words.ids(t) + end)
                for k, s in enumerate(range(0, len(raw), 4 * capacity)):
                    part = raw[s:s + 4 * capacity]
                    owner.append(i)
                    piece.append(k)
                    start.append(s // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            n = np.array(length, np.int64)
            order = np.argsort(n, kind="stable")
            ordered = n[order]
            ranks = np.empty(len(n), np.int64)
            ranks[order] = np.arange(len(n)) - np.searchsorted(ordered, ordered) + counts[ordered]
            counts += np.bincount(n, minlength=capacity + 1)
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pa.array(owner, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(n), pa.array(crc, pa.int64()), pa.array(np.full(len(n), task, np.int32)), pa.array(ranks)],
                ["doc_id", "piece", "start", "length", "ids_crc32", "task", "rank"],
            )
        del words  # before memory goes back: a kept worker would hold the place of the vocabulary
        trim()

    return df.select(df[doc_id].cast("long").alias("doc_id"), df[text].cast("string").alias("text")).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, task int, rank long")


def pack_pieces(pieces: DataFrame, capacity: int = 2048) -> DataFrame:
    """Adds sequence_id and offset to (…, length, task, rank) rows. ``pieces`` must be stable when read twice.

    The driver sees only the histogram of lengths (at most ``capacity`` rows) and the plan.
    """
    spark = pieces.sparkSession
    counts = pieces.groupBy("length", "task").agg(F.count(F.lit(1)).alias("n"))
    before = counts.select("length", "task", (F.sum("n").over(Window.partitionBy("length").orderBy("task")) - F.col("n")).alias("before"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    blocks = np.array(plan_blocks(histogram, capacity), np.int64).reshape(-1, 6)
    blocks = blocks[np.lexsort((blocks[:, 1], blocks[:, 0]))]
    shared = spark.sparkContext.broadcast(blocks)
    ranked = pieces.join(before, ["length", "task"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("rank") + F.col("before")).alias("rank"))

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plan = shared.value
        firsts = np.searchsorted(plan[:, 0], np.arange(capacity + 2))
        for b in rows:
            length, rank = (b.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            at = np.empty(len(length), np.int64)
            for n in np.unique(length):
                mine = np.flatnonzero(length == n)
                lo, hi = firsts[n], firsts[n + 1]
                at[mine] = lo + np.searchsorted(plan[lo:hi, 1], rank[mine], side="right") - 1
            p = plan[at]
            within = rank - p[:, 1]
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(p[:, 3] + within // p[:, 4]), pa.array(p[:, 5] + within % p[:, 4] * length)], [*b.schema.names[:5], "sequence_id", "offset"])

    return ranked.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    pieces = token_pieces(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
    return pack_pieces(checkpointed(pieces))
