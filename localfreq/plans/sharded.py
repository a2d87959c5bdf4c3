"""Time-sharded miner: the plan for data that no level-wise loop should read twice.

Whether a start is dense depends only on the next ``width`` times. Time is cut into shards; each shard gets the transactions of
its starts' windows, mines alone, and reports runs of starts within it. Runs of neighbouring shards join where they touch. One
large exchange, one small one, no driver loop; data are copied 1 + width / shard_width times.

Where patterns of any length are so many that each shard would find most of them again, patterns are dealt instead of times: by their first two
items, each pair with all transactions that hold it. Nothing is joined afterwards, and patterns leave the search as they are found.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localfreq.operators.detect import last_time
from localfreq.operators.segments import merge_runs
from localfreq.schema import pattern_len, pattern_text
from localfreq.session import parts

__all__ = ["mine_arrays", "mine_dense_by_pairs", "mine_dense_sharded", "mine_shard"]


def _runs(times: np.ndarray, width: int, sigma: int, lo: int, hi: int) -> list[tuple[int, int]]:
    """Runs of dense starts within [lo, hi] from sorted times."""
    if len(times) < sigma:
        return []
    a = np.maximum(lo, times[sigma - 1:] - width)
    b = np.minimum(hi, times[:len(times) - sigma + 1])
    ok = a <= b
    a, b = a[ok], b[ok]
    if not len(a):
        return []
    new = np.concatenate([[True], a[1:] > b[:-1] + 1])
    return list(zip(a[new].tolist(), b[np.concatenate([new[1:], [True]])].tolist(), strict=True))


def mine_shard(baskets: list[tuple[int, list[str]]], width: int, sigma: int, lo: int, hi: int, k_max: int | None) -> list[tuple[tuple[str, ...], int, int]]:
    """(items, s, d) of all patterns that have dense starts in [lo, hi], from (time, items) pairs."""
    names = sorted({x for _, items in baskets for x in items})
    code = {x: i for i, x in enumerate(names)}
    flat = [(code[x], t) for t, items in baskets for x in items]
    pairs = np.array(flat, np.int64).reshape(-1, 2)
    return mine_arrays(pairs[:, 0], pairs[:, 1], names, width, sigma, lo, hi, k_max)


def mine_arrays(codes: np.ndarray, times: np.ndarray, names: list[str], width: int, sigma: int, lo: int, hi: int, k_max: int | None) -> list[tuple[tuple[str, ...], int, int]]:
    """The search of one shard over (item code, time) pairs; ``names`` of the codes.

    One sort and one vectorised test over all items find those with a dense start; only these get bitmaps of their own.
    """
    order = np.lexsort((times, codes))
    c, t = codes[order], times[order]
    new = np.ones(len(c), bool)
    new[1:] = (c[1:] != c[:-1]) | (t[1:] != t[:-1])
    c, t = c[new], t[new]
    n = len(c) - sigma + 1
    if n <= 0:
        return []
    near = (c[sigma - 1:] == c[:n]) & (t[sigma - 1:] - t[:n] <= width) & (np.maximum(lo, t[sigma - 1:] - width) <= np.minimum(hi, t[:n]))
    out, singles, bits = [], [], []
    places = np.unique(t)
    for x in np.unique(c[:n][near]).tolist():
        i, j = np.searchsorted(c, [x, x + 1])
        runs = _runs(t[i:j], width, sigma, lo, hi)
        if runs:
            out += [((names[x],), s, d) for s, d in runs]
            singles.append(names[x])
            bits.append(_packed(np.searchsorted(places, t[i:j]), len(places)))
    order = sorted(range(len(singles)), key=singles.__getitem__)
    if order and (k_max is None or k_max > 1):
        search = _Search(places, width, sigma, lo, hi, k_max)
        search.below((), [singles[i] for i in order], np.stack([bits[i] for i in order]))
        out += search.out
    return out


def _packed(places: np.ndarray, n: int) -> np.ndarray:
    """Places as bits of 64-bit words."""
    flags = np.zeros(-(-n // 64) * 64, np.uint8)
    flags[places] = 1
    return np.packbits(flags, bitorder="little").view(np.uint64)


class _Search:
    """Depth-first search over bitmaps of a shard's transactions. Only the bitmaps along one path are held.

    Items go from the last to the first, so that all subsets of a pattern are decided before it. Full words that every window holds
    are counted first: where they alone reach sigma, all starts are dense, and no occurrence of the pattern is looked at on its own.
    """

    def __init__(self, places: np.ndarray, width: int, sigma: int, lo: int, hi: int, k_max: int | None):
        self.places, self.width, self.sigma, self.lo, self.hi, self.k_max = places, width, sigma, lo, hi, k_max
        self.dense: set[tuple[str, ...]] = set()
        self.out: list[tuple[tuple[str, ...], int, int]] = []
        # by the first full word of a window: the earliest start that has it, and the end of the full words there
        lowest, highest = (-(-int(np.searchsorted(places, x)) // 64) for x in (lo, hi))
        self.first = np.arange(lowest, highest + 1)
        start = np.array([lo, *(places[64 * (self.first[1:] - 1)] + 1)], np.int64)
        self.end = np.maximum(self.first, np.searchsorted(places, start + width, "right") // 64)
        self.first = np.minimum(self.first, self.end)

    def below(self, prefix: tuple[str, ...], items: list[str], bits: np.ndarray) -> None:
        """All dense patterns of ``prefix`` and two items or more; each of ``items`` with the prefix is dense and has a row of ``bits``."""
        for i in range(len(items) - 2, -1, -1):
            p = (*prefix, items[i])
            wanted = [j for j in range(i + 1, len(items)) if self._subsets_dense((*p, items[j]))]
            if not wanted:
                continue
            both = bits[wanted] & bits[i]
            counts = np.zeros((len(wanted), both.shape[1] + 1), np.int32)
            np.cumsum(np.bitwise_count(both), axis=1, out=counts[:, 1:])
            everywhere = (counts[:, self.end] - counts[:, self.first]).min(axis=1) >= self.sigma
            found = []
            for row, j in enumerate(wanted):
                if everywhere[row]:
                    runs = [(self.lo, self.hi)]
                elif counts[row, -1] < self.sigma:
                    continue
                else:
                    at = np.flatnonzero(np.unpackbits(both[row].view(np.uint8), bitorder="little"))
                    runs = _runs(self.places[at], self.width, self.sigma, self.lo, self.hi)
                if runs:
                    pattern = (*p, items[j])
                    self.dense.add(pattern)
                    self.out += [(pattern, s, d) for s, d in runs]
                    found.append(row)
            if len(found) > 1 and (self.k_max is None or len(p) + 1 < self.k_max):
                self.below(p, [items[wanted[r]] for r in found], both[found])

    def _subsets_dense(self, pattern: tuple[str, ...]) -> bool:
        """The subsets that leave out one item of the prefix; the other two are known to be dense."""
        return all(pattern[:j] + pattern[j + 1:] in self.dense for j in range(len(pattern) - 2))


def _span(width: int, c: int) -> str:
    """The kind of number for times within a shard."""
    return "u4" if width + c < 1 << 32 else "u8"


def _cut(batch: pa.RecordBatch, width: int, c: int, n_shards: int) -> pa.RecordBatch:
    """One row a shard that takes transactions of the batch: their times after the shard's begin, numbers of items, and items by place in ``names``.

    Bytes instead of a row a transaction and shard: what the exchange moves and its sort holds shrinks to about a quarter.
    """
    t, items = batch.column("t").to_numpy(), batch.column("items")
    coded, sizes = items.flatten().dictionary_encode(), items.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    low, high = np.maximum(0, t - width) // c, np.minimum(t // c, n_shards - 1)
    copies = np.maximum(0, high - low + 1)
    row = np.repeat(np.arange(len(t)), copies)
    shard = low[row] + np.arange(len(row)) - np.repeat(np.cumsum(copies) - copies, copies)
    order = np.argsort(shard, kind="stable")
    row, shard = row[order], shard[order]
    shards, first, n_rows = np.unique(shard, return_index=True, return_counts=True)
    size = sizes[row]
    codes = coded.indices.to_numpy(zero_copy_only=False)[_ranges((np.cumsum(sizes) - sizes)[row], size)]
    return pa.RecordBatch.from_pydict({"shard": pa.array(shards, pa.int64())} | _bytes(first, n_rows, t[row] - shard * c, size, codes, coded.dictionary, _span(width, c)))


def _ranges(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The numbers from each begin, as many as its size."""
    return np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(size.sum())


def _bytes(first: np.ndarray, n_rows: np.ndarray, times: np.ndarray, size: np.ndarray, codes: np.ndarray, dictionary: pa.Array, span: str) -> dict[str, pa.Array]:
    """Columns of a row a key: times, numbers of items, and items by place in ``names``. Rows lie key by key, each key's from ``first``; ``codes`` are all rows' items."""
    n_names = max(1, len(dictionary))
    owner = np.repeat(np.repeat(np.arange(len(first)), n_rows), size)
    used, place = np.unique(owner * n_names + codes, return_inverse=True)
    names_from = np.searchsorted(used // n_names, np.arange(len(first) + 1))
    place = place - names_from[owner]
    small = max(size.max(initial=0), place.max(initial=0)) < 256
    step = "u1" if small else "u4"

    def binary(values: np.ndarray, kind: str, ends: np.ndarray) -> pa.Array:
        offsets = np.concatenate([[0], ends]) * np.dtype(kind).itemsize
        return pa.Array.from_buffers(pa.large_binary(), len(ends), [None, pa.py_buffer(offsets.astype(np.int64)), pa.py_buffer(values.astype(kind))]).cast(pa.binary())

    rows_end = first + n_rows
    return {
        "times": binary(times, span, rows_end),
        "sizes": binary(size, step, rows_end),
        "places": binary(place, step, np.concatenate([[0], np.cumsum(size)])[rows_end]),
        "names": pa.ListArray.from_arrays(pa.array(names_from, pa.int32()), dictionary.take(pa.array(used % n_names))),
        "small": pa.array(np.full(len(first), small)),
    }


def _read(rows: pa.Table, span: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[str]]:
    """(times, numbers of items, item codes, names of the codes) of a key's rows of ``_bytes``."""
    steps = ["u1" if x else "u4" for x in rows.column("small").to_pylist()]
    ints = lambda name, kinds: [np.frombuffer(x.as_buffer(), k).astype(np.int64) for x, k in zip(rows.column(name), kinds, strict=True)]
    times, sizes, places = ints("times", [span] * len(steps)), ints("sizes", steps), ints("places", steps)
    names = rows.column("names").combine_chunks()
    coded, n = names.flatten().dictionary_encode(), names.value_lengths().to_numpy(zero_copy_only=False)
    before = np.cumsum(n) - n
    code = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)[np.concatenate([p + b for p, b in zip(places, before, strict=True)])]
    return np.concatenate(times), np.concatenate(sizes), code, coded.dictionary.to_pylist()


def _joined(rows: pa.Table, span: str, begin: int) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """(item codes, times, names of the codes) of a shard's rows of ``_cut``."""
    times, sizes, code, names = _read(rows, span)
    return code, np.repeat(times, sizes) + begin, names


def mine_dense_sharded(tx: DataFrame, width: int, sigma: int, *, shard_width: int, k_max: int | None = None, t_max: int | None = None, min_len: int = 1) -> DataFrame:
    """INTERVAL of all dense patterns, as ``mine_dense`` gives them. A shard (width + shard_width times) must fit one worker."""
    t_max = last_time(tx) if t_max is None else t_max
    if t_max is None or t_max < width:
        return tx.sparkSession.createDataFrame([], "pattern string, len int, s long, e long")
    c, last = int(shard_width), t_max - width

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return (_cut(b, width, c, last // c + 1) for b in batches if b.num_rows)

    def local(key: tuple, rows: pa.Table) -> pa.Table:
        lo = int(key[0].as_py()) * c
        codes, times, names = _joined(rows, _span(width, c), lo)
        found = mine_arrays(codes, times, names, width, sigma, lo, min(lo + c - 1, last), k_max)
        return pa.table({"items": pa.array([list(p) for p, _, _ in found], pa.list_(pa.string())), "s": pa.array([s for _, s, _ in found], pa.int64()), "d": pa.array([d for _, _, d in found], pa.int64())})

    filled = tx.where((F.size("items") > 0) & (F.col("t") >= 0)).select(F.col("t").cast("long").alias("t"), "items")
    dealt = filled.mapInArrow(cut, "shard long, times binary, sizes binary, places binary, names array<string>, small boolean")
    spark = tx.sparkSession
    pieces = min(last // c + 1, max(parts(spark), 4 * spark.sparkContext.defaultParallelism))  # given, since a shard's work does not follow its bytes
    runs = dealt.repartition(pieces, "shard").groupBy("shard").applyInArrow(local, "items array<string>, s long, d long")
    merged = merge_runs(runs.select(pattern_text(F.col("items")).alias("pattern"), "s", "d"), ["pattern"])
    return merged.select("pattern", pattern_len(F.col("pattern")).alias("len"), "s", (F.col("d") + width).alias("e")).where(F.col("len") >= min_len)


# --- patterns dealt by their first two items

#: Item places that one piece of a batch may take when its pairs are made.
_PIECE = 1_000_000


def _deal(batch: pa.RecordBatch, span: str) -> Iterator[pa.RecordBatch]:
    """One row an item, and a pair of items, of the batch: the times of transactions that hold it; a pair has their items after it as well. Items are in the order of a pattern's text."""
    t, items = batch.column("t").to_numpy(), batch.column("items")
    coded, sizes = items.flatten().dictionary_encode(), items.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    escaped = [x.replace("\\", "\\\\").replace("|", "\\|") for x in coded.dictionary.to_pylist()]
    names = pa.array(sorted(escaped), pa.string())
    n_names, rank = len(escaped), np.empty(len(escaped), np.int64)
    rank[sorted(range(n_names), key=escaped.__getitem__)] = np.arange(n_names)
    row = np.repeat(np.arange(len(t)), sizes)
    flat = np.unique(row * n_names + rank[coded.indices.to_numpy(zero_copy_only=False)])
    row, codes = flat // n_names, flat % n_names
    sizes = np.bincount(row, minlength=len(t))
    ends = np.cumsum(sizes)
    cuts = np.searchsorted(np.cumsum(sizes * sizes * (sizes + 4) // 6) // _PIECE, np.arange(1 + int((sizes * sizes * (sizes + 4) // 6).sum()) // _PIECE + 1))
    for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
        at = np.arange(ends[lo] - sizes[lo], ends[hi - 1]) if hi > lo else np.empty(0, np.int64)
        if not len(at):
            continue
        later = ends[row[at]] - at - 1
        one, two = np.repeat(at, later), _ranges(at + 1, later)
        key = np.concatenate([codes[at] * (n_names + 1), codes[one] * (n_names + 1) + codes[two] + 1])
        held, rest = np.concatenate([row[at], row[one]]), np.concatenate([ends[row[at]], two + 1])
        order = np.argsort(key, kind="stable")
        key, held, rest = key[order], held[order], rest[order]
        size = ends[held] - rest
        keys, first, n_rows = np.unique(key, return_index=True, return_counts=True)
        second = keys % (n_names + 1)
        ab = {"a": names.take(pa.array(keys // (n_names + 1))), "b": names.take(pa.array(np.where(second > 0, second - 1, 0), mask=second == 0))}
        yield pa.RecordBatch.from_pydict(ab | _bytes(first, n_rows, t[held], size, codes[_ranges(rest, size)], names, span))


#: Occurrences that are extended at once.
_TOGETHER = 100_000


class _Extensions:
    """Search for the extensions of one pattern over the rows that hold it, many patterns of one length at once: no item or pattern costs a step of its own.

    An occurrence is its pattern's number times ``far``, plus its time: neighbours of different patterns are then never within a window.
    What is found is cut into portions, and the last portion is extended first, so that little more than one path of portions is held.
    """

    def __init__(self, times: np.ndarray, width: int, sigma: int, last: int):
        self.times, self.width, self.sigma, self.last = times, width, sigma, last
        self.far = last + 2 * width + 2

    def runs(self, occ: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pattern, s, d) of all runs of dense starts, by pattern and time."""
        n, k = len(occ) - self.sigma + 1, self.sigma
        begins = occ[k - 1:] - occ[:n] <= self.width if n > 0 else np.empty(0, bool)
        if not begins.any():
            return (np.empty(0, np.int64),) * 3
        ends = begins.copy()
        apart = occ[k:] - occ[:n - 1] > self.width + 1  # a neighbour that is in no group itself is always apart
        begins[1:] &= apart
        ends[:-1] &= apart
        i, j = np.flatnonzero(begins), np.flatnonzero(ends)
        number = occ[i] // self.far
        before = number * self.far
        s, d = np.maximum(occ[i + k - 1] - self.width - before, 0), np.minimum(occ[j] - before, self.last)
        ok = s <= d
        return (number, s, d) if ok.all() else (number[ok], s[ok], d[ok])

    def search(self, text: str, length: int, rows: np.ndarray, codes: np.ndarray, names: list[str], k_max: int | None) -> Iterator[tuple[list[str], int, np.ndarray, np.ndarray, np.ndarray]]:
        """(texts, length, runs of each, s, d) of all dense extensions of a pattern that all rows hold; ``rows`` hold items of ``codes``, which are in the order of ``names``."""
        words = np.zeros((-(-len(names) // 64), len(self.times)), np.uint64)
        np.bitwise_or.at(words, (codes // 64, rows), np.uint64(1) << (codes % 64).astype(np.uint64))
        todo = [([text], length, np.zeros(1, np.int64), np.full(1, len(self.times)), np.arange(len(self.times), dtype=np.int32))]
        while todo:
            texts, length, after, counts, rows = todo.pop()  # patterns by the first item that may follow, their numbers of rows, and these
            ends = np.cumsum(counts)
            occ = np.repeat(np.arange(len(counts)) * self.far, counts) + self.times[rows]
            found = []
            for item in range(int(after[0]), len(names)):
                if item == after[0] or not item % 64:
                    word = words[item // 64][rows]
                here = np.flatnonzero((word[:ends[np.searchsorted(after, item, "right") - 1]] & np.uint64(1 << item % 64)) != 0)
                if len(here) < self.sigma:
                    continue
                mine = occ[here]
                number, s, d = self.runs(mine)
                if not len(number):
                    continue
                new = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1]]))
                dense = number[new]
                more = [f"{texts[x]}|{names[item]}" for x in dense.tolist()]
                yield more, length + 1, np.diff(new, append=len(number)), s, d
                if item + 1 < len(names) and (k_max is None or length + 1 < k_max):
                    lo, n = np.searchsorted(mine, dense * self.far), np.searchsorted(mine, (dense + 1) * self.far)
                    n -= lo
                    found.append((more, np.full(len(more), item + 1), n, rows[here if n.sum() == len(here) else here[_ranges(lo, n)]]))
            if found:
                more = [x for f in found for x in f[0]]
                after, counts, rows = (np.concatenate([f[i] for f in found]) for i in (1, 2, 3))
                ends = np.cumsum(counts)
                cuts = [0, *(np.flatnonzero(np.diff(ends // _TOGETHER)) + 1).tolist(), len(more)]
                todo += [(more[i:j], length + 1, after[i:j], counts[i:j], rows[ends[i] - counts[i]:ends[j - 1]]) for i, j in zip(cuts[:-1], cuts[1:], strict=True)]


def _in_batches(found: Iterator[tuple[list[str], int, np.ndarray, np.ndarray, np.ndarray]], width: int, each: int = 20_000) -> Iterator[pa.RecordBatch]:
    """INTERVAL rows of what a search finds."""
    texts: list[str] = []
    kept: list[tuple] = []
    n = 0

    def batch() -> pa.RecordBatch:
        size, s, d = (np.concatenate(x) for x in zip(*(x[1:] for x in kept), strict=True))
        lens = np.concatenate([np.full(len(x[1]), x[0]) for x in kept])
        return pa.RecordBatch.from_pydict({"pattern": pa.array(texts, pa.string()).take(pa.array(np.repeat(np.arange(len(texts)), size))), "len": pa.array(np.repeat(lens, size), pa.int32()), "s": pa.array(s, pa.int64()), "e": pa.array(d.astype(np.int64) + width)})

    for some, length, size, s, d in found:
        texts += some
        kept.append((length, size, s, d))
        n += len(s)
        if n >= each:
            yield batch()
            texts, kept, n = [], [], 0
    if kept:
        yield batch()


def _mine_pair(a: str, b: str | None, rows: pa.Table, span: str, width: int, sigma: int, last: int, k_max: int | None) -> Iterator[tuple[list[str], int, np.ndarray, np.ndarray, np.ndarray]]:
    """What is dense of one item, or of a pair and all patterns that begin with it, from its rows of ``_deal``."""
    times, sizes, codes, names = _read(rows, span)
    order = np.argsort(times)
    search = _Extensions(times[order], width, sigma, last)
    _, s, d = search.runs(search.times)
    if not len(s):
        return
    text = a if b is None else f"{a}|{b}"
    yield [text], 1 if b is None else 2, np.array([len(s)]), s, d
    if len(codes) >= sigma and (k_max is None or k_max > 2):
        place, rank = np.empty(len(order), np.int64), np.empty(len(names), np.int64)
        place[order] = np.arange(len(order))
        by_text = sorted(range(len(names)), key=names.__getitem__)
        rank[by_text] = np.arange(len(names))
        yield from search.search(text, 2, np.repeat(place, sizes), rank[codes], [names[i] for i in by_text], k_max)


def mine_dense_by_pairs(tx: DataFrame, width: int, sigma: int, *, k_max: int | None = None, t_max: int | None = None) -> DataFrame:
    """INTERVAL of all dense patterns, as ``mine_dense`` gives them; one time has one transaction. The transactions that hold one pair of items must fit one worker."""
    t_max = last_time(tx) if t_max is None else t_max
    if t_max is None or t_max < width:
        return tx.sparkSession.createDataFrame([], "pattern string, len int, s long, e long")
    last, span = t_max - width, "u4" if t_max < 1 << 32 else "u8"

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield from _deal(b, span)

    def local(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = (x.as_py() for x in key)
        yield from _in_batches(_mine_pair(a, b, pa.Table.from_batches(list(batches)), span, width, sigma, last, k_max), width)

    filled = tx.where((F.size("items") > 0) & (F.col("t") >= 0)).select(F.col("t").cast("long").alias("t"), "items")
    pairs = filled.mapInArrow(deal, "a string, b string, times binary, sizes binary, places binary, names array<string>, small boolean")
    if k_max == 1:
        pairs = pairs.where("b is null")
    spark = tx.sparkSession
    pieces = max(parts(spark), 4 * spark.sparkContext.defaultParallelism)  # given, since a pair's work does not follow its bytes
    return pairs.repartition(pieces, "a", "b").groupBy("a", "b").applyInArrow(local, "pattern string, len int, s long, e long")
