"""Exact Jaccard similarity join on word shingles with PartEnum signatures.

Sets are dealt into size bands such that similar sets lie in the same or in neighbouring bands. For a pair of
bands the largest possible difference k of two similar sets follows from their sizes. The domain of shingles (its
64-bit hashes) is cut into n1 first-level partitions of two second-level partitions each; a set's signatures enumerate, for each
first-level partition, the subsets of one of its two halves: the half's number with the content that the set has there. With
m = 2 * n1 > k halves, two similar sets have the same content in m - k halves at least, so they share a signature.

Halves in which a set has nothing say little and would gather unrelated documents. A set leaves them out if it has fewer than m - k
of them: then some shared half is not empty. The few sets with more empty halves keep them, so no link is lost.

From signatures to components:

1. Equal sets form one class; everything after works on classes.
2. Signature rows are exchanged once and sorted; a streaming pass keeps those that two classes or more share, names each bucket by its
   members, so that buckets with the same members count once, and numbers its rows in blocks of bounded size. A signature that many
   classes of one batch share is dealt over many keys; its parts keep one bucket name and blocks of their own.
3. Of the leaders (a bucket's smallest class) that its sketch allows, each class is compared with the one that it shares most buckets with; links
   are joined to components. Then come the leaders in other components: the closest pair by sketches for each two components.
4. Buckets whose classes lie in one component are done, and those of two classes whose sketches forbid a link or that have been compared. In the others, pairs of classes of different components are still open: the classes
   outside the bucket's largest component meet each other and the blocks of the largest one. Two blocks first give the most
   likely pair for each two components; their links join components, which closes most pairs. A last turn over the buckets that
   held pairs back gives every pair that may be similar and is still open. So all links between components are found, without listing all pairs of a group of copies.

A comparison first uses parity sketches: bit j of a set's sketch is the parity of its members that hash to j, so the sketches of two
sets differ in at most as many bits as the sets differ in members. Pairs that pass are decided by exact intersection of the sets of
their texts. Every step's result is a written table of the shared folder, deleted after its last reader. Where few rows of the corpus are looked for by
their ids, a filter of at most 32 MB keeps the texts of most others out of the exchange; beyond that size all go through it.

Exactness is up to collisions of 64-bit hashes. Texts without words, empty and null texts have the empty set and link with nothing;
their component is their own id. Rows with a null id take part, but a component's id is its smallest id that is not
null. Repeated rows share a component. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_right
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from localfreq.llm.common import Scratch, batches, free_name, read_table, string_bytes

__all__ = ["Bands", "components", "jaccard_components", "keep_one", "op2_ngram_jaccard_join", "shingle_sets", "word_hashes"]

_U = np.uint64
_SPACES = [0x20, *range(0x09, 0x0E)]
_SEGMENT = 1 << 20
_BLOCK = 512
_LEAST = -(1 << 63)
_FILTER = 1 << 28


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    h = (h ^ (h >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U(27))) * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


@lru_cache(1)
def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(is a word's byte, value of each byte with A-Z as a-z, powers, inverse powers)."""
    word = np.ones(256, bool)
    word[_SPACES] = False
    low = np.arange(256)
    low[65:91] += 32
    value = mix(low.astype(_U) + _U(0x5851F42D4C957F2D))
    base = 0x2545F4914F6CDD1D
    powers = np.cumprod(np.concatenate([[1], np.full(_SEGMENT, base)]).astype(_U))
    inverse = np.cumprod(np.concatenate([[1], np.full(_SEGMENT, pow(base, -1, 1 << 64))]).astype(_U))
    return word, value, powers, inverse


def word_spans(raw: np.ndarray, starts: np.ndarray, word: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(starts, ends) of the words of texts that lie one after another; ``word`` marks the bytes that words have."""
    inside = (_tables()[0] if word is None else word)[raw]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    cuts = starts[(starts > 0) & (starts < len(raw))]
    first[cuts] = inside[cuts]
    last[cuts - 1] = inside[cuts - 1]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def word_hashes(raw: np.ndarray, starts: np.ndarray, spans: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document) of every word of the texts that lie one after another in ``raw``."""
    _, value, powers, inverse = _tables()
    s, e = word_spans(raw, starts) if spans is None else spans
    out = np.empty(len(s), _U)
    i = 0
    while i < len(s):  # segments that the tables of powers cover
        j = max(i + 1, int(np.searchsorted(e, s[i] + _SEGMENT, side="right")))
        a, b = int(s[i]), int(e[j - 1])
        if b - a > _SEGMENT:  # one word of more than a segment
            out[i] = np.frombuffer(hashlib.blake2b(bytes(raw[a:b]).lower(), digest_size=8).digest(), _U)[0]
        else:
            sums = np.zeros(b - a + 1, _U)
            np.cumsum(value[raw[a:b]] * powers[:b - a], out=sums[1:])
            out[i:j] = (sums[e[i:j] - a] - sums[s[i:j] - a]) * inverse[s[i:j] - a]
        i = j
    out = mix(out ^ (e - s).astype(_U))
    return out, np.searchsorted(starts, s, side="right") - 1


def shingle_sets(column: pa.Array, width: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; a text of fewer words has one shingle of all its words, one of none has none."""
    raw, starts = string_bytes(column)
    words, doc = word_hashes(raw, starts)
    n = len(starts) - 1
    factors = mix(np.arange(1, width + 1, dtype=_U)) | _U(1)
    bounds = np.searchsorted(doc, np.arange(n + 1))
    grams = sum((words[i:len(words) - width + 1 + i] * factors[i] for i in range(width)), np.zeros(max(0, len(words) - width + 1), _U))
    grams = mix(grams)
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(grams[a:b - width + 1]))
        elif b > a:
            out.append(mix(np.array([(words[a:b] * factors[:b - a]).sum(dtype=_U) + _U(0x9E37 * (b - a))], _U)))
        else:
            out.append(np.zeros(0, _U))
    return out


class Bands:
    """Size bands and signatures for the threshold 100 * intersection >= percent * union."""

    def __init__(self, percent: int):
        self.percent, self.low, self.high = percent, [1], [100 // percent]
        self._cuts: dict[int, tuple] = {}

    def band(self, n: int) -> int:
        while self.high[-1] < n:
            self.low.append(self.high[-1] + 1)
            self.high.append(self.low[-1] * 100 // self.percent)
        return bisect_right(self.low, n) - 1

    def shape(self, band: int) -> tuple[int, int, np.ndarray]:
        """(k, m, borders of the m halves) for sets of this band and the next."""
        got = self._cuts.get(band)
        if got is None:
            self.band(self.high[band] + 1 if band < len(self.high) else self.low[band])
            r = self.high[band]
            k = (r + r * 100 // self.percent) * (100 - self.percent) // (100 + self.percent)
            m = k + 3 + k // 12
            m += m & 1
            borders = np.array([-(-(j << 64) // m) for j in range(1, m)], _U)
            got = self._cuts[band] = (k, m, borders)
        return got

    def signatures(self, ordered: np.ndarray) -> list[np.ndarray]:
        """The signatures of a sorted set, for its band as the lower and as the upper one."""
        n = len(ordered)
        if not n:
            return []
        own = self.band(n)
        sums = np.zeros(n + 1, _U)
        np.cumsum(mix(ordered ^ _U(0xA0761D6478BD642F)), out=sums[1:])
        out = []
        for band in (own, own - 1):
            if band < 0:
                continue
            k, m, borders = self.shape(band)
            if not k:  # only equal sets are similar
                continue
            at = np.concatenate([[0], np.searchsorted(ordered, borders), [n]])
            content = sums[at[1:]] - sums[at[:-1]]
            halves = np.arange(m, dtype=_U)
            filled = at[1:] > at[:-1]
            if m - int(filled.sum()) < m - k:
                content, halves = content[filled], halves[filled]
            out.append(mix(content + halves * _U(0xD6E8FEB86659FD93) + _U((band + 1) * 0xE7037ED1A0B428DB % (1 << 64))))
        return out


def _node(ordered: np.ndarray) -> int:
    """The class of a set: a hash of all its members."""
    total = int(mix(ordered).sum(dtype=_U)) + len(ordered) * 0x9E3779B97F4A7C15
    return int(mix(np.array([total % (1 << 64)], _U)).view(np.int64)[0])


def _classes(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, n_shingles, node): node is null for the empty set."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows, _SEGMENT):
            sets = shingle_sets(b.column(1), width)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array([_node(s) if len(s) else None for s in sets], pa.int64())], ["doc_id", "n_shingles", "node"])

    return docs.mapInArrow(run, "doc_id long, n_shingles long, node long")


def _id_filter(ids: DataFrame) -> np.ndarray | None:
    """A bitmap that holds two bits of the hash of each of ``ids`` (one column, long, not null), sized by their number: ``_may_be`` passes all of them and few others.

    None where it would have more than ``_FILTER`` bits: then everything passes, so an exact join must follow.
    """
    n = ids.count()
    size = max(1 << 10, 1 << (8 * n - 1).bit_length()) if n else 1 << 10
    if size > _FILTER:
        return None
    hashed = ids.select(_id_hash(F.col(ids.columns[0])).alias("h"))
    place = F.explode(F.array(F.col("h").bitwiseAND(F.lit(size - 1)), F.shiftrightunsigned("h", 32).bitwiseAND(F.lit(size - 1)))).alias("p")
    words = hashed.select(place).groupBy(F.shiftright("p", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 63 as int))")).alias("b")).toArrow()  # the bitmap at most
    bitmap = np.zeros(size // 64, _U)
    bitmap[words.column(0).to_numpy()] = words.column(1).to_numpy().view(_U)
    return bitmap


def _id_hash(c: Column) -> Column:
    """What ``_may_be`` tests: null as the least number."""
    return F.xxhash64(F.coalesce(c.cast("long"), F.lit(_LEAST)))


def _may_be(bitmap: np.ndarray | None, hashes: pa.Array) -> pa.Array:
    """Whether ids of these hashes may be among the filter's. Called inside a task's one Python function: a UDF beside it would keep a second worker in memory."""
    x = hashes.to_numpy().view(_U)
    if bitmap is None:
        return pa.array(np.ones(len(x), bool))
    last = _U(64 * len(bitmap) - 1)
    one, two = (bitmap[p >> _U(6)] >> (p & _U(63)) for p in (x & last, (x >> _U(32)) & last))
    return pa.array((one & two & _U(1)).astype(bool))


def _signatures(docs: DataFrame, width: int, percent: int, *, hot: int = 256, held: int = 500_000) -> DataFrame:
    """(sig, node, home), each class once a task at least.

    A signature that ``hot`` classes or more of one batch of ``held`` rows share is dealt over 1,024 keys: ``home`` is then the signature
    itself, and one of its rows stays under its own key and marks it.
    """

    def dealt(sigs: list[np.ndarray], nodes: list[np.ndarray]) -> pa.RecordBatch:
        sig, node = np.concatenate(sigs), np.concatenate(nodes)
        order = np.argsort(sig, kind="stable")
        start = np.flatnonzero(np.concatenate([[True], sig[order][1:] != sig[order][:-1]]))
        size = np.diff(np.append(start, len(sig)))
        often = np.zeros(len(sig), bool)
        often[order] = np.repeat(size >= hot, size)
        key = sig.copy()
        key[often] = mix(sig[often] + ((mix(node[often].view(_U)) & _U(1023)) + _U(1)) * _U(0x9E3779B97F4A7C15))
        marks = order[start[size >= hot]]
        key, node, home = np.concatenate([key, sig[marks]]), np.concatenate([node, node[marks]]), np.concatenate([sig, sig[marks]])
        plain = np.concatenate([~often, np.zeros(len(marks), bool)])
        return pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(node), pa.array(home.view(np.int64), mask=plain)], ["sig", "node", "home"])

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bands, seen = Bands(percent), set()
        sigs, nodes, size = [], [], 0
        for b in batches(rows, _SEGMENT):
            for s in shingle_sets(b.column(1), width):
                node = _node(s) if len(s) else None
                if node is None or node in seen:
                    continue
                if len(seen) >= 200_000:
                    seen.clear()
                seen.add(node)
                for x in bands.signatures(s):
                    sigs.append(x)
                    nodes.append(np.full(len(x), node, np.int64))
                    size += len(x)
            if size >= held:
                yield dealt(sigs, nodes)
                sigs, nodes, size = [], [], 0
        if size:
            yield dealt(sigs, nodes)

    return docs.mapInArrow(run, "sig long, node long, home long")


def _shared(signatures: DataFrame, *, long: int = 200_000) -> DataFrame:
    """(bucket, i, node, lead, two): the buckets of two or more classes in blocks i; two: of just two. Sorted by Spark, read as a stream; a long bucket passes in pieces."""

    def emit(sig: np.ndarray, node: np.ndarray, home: np.ndarray, known: np.ndarray, passed: tuple | None, more: bool) -> pa.RecordBatch | None:
        """``passed``: (rows so far, lead) of the first signature, where pieces of it are out; ``more``: pieces of the last one follow."""
        start = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
        split = np.logical_or.reduceat(known, start)
        origin = np.where(split, np.maximum.reduceat(np.where(known, home, _LEAST), start), sig[start])
        new = np.ones(len(sig), bool)
        new[1:] = (sig[1:] != sig[:-1]) | (node[1:] != node[:-1])
        sig, node = sig[new], node[new]
        start = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
        size = np.diff(np.append(start, len(sig)))
        names = mix(np.add.reduceat(mix(node.view(_U)), start) + size.astype(_U))
        base, lead, keep = np.zeros(len(start), np.int64), node[start], (size > 1) | split
        pieces = split.copy()
        if passed is not None:
            base[0], lead[0], keep[0], pieces[0] = passed[0], passed[1], True, True
        if more:
            keep[-1] = pieces[-1] = True
        names = np.where(pieces, mix(origin.view(_U) ^ _U(0xD1B54A32D192ED03)), names).view(np.int64)
        offset = np.where(split, (mix(sig[start].view(_U)) & _U((1 << 40) - 1)).astype(np.int64) << 20, 0)
        place = offset.repeat(size) + (np.arange(len(sig)) - start.repeat(size) + base.repeat(size)) // _BLOCK
        rows = keep.repeat(size)
        if not rows.any():
            return None
        return pa.RecordBatch.from_arrays([pa.array(x[rows]) for x in (names.repeat(size), place, node, lead.repeat(size), ((size == 2) & ~pieces).repeat(size))], ["bucket", "i", "node", "lead", "two"])

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_rows = [np.zeros(0, np.int64)] * 3 + [np.zeros(0, bool)]
        passed: tuple | None = None  # (signature, rows so far, lead) of a signature of which pieces are out
        for b in rows:
            now = [b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).fill_null(0).to_numpy(), b.column(2).is_valid().to_numpy(zero_copy_only=False)]
            sig, node, home, known = (np.concatenate(x) for x in zip(open_rows, now, strict=True))
            if not len(sig):
                continue
            cut = int(np.searchsorted(sig, sig[-1]))
            whole = len(sig) - cut <= long
            end = cut if whole else len(sig)
            if end:
                before = passed[1:] if passed is not None and passed[0] == sig[0] else None
                out = emit(sig[:end], node[:end], home[:end], known[:end], before, not whole)
                if out is not None:
                    yield out
                if not whole:
                    same = cut == 0 and before is not None
                    passed = (sig[-1], len(sig) - cut + (before[0] if same else 0), before[1] if same else node[cut])
            open_rows = [x[end:] for x in (sig, node, home, known)]
        if len(open_rows[0]):
            out = emit(*open_rows, passed[1:] if passed is not None and passed[0] == open_rows[0][0] else None, False)
            if out is not None:
                yield out

    return signatures.repartition("sig").sortWithinPartitions("sig", "node").mapInArrow(run, "bucket long, i long, node long, lead long, two boolean").distinct()


def _texts(docs: DataFrame, width: int, chosen: DataFrame) -> DataFrame:
    """(node, n, sketch, text) of the classes in ``chosen`` (node, key), each by the text of one row of that id.

    Rows are dealt by class and id, so that copies of one text, however many, spread. Only rows whose id may be chosen are looked at.
    """
    bitmap = _id_filter(chosen.select("key"))

    def named(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows, _SEGMENT):
            b = b.filter(_may_be(bitmap, b.column(2)))
            sets = shingle_sets(b.column(1), width)
            yield pa.RecordBatch.from_arrays([pa.array([_node(s) if len(s) else None for s in sets], pa.int64()), b.column(0).fill_null(_LEAST), b.column(1)], ["node", "key", "text"])

    def sketched(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows, _SEGMENT):
            sets = shingle_sets(b.column(1), width)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array([sketch(s) for s in sets], pa.binary()), b.column(1)], ["node", "n", "sketch", "text"])

    found = docs.select("doc_id", "text", _id_hash(F.col("doc_id")).alias("hash")).mapInArrow(named, "node long, key long, text string").where("node is not null").join(chosen, ["node", "key"], "left_semi").dropDuplicates(["node", "key"])
    return found.select("node", "text").mapInArrow(sketched, "node long, n long, sketch binary, text string")


def sketch(ordered: np.ndarray) -> bytes:
    """Parity sketch of a set: two to four bits a member, a power of two of them, so that longer ones fold to shorter ones."""
    bits = max(64, 1 << (2 * len(ordered) - 1).bit_length())
    places = (mix(ordered ^ _U(0x6A09E667F3BCC909)) & _U(bits - 1)).astype(np.int64)
    return np.packbits((np.bincount(places, minlength=bits) & 1).astype(np.uint8), bitorder="little").tobytes()


def _folded(sketches: list[bytes], size: int) -> np.ndarray:
    """Sketches as rows of words, folded to ``size`` bytes: bit j is then the parity modulo the shorter length."""
    return np.stack([np.bitwise_xor.reduce(np.frombuffer(x, _U).reshape(-1, size // 8), axis=0) for x in sketches])


def _may_link(na: np.ndarray, nb: np.ndarray, apart: np.ndarray, percent: int) -> np.ndarray:
    """Whether sets of these sizes, whose sketches differ in so many bits, can be similar."""
    return (apart * (100 + percent) <= (na + nb) * (100 - percent)) & (np.minimum(na, nb) * 100 >= np.maximum(na, nb) * percent)


def components(links: DataFrame, scratch: Scratch) -> DataFrame:
    """A table (node, label): the smallest node that each node of (a, b) reaches. Large-star and small-star steps until nothing moves.

    Minima are aggregated before the exchange and joined back, so the centre of a large star is no hot task.
    """
    edges = scratch.keep(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    state = None
    while True:
        count = edges.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if tuple(count) == state:
            break
        state = tuple(count)
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        before, edges = edges, scratch.keep(small)
        scratch.drop(before)
    labels = scratch.keep(edges.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("label")))
    scratch.drop(edges)
    return labels


def _sketched(pairs: DataFrame, sketches: DataFrame, percent: int) -> DataFrame:
    """(a, b, k, apart) of the pairs (a, b, k) that may be similar by their sketches."""
    both = pairs.join(sketches.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa")), "a").join(sketches.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb")), "b")

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in rows:
            na, nb = b.column(2).to_numpy(), b.column(3).to_numpy()
            apart = np.array([int(np.bitwise_count(np.bitwise_xor(*(_folded([s], min(len(x), len(y)))[0] for s in (x, y)))).sum()) for x, y in zip(b.column(4).to_pylist(), b.column(5).to_pylist(), strict=True)], np.int64)
            keep = pa.array(_may_link(na, nb, apart, percent), pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0).filter(keep), b.column(1).filter(keep), b.column(6).filter(keep), pa.array(apart).filter(keep)], ["a", "b", "k", "apart"])

    return both.select("a", "b", "na", "nb", "sa", "sb", "k").mapInArrow(run, "a long, b long, k long, apart long")


def _block_hits(left: pa.RecordBatch, right: pa.RecordBatch | None, percent: int, every: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(a, b, more) of two blocks, or of one with itself (right None): pairs of different labels that may be similar.

    Without ``every`` only the closest pair for each two labels is given, and ``more`` says whether it stands for others.
    In one block the members of its commonest label are met by the others and not looked at one by one.
    """
    sides = [left] if right is None else [left, right]
    texts = [x.column(3).to_pylist() for x in sides]
    size = min(len(t) for x in texts for t in x)
    folded = [_folded(t, size) for t in texts]
    (node_l, label_l, n_l), (node_r, label_r, n_r) = ([sides[i].column(c).to_numpy(zero_copy_only=False) for c in (0, 1, 2)] for i in (0, len(sides) - 1))
    out: list[list[np.ndarray]] = [[], [], [], [], []]
    asked, earlier = np.arange(len(node_l)), np.zeros(len(node_r), bool)
    if right is None:
        found, place, k = np.unique(label_l, return_inverse=True, return_counts=True)
        common = place == np.argmax(k) if len(found) else np.zeros(0, bool)
        asked, earlier = np.flatnonzero(~common), common
    for k in asked:
        apart = np.bitwise_count(folded[-1] ^ folded[0][k]).sum(axis=1, dtype=np.int64)
        near = _may_link(n_l[k], n_r, apart, percent) & (label_r != label_l[k])
        hit = np.flatnonzero(near if right is not None else near & (earlier | (node_r > node_l[k])))
        for x, y in zip(out, (np.full(len(hit), node_l[k]), node_r[hit], np.full(len(hit), label_l[k]), label_r[hit], apart[hit]), strict=True):
            x.append(y)
    a, b, low, high, apart = (np.concatenate(x).astype(np.int64) if x else np.zeros(0, np.int64) for x in out)
    if every or not len(a):
        return a, b, np.zeros(len(a), bool)
    low, high = np.minimum(low, high), np.maximum(low, high)
    order = np.lexsort((apart, high, low))
    new = np.ones(len(order), bool)
    new[1:] = (low[order][1:] != low[order][:-1]) | (high[order][1:] != high[order][:-1])
    more = np.diff(np.append(np.flatnonzero(new), len(order))) > 1
    return a[order[new]], b[order[new]], more


def _open_pairs(members: DataFrame, labels: DataFrame, sketches: DataFrame, percent: int, scratch: Scratch, *, every: bool) -> DataFrame:
    """A table (bucket, a, b, more): pairs of different components that share a bucket and may be similar.

    A bucket of up to ``_BLOCK`` classes is one block. In a larger one the classes outside its largest component meet each other and the blocks of the
    largest one. No block holds more than about ``_BLOCK`` classes, and joins of members are by bucket and block, whatever the bucket's size.
    """
    placed = members.join(labels, "node", "left").select("bucket", "i", "node", F.coalesce("label", "node").alias("label"))
    spread = placed.groupBy("bucket").agg(F.min("label").alias("x"), F.max("label").alias("y")).where("x <> y").select("bucket")
    cells = placed.select("bucket", "i").distinct().join(spread, "bucket")
    placed = scratch.keep(placed.join(cells, ["bucket", "i"]))
    counts = placed.groupBy("bucket", "label").agg(F.count(F.lit(1)).alias("k")).groupBy("bucket").agg((F.sum("k") - F.max("k")).alias("others"), F.max(F.struct("k", "label"))["label"].alias("main"), (F.sum("k") <= _BLOCK).alias("whole"))
    mains = placed.select("bucket", "i").distinct().join(counts, "bucket")
    rows = placed.join(mains, ["bucket", "i"]).join(sketches, "node")
    apart = F.pmod(F.xxhash64("node"), F.ceil(F.col("others") / F.lit(_BLOCK))).cast("long")
    outside, whole = F.col("label") != F.col("main"), F.col("whole")
    gather = F.collect_list(F.struct("node", "label", "n", "sketch")).alias("l")
    gathered = scratch.keep(rows.groupBy("bucket", "whole", (whole | outside).alias("outside"), F.when(whole, 0).when(outside, apart).otherwise(F.col("i")).alias("i")).agg(gather))

    def run(batches_in: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_in:
            for i in range(b.num_rows):
                left = pa.RecordBatch.from_struct_array(b.column(1)[i].values)
                right = pa.RecordBatch.from_struct_array(b.column(2)[i].values) if b.column(2)[i].is_valid else None
                x, y, more = _block_hits(left, right, percent, every)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), b.column(0)[i].as_py(), np.int64)), pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(more)], ["bucket", "a", "b", "more"])

    parted = gathered.where("not whole")
    out = parted.where("outside").select("bucket", "i", "l")
    other = parted.select("bucket", "outside", F.col("i").alias("j"), F.col("l").alias("r"))
    met = out.join(other, "bucket").where("not outside or i < j").select("bucket", "l", "r")
    alone = gathered.where("outside").select("bucket", "l", F.lit(None).cast(gathered.schema["l"].dataType).alias("r"))
    hits = scratch.keep(alone.unionByName(met).mapInArrow(run, "bucket long, a long, b long, more boolean"))
    scratch.drop(placed, gathered)
    return hits


def _verified(pairs: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) of classes that are similar, by exact intersection. A class that many pairs name as b is dealt over many tasks."""
    dealt = pairs.select("a", "b", F.pmod(F.xxhash64("a"), F.lit(1024)).alias("part"))
    ours = texts.select(F.col("node").alias("a"), F.col("text").alias("ta"))
    theirs = dealt.select("b", "part").distinct().join(texts.select(F.col("node").alias("b"), F.col("text").alias("tb")), "b")
    both = dealt.join(ours, "a").join(theirs, ["b", "part"]).select("a", "b", "ta", "tb")

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows, _SEGMENT):
            keep = []
            for x, y in zip(shingle_sets(b.column(2), width), shingle_sets(b.column(3), width), strict=True):
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * common >= percent * (len(x) + len(y) - common))
            keep = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0).filter(keep), b.column(1).filter(keep)], ["a", "b"])

    return both.mapInArrow(run, "a long, b long")


def _with_labels(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """``pairs`` (a, b, ...) with the components x and y of their classes, those of one component left out."""
    for side, name in (("a", "x"), ("b", "y")):
        pairs = pairs.join(labels.select(F.col("node").alias(side), F.col("label").alias(name)), side, "left").withColumn(name, F.coalesce(name, side))
    return pairs.where("x <> y")


def _solved(docs: DataFrame, width: int, percent: int, scratch: Scratch, *, long: int = 200_000, **sizes: int) -> tuple[DataFrame, DataFrame]:
    """Tables (doc_id, n_shingles, node) of all rows and (node, label) of the classes that have links."""
    rows = scratch.keep(_classes(docs, width))
    members = scratch.keep(_shared(_signatures(docs, width, percent, **sizes), long=long))
    first = rows.where("node is not null").groupBy("node").agg(F.min(F.coalesce("doc_id", F.lit(_LEAST))).alias("key"))
    chosen = scratch.keep(first.join(members.select("node").distinct(), "node", "left_semi"))
    texts = scratch.keep(_texts(docs, width, chosen))
    scratch.drop(chosen)
    sketches = texts.select("node", "n", "sketch")
    star = scratch.keep(members.where("node <> lead").groupBy(F.col("node").alias("a"), F.col("lead").alias("b")).agg(F.count(F.lit(1)).alias("k")))
    likely = scratch.keep(_sketched(star, sketches, percent))
    scratch.drop(star)
    best = F.max(F.struct("k", F.bitwise_not("b").alias("c")))["c"]
    tested = scratch.keep(likely.groupBy("a").agg(F.bitwise_not(best).alias("b")))
    found = scratch.keep(_verified(tested, texts, width, percent))
    labels = components(found, scratch)
    scratch.drop(found)

    def joined(pairs: DataFrame) -> None:
        nonlocal labels
        if pairs.isEmpty():
            return
        links = scratch.keep(_verified(pairs, texts, width, percent))
        if not links.isEmpty():
            before, labels = labels, components(labels.select(F.col("node").alias("a"), F.col("label").alias("b")).unionByName(links), scratch)
            scratch.drop(before)
        scratch.drop(links)

    rest = likely.join(tested, ["a", "b"], "left_anti")
    near = _with_labels(rest, labels)
    closest = scratch.keep(near.groupBy(F.least("x", "y"), F.greatest("x", "y")).agg(F.min(F.struct("apart", "a", "b")).alias("p")).select("p.a", "p.b"))
    joined(closest)
    decided = [tested, closest]
    left = _with_labels(rest.select("a", "b").join(closest, ["a", "b"], "left_anti"), labels).select(F.col("a").alias("node"), F.col("b").alias("lead"))
    two = members.where("two").join(members.where("two").join(left, ["node", "lead"], "left_semi").select("bucket"), "bucket", "left_semi")
    watched = opened = scratch.keep(members.where("not two").unionByName(two.select(*members.columns)))
    for every in (False, True):
        hits = _open_pairs(watched, labels, sketches, percent, scratch, every=every)
        pairs = hits.select("a", "b").distinct()
        for t in decided:
            pairs = pairs.join(t.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")), ["a", "b"], "left_anti")
        pairs = scratch.keep(pairs)
        decided.append(pairs)
        joined(pairs)
        more = hits.where("more").select("bucket").distinct()
        if more.isEmpty():
            break
        watched = opened.join(more, "bucket", "left_semi")  # only these had pairs that were not given
    scratch.drop(*decided, likely, opened, texts, members)
    return rows, labels


def _by_label(rows: DataFrame, found: DataFrame, parts: int = 16) -> DataFrame:
    """``rows`` (node, label, ...) joined with one row a label; the rows of one component are dealt over ``parts`` keys."""
    copies = found.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))))
    return rows.withColumn("part", F.pmod(F.xxhash64("node"), F.lit(parts))).join(copies, ["label", "part"]).drop("part")


def _docs(df: DataFrame, doc_id: str, text: str) -> DataFrame:
    return df.select(df[doc_id].cast("long").alias("doc_id"), df[text].cast("string").alias("text"))


def jaccard_components(df: DataFrame, *, width: int = 5, percent: int = 80, doc_id: str = "doc_id", text: str = "text", **sizes: int) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row: texts link when 100 * |intersection| >= percent * |union|."""
    rows, labels = _solved(_docs(df, doc_id, text), width, percent, Scratch(df.sparkSession), **sizes)
    classes = rows.where("node is not null").groupBy("node").agg(F.min("doc_id").alias("least"))
    roots = labels.select(F.col("label").alias("node"), "label").distinct()  # a component's smallest class has no row of its own
    linked = classes.join(labels.unionByName(roots), "node")
    of = _by_label(linked, linked.groupBy("label").agg(F.min("least").alias("component_id"))).select("node", "component_id")
    final = classes.join(of, "node", "left").select("node", F.coalesce("component_id", "least").alias("component_id"))
    return rows.join(final, "node", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_one(df: DataFrame, *, width: int = 5, percent: int = 80, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row of each component, all its columns: that of the smallest id, rows without id last; of rows that share this id too, the smallest in
    the order of columns. Rows are told apart by id and set of shingles, so repeated ids of different texts are judged each on its own. Texts without words stay.
    """
    scratch = Scratch(df.sparkSession)
    rows, labels = _solved(_docs(df, doc_id, text), width, percent, scratch)
    keys = ["node", "known", "key"]
    known, key = F.col("doc_id").isNotNull(), F.coalesce("doc_id", F.lit(0))
    each = rows.where("node is not null").groupBy("node", known.alias("known"), key.alias("key")).agg(F.count(F.lit(1)).alias("n"))
    each = each.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    best = each.groupBy("label").agg(F.min(F.struct((~F.col("known")).alias("last"), "key", "node")).alias("best"), F.sum("n").alias("size")).where("size > 1").drop("size")
    ours = (F.col("best.node") == F.col("node")) & (F.col("best.key") == F.col("key")) & (F.col("best.last") != F.col("known"))
    judged = _by_label(each, best).select(*keys, ours.alias("ours"), "n").where("not ours or n > 1")
    judged = scratch.keep(judged.select(*keys, "ours"))
    scratch.drop(rows, labels)

    at, names = df.columns.index(text), [free_name(df, f"of_{k}") for k in keys]
    node, known, key = names

    def run(batches_in: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(batches_in, _SEGMENT):
            b = b.filter(_may_be(bitmap, b.column(b.num_columns - 1))).select(range(b.num_columns - 1))
            sets = shingle_sets(b.column(at).cast(pa.string()), width)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([_node(s) if len(s) else None for s in sets], pa.int64())], [*b.schema.names, node])

    spread = F.when(F.col(node).isNull(), F.xxhash64(*df.columns)).otherwise(F.coalesce(F.col(doc_id).cast("long"), F.lit(0)))  # rows without words match nothing, wherever they go
    bitmap = _id_filter(judged.select(F.when(F.col("known"), F.col("key")).otherwise(F.lit(_LEAST)).alias("id")))

    def others(batches_in: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(batches_in, _SEGMENT):
            yield b.filter(pc.invert(_may_be(bitmap, b.column(b.num_columns - 1)))).select(range(b.num_columns - 1))

    hashed = df.withColumn(free_name(df, "of_id"), _id_hash(F.col(doc_id)))
    told = hashed.mapInArrow(run, StructType([*df.schema.fields]).add(node, "long")).withColumns({known: F.col(doc_id).isNotNull(), key: spread})
    judged = judged.select(*(F.col(k).alias(n) for k, n in zip(keys, names, strict=True)), "ours")
    out = told.join(judged.select(*names), names, "left_anti").select(*df.columns)
    if bitmap is not None:
        out = hashed.mapInArrow(others, df.schema).unionByName(out)
    again = judged.where("ours").select(*names)
    if again.isEmpty():
        return out
    rows = told.join(again, names, "left_semi").groupBy(*names).agg(F.min(F.struct(*df.columns)).alias("row"))
    return out.unionByName(rows.select("row.*"))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(read_table(spark, sf_dir, "documents"), width=4, percent=85)
