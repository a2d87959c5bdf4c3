"""Toxicity by a bidirectional gated recurrent network with attention pooling, trained in numpy.

A text's words (letters and digits, lower case) are read in windows of ``WINDOW`` words, each half over the last. A
word's input joins a word part and character parts (its first and last characters): hashed rows of embeddings whose
first channel holds the smoothed log-odds of the row among the training documents and whose other channels start as random
numbers and are trained with the network. Forward and backward gated recurrent units read a window, attention weighs their states, and a linear layer gives the window's
logit. A document's logit is the largest of all its windows; training follows that window (multiple-instance learning).

At most ``sample`` toxic and ``clean`` other labelled rows train the model; of texts of more than ``most_words`` words,
evenly spread windows of that many words in all do. Scoring reads all
windows of every whole text, in blocks of fixed size, without a shuffle.

Null and empty texts and texts without words score as the least suspicious window would. Without labels of both kinds all
scores are the share of label 1. Repeated rows get equal scores; null labels and ids train nothing.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from copy import copy

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.llm.common import batches, collect_garbage, read_table, string_bytes, trim
from localfreq.llm.simjoin import _tables, mix, word_hashes, word_spans

__all__ = ["WINDOW", "AttentiveGru", "fit_toxicity", "op6_toxicity", "score_toxicity", "word_inputs"]

WINDOW, STRIDE = 24, 12
_ROWS = (1 << 16, 1 << 13, 1 << 13)  # word, first characters, last characters
_RANDOM, _HIDDEN = 3, 8
_CHANNELS = 3 * (1 + _RANDOM)


def _letters() -> np.ndarray:
    table = np.zeros(256, bool)
    table[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
    return table


def word_inputs(raw: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows, document): for each word the embedding rows of the word, its first four and its last three bytes."""
    s, e = word_spans(raw, starts, _letters())
    words, doc = word_hashes(raw, starts, (s, e))
    _, value, powers, _ = _tables()
    heads, tails = np.zeros(len(s), np.uint64), np.zeros(len(s), np.uint64)
    for i in range(4):
        at = np.minimum(s + i, e - 1)
        heads += np.where(s + i < e, value[raw[at]], np.uint64(0)) * powers[i]
    for i in range(3):
        at = np.maximum(e - 1 - i, s)
        tails += np.where(e - 1 - i >= s, value[raw[at]], np.uint64(0)) * powers[i]
    rows = [mix(h) % np.uint64(n) for h, n in zip((words, heads, tails), _ROWS, strict=True)]
    return np.stack(rows, axis=1).astype(np.int32), doc


def windows_of(many: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first word, words, document) of all windows of documents with so many words, whose words lie one after another."""
    n = np.where(many > 0, np.maximum(1, -(-(many - WINDOW) // STRIDE) + 1), 0)
    doc = np.repeat(np.arange(len(many)), n)
    turn = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
    base = np.cumsum(many) - many
    return base[doc] + turn * STRIDE, np.minimum(WINDOW, many[doc] - turn * STRIDE), doc


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-x))


class AttentiveGru:
    """Bidirectional gated recurrent units with attention pooling; all parameters are small numpy arrays."""

    def __init__(self, seed: int = 11):
        rng = np.random.default_rng(seed)
        h, small = _HIDDEN, lambda *shape: rng.normal(0, 0.15, shape).astype(np.float32)
        self.tables = [np.concatenate([np.zeros((n, 1), np.float32), rng.normal(0, 0.1, (n, _RANDOM)).astype(np.float32)], axis=1) for n in _ROWS]
        self.p = {"w": small(_CHANNELS, 6 * h), "b": np.zeros(6 * h, np.float32), "uf": small(h, 3 * h), "ub": small(h, 3 * h), "v": small(2 * h), "o": small(2 * h), "c": np.zeros(1, np.float32)}
        for side in (0, 3 * h):  # log-odds open the candidate state, in which training starts
            self.p["w"][[0, 1 + _RANDOM, 2 + 2 * _RANDOM], side + 2 * h:side + 3 * h] += 0.3
        self.p["v"] += 0.3
        self.p["o"] += 0.3
        self.shift, self.constant, self.projected = 0.0, None, None

    def embed(self, rows: np.ndarray) -> np.ndarray:
        return np.concatenate([t[rows[:, i]] for i, t in enumerate(self.tables)], axis=1)

    def project(self) -> None:
        """Takes the tables through the input weights once, for scoring in small blocks."""
        c = 1 + _RANDOM
        self.projected = [t @ self.p["w"][i * c:(i + 1) * c] for i, t in enumerate(self.tables)]

    def gates(self, rows: np.ndarray) -> np.ndarray:
        """Input parts of all gates of both directions, per word."""
        out = np.repeat(self.p["b"][None], len(rows), axis=0)
        if self.projected is not None:
            for i, t in enumerate(self.projected):
                out += t[rows[:, i]]
            return out
        c = 1 + _RANDOM
        for i, t in enumerate(self.tables):
            out += (t @ self.p["w"][i * c:(i + 1) * c])[rows[:, i]] if len(rows) > len(t) else t[rows[:, i]] @ self.p["w"][i * c:(i + 1) * c]
        return out

    def _direction(self, a: np.ndarray, mask: np.ndarray, u: np.ndarray, keep: list | None, order: range) -> np.ndarray:
        """States (step, window, hidden) of one direction; a: (step, window, 3h)."""
        steps, n, _ = a.shape
        hsize = _HIDDEN
        h = np.zeros((n, hsize), np.float32)
        out = np.empty((steps, n, hsize), np.float32)
        for t in order:
            hu = h @ u
            zr = _sigmoid(a[t, :, :2 * hsize] + hu[:, :2 * hsize])
            z, r = zr[:, :hsize], zr[:, hsize:]
            cand = np.tanh(a[t, :, 2 * hsize:] + r * hu[:, 2 * hsize:])
            new = cand + z * (h - cand)
            if keep is not None:
                keep.append((t, h, z, r, cand, hu[:, 2 * hsize:]))
            h = new * mask[t][:, None]
            out[t] = h
        return out

    def forward(self, gates: np.ndarray, first: np.ndarray, size: np.ndarray, tape: dict | None = None) -> np.ndarray:
        """Logits of windows of words whose gates are given."""
        steps = np.arange(WINDOW)
        at = np.minimum(first[None] + steps[:, None], len(gates) - 1)
        mask = (steps[:, None] < size[None]).astype(np.float32)
        a = gates[at]
        k = 3 * _HIDDEN
        kf, kb = (None, None) if tape is None else ([], [])
        hf = self._direction(a[:, :, :k], mask, self.p["uf"], kf, range(WINDOW))
        hb = self._direction(a[:, :, k:], mask, self.p["ub"], kb, range(WINDOW - 1, -1, -1))
        states = np.concatenate([hf, hb], axis=2)
        e = states @ self.p["v"]
        e = np.where(mask > 0, e, -1e9)
        e = np.exp(e - e.max(axis=0))
        alpha = e / e.sum(axis=0)
        pooled = np.einsum("tn,tnh->nh", alpha, states)
        if tape is not None:
            tape.update(at=at, mask=mask, kf=kf, kb=kb, states=states, alpha=alpha, pooled=pooled)
        return pooled @ self.p["o"] + self.p["c"][0]

    def backward(self, tape: dict, d: np.ndarray, inputs: np.ndarray) -> dict[str, np.ndarray]:
        """Gradients for the logits' gradient d; inputs: the words' embedded channels."""
        h, k = _HIDDEN, 3 * _HIDDEN
        states, alpha, mask = tape["states"], tape["alpha"], tape["mask"]
        g = {"o": tape["pooled"].T @ d, "c": np.array([d.sum()], np.float32)}
        dp = d[:, None] * self.p["o"]
        da = np.einsum("nh,tnh->tn", dp, states)
        de = alpha * (da - (alpha * da).sum(axis=0))
        g["v"] = np.einsum("tn,tnh->h", de, states)
        ds = alpha[:, :, None] * dp[None] + de[:, :, None] * self.p["v"]
        dgates = np.zeros((WINDOW, len(d), 2 * k), np.float32)
        for side, u, kept in ((0, "uf", tape["kf"]), (1, "ub", tape["kb"])):
            carry = np.zeros((len(d), h), np.float32)
            gu = np.zeros_like(self.p[u])
            for t, prev, z, r, cand, hun in reversed(kept):
                total = (ds[t, :, side * h:(side + 1) * h] + carry) * mask[t][:, None]
                dz = total * (prev - cand) * z * (1 - z)
                dc = total * (1 - z) * (1 - cand * cand)
                dr = dc * hun * r * (1 - r)
                dhu = np.concatenate([dz, dr, dc * r], axis=1)
                dgates[t, :, side * k:(side + 1) * k] = np.concatenate([dz, dr, dc], axis=1)
                gu += prev.T @ dhu
                carry = total * z + dhu @ self.p[u].T
            g[u] = gu
        x = inputs[tape["at"]] * mask[:, :, None]
        dgates *= mask[:, :, None]
        g["w"] = np.einsum("tnc,tng->cg", x, dgates)
        g["x"] = dgates @ self.p["w"].T
        g["b"] = dgates.sum(axis=(0, 1))
        return g

    def _train_tables(self, rows: np.ndarray, grads: np.ndarray, moved: list[np.ndarray], rate: float = 0.02) -> None:
        """One step of the embeddings of the words read, each channel by the size of its gradients so far; log-odds stay."""
        c = 1 + _RANDOM
        for i, t in enumerate(self.tables):
            at, back = np.unique(rows[:, :, i], return_inverse=True)
            g = np.zeros((len(at), _RANDOM), np.float32)
            np.add.at(g, back.ravel(), grads[:, :, i * c + 1:(i + 1) * c].reshape(-1, _RANDOM))
            moved[i][at] += g * g
            t[at, 1:] -= rate * g / np.sqrt(moved[i][at])

    def logits(self, rows: np.ndarray, many: np.ndarray, block: int = 2048) -> np.ndarray:
        """The largest logit over all windows of each document; -20 without words."""
        first, size, doc = windows_of(many)
        gates = self.gates(rows)
        out = np.full(len(many), -20.0, np.float32)
        for i in range(0, len(first), block):
            np.maximum.at(out, doc[i:i + block], self.forward(gates, first[i:i + block], size[i:i + block]))
        return out

    def score(self, rows: np.ndarray, many: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(many), self.constant)
        x = self.logits(rows, many).astype(float) - self.shift + math.log(0.3 / 0.7)
        return 1 / (1 + np.exp(np.clip(-x, -40, 40)))

    def fit(self, docs: list[np.ndarray], label: np.ndarray, *, steps: int = 160, batch: int = 192, seed: int = 5) -> AttentiveGru:
        if len({*label.tolist()}) < 2:
            self.constant = float(label.mean()) if len(label) else 0.0
            return self
        ones, zeros = float(label.sum()), float((1 - label).sum())
        for i, t in enumerate(self.tables):
            seen = np.zeros((2, len(t)))
            for d, y in zip(docs, label, strict=True):
                seen[int(y), np.unique(d[:, i])] += 1
            rate = (seen + 3 * seen.sum(axis=0) / (ones + zeros) * np.array([[zeros], [ones]]) / (ones + zeros) + 0.5) / (np.array([[zeros], [ones]]) + 1)
            t[:, 0] = np.where(seen.sum(axis=0) >= 4, np.clip(np.log(rate[1] / rate[0]), -1, 4), 0.0)
        rng = np.random.default_rng(seed)
        usable = [np.array([i for i in np.flatnonzero(label == y) if len(docs[i])]) for y in (0, 1)]
        if not all(map(len, usable)):
            self.constant = float(label.mean())
            return self
        m, v = ({k: np.zeros_like(x) for k, x in self.p.items()} for _ in range(2))
        moved = [np.full((len(t), _RANDOM), 1e-6, np.float32) for t in self.tables]
        for step in range(1, steps + 1):
            chosen = np.concatenate([rng.choice(u, batch // 2) for u in usable])
            rows, many = np.concatenate([docs[i] for i in chosen]), np.array([len(docs[i]) for i in chosen])
            first, size, doc = windows_of(many)
            gates = self.gates(rows)
            logit = self.forward(gates, first, size)
            top = np.lexsort((logit, doc))
            top = top[np.flatnonzero(np.append(doc[top][1:] != doc[top][:-1], True))]
            tape: dict = {}
            x = self.forward(gates, first[top], size[top], tape)
            y = label[chosen][doc[top]]
            grads = self.backward(tape, ((_sigmoid(x) - y) / len(y)).astype(np.float32), self.embed(rows))
            self._train_tables(rows[tape["at"]], grads.pop("x") * tape["mask"][:, :, None], moved)
            for k, gr in grads.items():
                gr = np.clip(gr + 1e-4 * self.p[k], -1, 1)
                m[k] = 0.9 * m[k] + 0.1 * gr
                v[k] = 0.99 * v[k] + 0.01 * gr * gr
                self.p[k] = (self.p[k] - 0.02 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        x = np.concatenate([self.logits(np.concatenate(docs[i:i + 64]), np.array([len(d) for d in docs[i:i + 64]])) for i in range(0, len(docs), 64)])
        order = np.sort(x)
        cuts = (order[1:] + order[:-1]) / 2
        right = [(x[label == 1] >= c).mean() + 2 * (x[label == 0] < c).mean() for c in cuts]
        best = np.flatnonzero(np.array(right) >= max(right) - 1e-12)
        self.shift = float((cuts[best[0]] + cuts[best[-1]]) / 2)
        return self


def _spread(rows: np.ndarray, most_words: int) -> np.ndarray:
    """The words' rows of one text, or of evenly spread windows of ``most_words`` words in all."""
    if len(rows) <= most_words:
        return rows
    first = np.linspace(0, len(rows) - WINDOW, most_words // WINDOW).astype(np.int64)
    return rows[(first[:, None] + np.arange(WINDOW)).ravel()]


def fit_toxicity(documents: DataFrame, labels: DataFrame, *, sample: int = 1500, clean: int = 4000, most_words: int = 4800) -> AttentiveGru:
    """A network from at most ``sample`` toxic and ``clean`` other labelled rows that are not held out, repeated ids included."""
    known = labels.where("toxic is not null and doc_id is not null").where(F.crc32(F.col("doc_id").cast("string")) % 4 != 2).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = [known.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n) for y, n in ((0, clean), (1, sample))]
    rows = documents.select("doc_id", "text").join(F.broadcast(chosen[0].unionByName(chosen[1])), "doc_id").select("doc_id", "text", "toxic")

    def run(batches_in: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(batches_in, 1 << 18):
            rows, doc = word_inputs(*string_bytes(b.column(1)))
            bounds = np.searchsorted(doc, np.arange(b.num_rows + 1))
            parts = [_spread(rows[i:j], most_words) for i, j in zip(bounds[:-1], bounds[1:], strict=True)]
            offsets = pa.array(np.cumsum([0, *map(len, parts)]) * 3, pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, pa.array(np.concatenate(parts).ravel())), b.column(2)], ["doc_id", "rows", "toxic"])

    read = rows.mapInArrow(run, "doc_id long, rows array<int>, toxic int")
    order = [F.xxhash64("doc_id"), "doc_id", F.xxhash64("rows")]
    got = read.where("toxic = 0").orderBy(*order).limit(clean).unionByName(read.where("toxic = 1").orderBy(*order).limit(sample)).toArrow().combine_chunks()
    collect_garbage(documents.sparkSession)  # training needs the driver's memory now
    label, lists = got.column(2).to_numpy(), got.column(1)
    docs = [np.asarray(lists[i].values.to_numpy(zero_copy_only=False), np.int32).reshape(-1, 3) for i in range(len(lists))]
    order = np.lexsort((np.array([len(d) for d in docs]), got.column(0).to_numpy()))
    model = AttentiveGru().fit([docs[i] for i in order], label[order].astype(np.float32))
    del got, lists, docs
    trim()
    return model


def score_toxicity(df: DataFrame, model: AttentiveGru) -> DataFrame:
    """``df`` with a column ``toxicity_score``, in place of one of that name; narrow, all other columns stay."""
    from pyspark.sql.types import DoubleType, StructType

    df = df.drop("toxicity_score")
    at = df.columns.index("text")
    shared = df.sparkSession.sparkContext.broadcast(model)  # of fixed size

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = copy(shared.value)  # its projections go with the task
        model.project()
        for b in batches(rows, 1 << 18):
            words, doc = word_inputs(*string_bytes(b.column(at)))
            score = model.score(words, np.bincount(doc, minlength=b.num_rows))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score, pa.float64())], [*b.schema.names, "toxicity_score"])

    return df.mapInArrow(run, StructType([*df.schema.fields]).add("toxicity_score", DoubleType()))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    scored = score_toxicity(docs, fit_toxicity(docs, read_table(spark, sf_dir, "labels")))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), F.col("toxicity_score").alias("score"), (F.col("toxicity_score") >= 0.3).cast("int").alias("predicted"))
