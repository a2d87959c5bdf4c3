"""Quality scores by Bradley-Terry pairwise ranking.

A document's strength is linear in features of its whole text. For pairs of one document marked good and one marked
bad, the logistic loss of the strengths' difference (that is, of the weighted difference of features) is minimised. A
quantile of the sample's strengths is the threshold: the one that best separates the marked documents. The score is a logistic
function of the distance to it, so 0.5 is the threshold.

At most ``sample`` labelled documents train the model, those of the smallest hashes of their ids. Features of every
document come from one vectorised pass over its bytes; nothing is shuffled when scoring.

Null and empty texts have all features zero and get a score like any other. Without labels of both kinds every score is the
share of label 1 (0.5 without labels). Repeated rows get equal scores; null labels and ids train nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localfreq.llm.common import batches, read_table, string_bytes
from localfreq.llm.simjoin import word_hashes, word_spans

__all__ = ["FEATURES", "PairRanker", "fit_ranker", "op1_quality_scores", "score_quality", "text_features"]

FEATURES = ("log_bytes", "upper", "bangs", "bars", "symbols", "digits", "beyond_ascii", "lines", "stops", "word_length", "repeats", "distinct", "pairs_distinct", "bangs_any", "symbols_any")

_CLASSES = {"upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", "bangs": b"!", "bars": b"|", "symbols": b"#%&*$@^~<>{}[]\\+=_", "digits": b"0123456789", "lines": b"\n", "stops": b".,;:?"}


def text_features(column: pa.Array) -> np.ndarray:
    """One row of features per text."""
    raw, starts = string_bytes(column)
    n = len(starts) - 1
    size = np.diff(starts)
    per = np.maximum(size, 1)

    def count(flags: np.ndarray) -> np.ndarray:
        sums = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
        return sums[starts[1:]] - sums[starts[:-1]]

    shares = {}
    for name, members in _CLASSES.items():
        table = np.zeros(256, bool)
        table[list(members)] = True
        shares[name] = count(table[raw]) / per
    shares["beyond_ascii"] = count(raw >= 128) / per
    spans = word_spans(raw, starts)
    words, doc = word_hashes(raw, starts, spans)
    many = np.bincount(doc, minlength=n)
    bounds = np.concatenate([[0], np.cumsum(many)])
    each = np.maximum(many, 1)
    same = np.zeros(len(words), bool)
    same[1:] = (words[1:] == words[:-1]) & (doc[1:] == doc[:-1])
    couples = words.copy()
    couples[1:] += words[:-1] * np.uint64(0x9E3779B97F4A7C15)
    kinds = np.array([len(np.unique(words[a:b])) for a, b in zip(bounds[:-1], bounds[1:], strict=True)])
    kinds2 = np.array([len(np.unique(couples[a:b])) for a, b in zip(bounds[:-1], bounds[1:], strict=True)])
    soft = lambda x: np.log1p(50 * x)
    columns = {
        "log_bytes": np.log1p(size), **{k: soft(v) for k, v in shares.items()},
        "word_length": np.log1p(np.bincount(doc, spans[1] - spans[0], n) / each),
        "repeats": soft(np.bincount(doc, same, n) / each), "distinct": np.where(many > 0, kinds / each, 0.0), "pairs_distinct": np.where(many > 0, kinds2 / each, 0.0),
        "bangs_any": np.minimum(1.0, 200 * shares["bangs"]), "symbols_any": np.minimum(1.0, 200 * shares["symbols"]),
    }
    return np.stack([columns[f] for f in FEATURES], axis=1) if n else np.zeros((0, len(FEATURES)))


class PairRanker:
    """Strengths from preference pairs, and a threshold at a quantile of the strengths."""

    def __init__(self, *, pairs: int = 40_000, steps: int = 300, decay: float = 1e-3, seed: int = 7):
        self.pairs, self.steps, self.decay, self.seed = pairs, steps, decay, seed
        self.centre = self.scale = self.weights = None
        self.threshold, self.slope, self.constant = 0.0, 1.0, None

    def fit(self, x: np.ndarray, label: np.ndarray) -> PairRanker:
        good, bad = np.flatnonzero(label == 1), np.flatnonzero(label == 0)
        if not len(good) or not len(bad):
            self.constant = float(label.mean()) if len(label) else 0.5
            return self
        self.centre, self.scale = x.mean(axis=0), x.std(axis=0) + 1e-6
        z = np.clip((x - self.centre) / self.scale, -6, 6)
        rng = np.random.default_rng(self.seed)
        apart = z[rng.choice(good, self.pairs)] - z[rng.choice(bad, self.pairs)]
        w, first, second = np.zeros(z.shape[1]), 0.0, 0.0
        for t in range(1, self.steps + 1):  # Adam on the logistic loss of differences
            p = 1 / (1 + np.exp(np.clip(apart @ w, -30, 30)))
            g = -(apart * p[:, None]).mean(axis=0) + self.decay * w
            first, second = 0.9 * first + 0.1 * g, 0.99 * second + 0.01 * g * g
            w = w - 0.1 * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.99**t)) + 1e-9)
        self.weights = w
        s = z @ w
        cuts = np.quantile(s, np.linspace(0.001, 0.999, 999))
        right = [((s[good] >= c).mean() + (s[bad] < c).mean()) for c in cuts]
        best = np.flatnonzero(np.array(right) >= max(right) - 1e-12)
        self.threshold = float(cuts[best].mean())
        self.slope = 4.0 / (float(np.abs(s - self.threshold).mean()) + 1e-9)
        return self

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        s = np.clip((x - self.centre) / self.scale, -6, 6) @ self.weights
        return 1 / (1 + np.exp(np.clip(-self.slope * (s - self.threshold), -40, 40)))


def fit_ranker(documents: DataFrame, labels: DataFrame, *, sample: int = 6000) -> PairRanker:
    """A ranker from at most ``sample`` rows of labelled documents that are not held out, repeated ids included."""
    known = labels.where("quality is not null and doc_id is not null").where(F.crc32(F.col("doc_id").cast("string")) % 3 != 1)
    chosen = known.groupBy("doc_id").agg(F.max("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = documents.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("doc_id", "text", F.col("quality").cast("int").alias("quality"))

    def run(batches_in: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(batches_in, 1 << 20):
            x = text_features(b.column(1))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), x.shape[1]).cast(pa.list_(pa.float64())), b.column(2)], ["doc_id", "x", "quality"])

    got = rows.mapInArrow(run, "doc_id long, x array<double>, quality int").orderBy(F.xxhash64("doc_id"), "doc_id", "x").limit(sample).toArrow()
    x = np.array(got.column(1).to_pylist(), float).reshape(-1, len(FEATURES))
    return PairRanker().fit(x, got.column(2).to_numpy())


def score_quality(df: DataFrame, ranker: PairRanker) -> DataFrame:
    """``df`` with a column ``quality_score``, in place of one of that name; narrow, all other columns stay."""
    df = df.drop("quality_score")
    at = df.columns.index("text")

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows, 1 << 20):
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(ranker.score(text_features(b.column(at))))], [*b.schema.names, "quality_score"])

    from pyspark.sql.types import DoubleType, StructType

    return df.mapInArrow(run, StructType([*df.schema.fields]).add("quality_score", DoubleType()))


def op1_quality_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    ranker = fit_ranker(docs, read_table(spark, sf_dir, "labels"))
    scored = score_quality(docs, ranker)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), F.col("quality_score").alias("score"), (F.col("quality_score") >= 0.5).cast("int").alias("predicted"))
