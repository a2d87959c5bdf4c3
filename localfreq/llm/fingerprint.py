"""Homomorphic multiset fingerprints of documents, with DataFrame expressions only.

A text is cut into paragraphs (lines, and sentences of lines), each hashed to wide vectors. A document's
fingerprint is the sum of its paragraphs' vectors, every lane modulo a power of two: order does not matter, and a
paragraph is added or taken away by adding or subtracting its vector, without the rest of the document.

The vector of a paragraph has a count, four lanes of 32 hash bits (these carry equality), and 128 sign lanes of
+1 or -1. A difference of two fingerprints is the sum over the paragraphs that only one of them has,
so the mean square of its sign lanes estimates how many these are: likeness is one less that share, 0 to 1.

Nulls count as empty texts; an empty text has one empty paragraph. Equal texts have equal fingerprints; texts that differ
only in the order of paragraphs do too. Null ids stand last in the descending order and repeated ids
by a hash of their texts, then the texts; every input row gives one row. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.llm.common import read_table, shuffle_parts

__all__ = ["changed_sums", "edited_texts", "fingerprint_of", "fingerprint_sums", "likeness", "op4_document_fingerprints", "paragraphs", "with_next"]

#: Two sign lanes of 32 bits share a long, so sums stay apart for more paragraphs than a string can have.
_GROUP, _HASHES = 32, 2
_MASK = 1 | 1 << _GROUP
_LEAST = -(2**63)


def paragraphs(text: Column) -> Column:
    """The paragraphs of a text: lines, cut after the ends of sentences."""
    return F.split(text, r"\n|(?<=[.!?|]) ")


def _sum_columns(unit: Column) -> dict[str, Column]:
    """Name -> aggregate over a document's paragraphs."""
    hashes = [F.xxhash64(unit, F.lit(seed)) for seed in range(_HASHES)]
    low = [F.sum(h.bitwiseAND(F.lit(0xFFFFFFFF))) for h in hashes]
    high = [F.sum(F.shiftrightunsigned(h, 32)) for h in hashes]
    signs = [F.sum(F.shiftrightunsigned(h, j).bitwiseAND(F.lit(_MASK))) for h in hashes for j in range(_GROUP)]
    return {"n": F.count(F.lit(1)), **{f"e{i}": c for i, c in enumerate(low + high)}, **{f"s{i}": c for i, c in enumerate(signs)}}


def _names() -> list[str]:
    return ["n", *(f"e{i}" for i in range(2 * _HASHES)), *(f"s{i}" for i in range(_HASHES * _GROUP))]


def fingerprint_sums(df: DataFrame, keys: list[str], unit: str) -> DataFrame:
    """Sums of the paragraphs' vectors by ``keys``; one row a paragraph in, partial sums before any exchange."""
    return df.groupBy(*keys).agg(*(c.alias(k) for k, c in _sum_columns(F.col(unit)).items()))


def changed_sums(sums: DataFrame, inserted: DataFrame, deleted: DataFrame, keys: list[str]) -> DataFrame:
    """Sums by ``keys`` after paragraphs come and go, from ``fingerprint_sums`` of the document before, of what is inserted and of what is
    deleted (a part of the document): documents need not be read again. A key that is only inserted is a new document.
    """
    names = _names()
    turned = deleted.select(*keys, *((-F.col(c)).alias(c) for c in names))
    both = sums.select(*keys, *names).unionByName(inserted.select(*keys, *names)).unionByName(turned)
    return both.groupBy(*keys).agg(*(F.sum(c).alias(c) for c in names))


def _lanes(prefix: str = "") -> list[Column]:
    """The 128 signed sums: twice the count of set bits less the number of paragraphs."""
    n = F.col(f"{prefix}n")
    return [F.shiftrightunsigned(F.col(f"{prefix}s{i}"), _GROUP * k).bitwiseAND(F.lit((1 << _GROUP) - 1)) * 2 - n for i in range(_HASHES * _GROUP) for k in range(2)]


def fingerprint_of(prefix: str = "") -> Column:
    """The fingerprint as text: hexadecimal lanes, equality lanes modulo 2**32 and sign lanes modulo 2**16."""
    wide = [F.lpad(F.lower(F.hex(F.col(f"{prefix}{c}").bitwiseAND(F.lit(0xFFFFFFFF)))), 8, "0") for c in _names()[: 1 + 2 * _HASHES]]
    return F.concat(*wide, *(F.lpad(F.lower(F.hex(x.bitwiseAND(F.lit(0xFFFF)))), 4, "0") for x in _lanes(prefix)))


def _packed(prefix: str = "") -> Column:
    return F.array(*(x.cast("double") for x in _lanes(prefix)))


def likeness(a: Column, b: Column) -> Column:
    """Likeness of two arrays of signed lanes: 1 for equal ones, about 0 for those without common paragraphs."""
    sq = lambda x: F.aggregate(x, F.lit(0.0), lambda s, v: s + v * v)
    apart = F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v)
    both = sq(a) + sq(b)
    return F.when(apart == 0, F.lit(1.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), 1 - apart / both)))


def _bucket(cuts: list[int], key: Column, h: Column) -> Column:
    """The range of a row among sorted cuts, which repeat where one id holds several ranges: such an id's rows are cut by their hash.

    The search has two steps, so that its cost grows with the root of the number of cuts.
    """
    many = {c: cuts.count(c) for c in set(cuts)} if len(set(cuts)) < len(cuts) else {}
    cuts = sorted(set(cuts))
    step = max(1, int(len(cuts) ** 0.5))
    groups = [cuts[i:i + step] for i in range(0, len(cuts), step)]
    first = F.size(F.filter(F.lit([g[-1] for g in groups]), lambda c: c < key)) if groups else F.lit(0)
    inside = F.coalesce(F.size(F.filter(F.try_element_at(F.array(*(F.lit(g) for g in groups)), first + 1), lambda c: c < key)), F.lit(0)) if groups else F.lit(0)
    place = (first * step + inside).cast("long") * (1 << 20)
    hot = {c: n for c, n in many.items() if n > 1}
    if not hot:
        return place
    parts = F.try_element_at(F.create_map(*(F.lit(x) for kv in hot.items() for x in kv)), key)
    return place + F.coalesce(F.floor(F.pmod(h, F.lit(1 << 20)) * parts / F.lit(1 << 20)), F.lit(0)).cast("long")


def with_next(docs: DataFrame, parts: int) -> DataFrame:
    """(bucket, ghost, doc_id, h, text, next_text, rn): each text with the next in descending order of ids, the last with the first.

    Ids are cut into ``parts`` ranges at percentiles (an id that holds several ranges, by a hash of its texts), each range is sorted by one
    task, and the first document of the range below is copied into it as a ghost row, so that no row needs a second exchange.
    """
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    key, h = F.coalesce(F.col("doc_id"), F.lit(_LEAST)), F.pmod(F.xxhash64("text"), F.lit(1 << 20))
    cuts = docs.select(key.alias("k")).agg(F.percentile_approx("k", [i / parts for i in range(1, parts)] or [0.5], max(10_000, 10 * parts)).alias("c")).first()["c"]
    dealt = docs.withColumn("h", h).withColumn("bucket", _bucket(sorted(map(int, cuts or [])), key, F.col("h")))
    edges = sorted(((r["bucket"], *r["top"]) for r in dealt.groupBy("bucket").agg(F.max(F.struct(key.alias("k"), "h")).alias("top")).collect()), reverse=True)  # one row a range
    if not edges:
        return dealt.withColumns({"ghost": F.lit(0), "next_text": F.lit(""), "rn": F.lit(1)})
    wanted = docs.sparkSession.createDataFrame([(b, *edges[(i + 1) % len(edges)][1:]) for i, (b, *_) in enumerate(edges)], "into long, top long, top_h long")
    heads = docs.withColumns({"top": key, "top_h": h}).join(F.broadcast(wanted), ["top", "top_h"]).groupBy("into").agg(F.min("text").alias("text"))
    ghosts = heads.select(F.lit(None).cast("long").alias("doc_id"), "text", F.lit(0).cast("long").alias("h"), F.col("into").alias("bucket"), F.lit(1).alias("ghost"))
    rows = dealt.withColumn("ghost", F.lit(0)).unionByName(ghosts).repartitionByRange(parts, "bucket")
    by = Window.partitionBy("bucket").orderBy("ghost", F.col("doc_id").desc_nulls_last(), F.desc("h"), "text")
    return rows.withColumns({"next_text": F.lead("text").over(by), "rn": F.row_number().over(by)})


def edited_texts(paired: DataFrame) -> DataFrame:
    """Adds n_chars and edited: the last third of the code points replaced by the first as many of the next text."""
    n = F.length("text")
    third = F.floor(n / 3).cast("int")
    edited = F.concat(F.expr("substring(text, 1, length(text) - cast(floor(length(text) / 3) as int))"), F.coalesce(F.expr("substring(next_text, 1, cast(floor(length(text) / 3) as int))"), F.lit("")))
    return paired.withColumns({"n_chars": n.cast("long"), "edited": F.when(third > 0, edited).otherwise(F.col("text"))})


def op4_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    parts = max(2, shuffle_parts(spark), -(-docs.count() // 500_000))  # ranges grow with the rows
    rows = edited_texts(with_next(docs, parts))
    rows = rows.select("bucket", "rn", "ghost", "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "text", "edited")
    both = F.array(F.struct(F.lit(0).alias("which"), paragraphs(F.col("text")).alias("units")), F.struct(F.lit(1).alias("which"), paragraphs(F.col("edited")).alias("units")))
    keys = ["bucket", "rn", "ghost", "doc_id", "n_chars", "edited_sha256"]
    units = rows.select(*keys, F.explode(both).alias("v")).select(*keys, F.col("v.which").alias("which"), F.explode("v.units").alias("unit"))
    sums = fingerprint_sums(units, [*keys, "which"], "unit").select(*keys, "which", fingerprint_of().alias("f"), _packed().alias("lanes"))
    one = sums.groupBy(*keys).agg(*(F.max(F.when(F.col("which") == w, F.col(c))).alias(f"{c}{w}") for w in (0, 1) for c in ("f", "lanes")))
    by = Window.partitionBy("bucket").orderBy("rn")
    out = one.withColumn("lanes_next", F.lead("lanes0").over(by)).where("ghost = 0")
    return out.select("doc_id", "n_chars", "edited_sha256", F.col("f0").alias("fingerprint"), F.col("f1").alias("edited_fingerprint"), F.round(likeness(F.col("lanes0"), F.col("lanes1")), 6).alias("near_edited"), F.round(likeness(F.col("lanes0"), F.coalesce("lanes_next", "lanes0")), 6).alias("near_next"))
