"""Token counts of flat token files by a separator scan.

A flat token file is a run of little-endian token ids without an index; an end-of-document id stands after every
document. The scan reads blocks of a file independently: one vectorised comparison finds the separators of a block. A
prefix scan over the blocks of each file then stitches documents across block borders: it carries the place of the
last separator over any number of blocks that have none. Only separators and two numbers a block are shuffled.

An empty file or block has no documents. Tokens after a file's last separator form an unfinished document, reported
with ``ended`` false. Documents without tokens count 0. Null blocks count as empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from localfreq.llm.common import batches, read_table, texts_of

__all__ = ["file_blocks", "flat_blocks", "op9_token_counts", "scan_separators"]


def file_blocks(spark: SparkSession, path: str, *, width: int = 2, block_tokens: int = 1 << 20) -> DataFrame:
    """(file, block, data) of the flat token files at ``path``, of any size: Spark lists them, and every block is its own range of bytes.

    Ranges are read by Arrow's file systems (local, HDFS, S3, GCS), wherever the block's task runs. An empty file has one empty block.
    """
    step = width * block_tokens

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        for b in rows:
            for name, k, size in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                system, inner = fs.FileSystem.from_uri(name)
                with system.open_input_file(inner) as f:
                    f.seek(k * step)
                    data = f.read(max(0, min(step, size - k * step)))
                yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([k], pa.int64()), pa.array([data], pa.binary())], ["file", "block", "data"])

    files = spark.read.format("binaryFile").load(path).select("path", "length")
    last = F.greatest(F.lit(0), F.ceil(F.col("length") / F.lit(step)) - 1)
    ranges = files.select("path", F.explode(F.sequence(F.lit(0).cast("long"), last.cast("long"))).alias("block"), "length")
    return ranges.repartition("path", "block").mapInArrow(run, "file string, block long, data binary")


def _scan(data: bytes | None, dtype: str, end_id: int) -> tuple[int, np.ndarray]:
    ids = np.frombuffer(data or b"", dtype)
    return len(ids), np.flatnonzero(ids == end_id)


def scan_separators(blocks: DataFrame, *, end_id: int, width: int = 2) -> DataFrame:
    """(file, ordinal, start, n_tokens, ended): one row per document of each file, in the file's order.

    Blocks that know which documents end in them (``doc_ids``) give doc_id as well.
    """
    dtype, names = {2: "<u2", 4: "<u4"}[width], ["file", "block", "data", *(["doc_ids"] if "doc_ids" in blocks.columns else [])]

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in rows:
            found = [_scan(x, dtype, end_id) for x in b.column(2).to_pylist()]
            offsets = pa.array(np.cumsum([0, *(len(p) for _, p in found)]), pa.int32())
            places = pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([p for _, p in found]) if found else np.zeros(0, np.int64)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([n for n, _ in found], pa.int64()), places, *b.columns[3:]], ["file", "block", "size", "places", *names[3:]])

    return stitched(blocks.select(*names).mapInArrow(run, "file string, block long, size long, places array<long>" + ", doc_ids array<long>" * (len(names) - 3)))


def stitched(scanned: DataFrame) -> DataFrame:
    """Documents from (file, block, size, places of separators within the block): the prefix scan."""
    by = Window.partitionBy("file").orderBy("block")
    before = by.rowsBetween(Window.unboundedPreceding, -1)
    n = F.size("places")
    last = F.when(n > 0, F.col("at") + F.element_at("places", -1))
    summed = scanned.withColumns({"at": F.coalesce(F.sum("size").over(before), F.lit(0)), "seen": F.coalesce(F.sum(n).over(before), F.lit(0)).cast("long"), "final": F.lead("block").over(by).isNull()})
    carried = summed.withColumn("since", F.coalesce(F.last(last, ignorenulls=True).over(before) + 1, F.lit(0)))
    owner = [F.element_at("doc_ids", F.col("i") + 1).alias("doc_id")] if "doc_ids" in scanned.columns else []
    start = F.when(F.col("i") == 0, F.col("since")).otherwise(F.col("at") + F.element_at("places", F.greatest(F.col("i"), F.lit(1))) + 1)
    ended = carried.select("*", F.posexplode("places").alias("i", "p")).select("file", (F.col("seen") + F.col("i")).alias("ordinal"), start.alias("start"), (F.col("at") + F.col("p") - start).alias("n_tokens"), F.lit(True).alias("ended"), *owner)
    tail, stop = F.when(n > 0, last + 1).otherwise(F.col("since")), F.col("at") + F.col("size")
    open_ = carried.where(F.col("final") & (stop > tail)).select("file", (F.col("seen") + n).alias("ordinal"), tail.alias("start"), (stop - tail).alias("n_tokens"), F.lit(False).alias("ended"), *([F.lit(None).cast("long").alias("doc_id")] if owner else []))
    return ended.unionByName(open_)


def flat_blocks(df: DataFrame, path: str, *, end_id: int, width: int = 2, block_tokens: int = 1 << 16, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The blocks that flat token files of ``df`` have, one file a task, each with the ids of the documents that end in it.

    Names of special tokens in a text are ordinary text here, so no text can end a document.
    Columns file, block, data, doc_ids. Write ``data`` to keep the files; the scan itself looks at ``data`` only.
    """

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from localfreq.llm.bpe import ByteBpe

        bpe, end, step = ByteBpe(path, special_as_text=True, packed=width), end_id.to_bytes(width, "little"), width * block_tokens
        name, block, rest, owners = f"part-{TaskContext.get().partitionId():06d}", 0, bytearray(), []  # owners: (end in rest, id)

        def out(data: bytes, ids: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([block], pa.int64()), pa.array([data], pa.binary()), pa.array([ids], pa.list_(pa.int64()))], ["file", "block", "data", "doc_ids"])

        for b in batches(rows):
            for i, t in zip(b.column(0).to_pylist(), texts_of(b.column(1)), strict=True):
                rest += bpe.encode(t)[1] + end
                owners.append((len(rest), i))
                while len(rest) >= step:
                    k = sum(e <= step for e, _ in owners)
                    yield out(bytes(rest[:step]), [d for _, d in owners[:k]])
                    del rest[:step]
                    owners, block = [(e - step, d) for e, d in owners[k:]], block + 1
        if rest:
            yield out(bytes(rest), [d for _, d in owners])

    return df.select(df[doc_id].cast("long").alias("doc_id"), df[text].cast("string").alias("text")).mapInArrow(run, "file string, block long, data binary, doc_ids array<long>")


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, file, ordinal, start, n_tokens) of every document, counted from the flat stream of its tokens."""
    import public_tokenizers

    end = 50256
    blocks = flat_blocks(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), end_id=end)
    return scan_separators(blocks, end_id=end).where("ended").select("doc_id", "file", "ordinal", "start", "n_tokens")
