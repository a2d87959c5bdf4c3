"""Helpers that the training-data operators share."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

__all__ = ["Scratch", "checkpointed", "collect_garbage", "free_name", "read_table", "shared_folder", "shuffle_parts", "string_bytes", "texts_of", "trim"]


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the given folder; only Spark's readers touch the path, so any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the one the session names in ``spark.checkpoint.dir``.

    Only a session that runs in one machine gets a folder of its own where none is set; on a cluster that is an error.
    """
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not context.master.startswith("local") or context.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
            folder = tempfile.mkdtemp(prefix="checkpoints-")
        context.setCheckpointDir(folder)
    return context._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage by a reliable checkpoint, which survives the loss of executors."""
    shared_folder(df.sparkSession)
    out = df.checkpoint(eager=True)
    collect_garbage(df.sparkSession)
    return out


#: The share of its limit that the driver's heap may take between steps.
_HEAP_SHARE = 0.5


def collect_garbage(spark: SparkSession) -> None:
    """Between steps, let a driver whose heap has grown past a share of its limit collect its garbage and give memory back.

    A step leaves plans, broadcasts and shuffles that nothing uses any more. Spark frees them when the driver's heap is collected, and a heap that
    still may grow grows instead.
    """
    gc.collect()  # what only dead Python objects hold
    runtime = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    if runtime.totalMemory() > _HEAP_SHARE * runtime.maxMemory():
        runtime.gc()


class Scratch:
    """Tables of one job in the shared folder. Each is written once, read by column, and deleted when its readers are done.

    Written tables cut the lineage and survive lost executors. The shuffle files behind a table go as soon as it is written, by
    Spark's own clean-up at the end of an execution, so that the disk holds one step's exchanges at a time.
    """

    _CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

    def __init__(self, spark: SparkSession):
        self.spark, self.base, self.turn = spark, f"{shared_folder(spark)}/tables-{uuid.uuid4().hex}", 0

    def keep(self, df: DataFrame) -> DataFrame:
        """``df`` as a written table."""
        self.turn += 1
        path, before = f"{self.base}/{self.turn}", self.spark.conf.get(self._CLEAN, "false")
        self.spark.conf.set(self._CLEAN, "true")
        try:
            df.write.parquet(path)
        finally:
            self.spark.conf.set(self._CLEAN, before)
        collect_garbage(self.spark)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, *tables: DataFrame) -> None:
        """Delete tables that nothing reads any more."""
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        for t in tables:
            path = jvm.org.apache.hadoop.fs.Path(t._scratch_path)
            path.getFileSystem(conf).delete(path, True)


def free_name(df: DataFrame, wish: str) -> str:
    """A column name like ``wish`` that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    while wish.lower() in taken:
        wish += "_"
    return wish


def trim() -> None:
    """Give memory that a worker has freed back to the system: Spark keeps workers for later tasks."""
    import ctypes

    gc.collect()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps its own counsel
        pass


def texts_of(column: pa.Array) -> list[str]:
    """Texts of an Arrow column, null as the empty text."""
    return [x or "" for x in column.to_pylist()]


def string_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column without copying each text; null is the empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    n = len(column)
    starts = np.frombuffer(offsets, np.int64, n + 1, column.offset * 8) if n else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[starts[0]:starts[-1]], starts - starts[0]


def batches(rows: Iterator[pa.RecordBatch], most_bytes: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that each holds about ``most_bytes`` at most (one row at least)."""
    for b in rows:
        if b.num_rows <= 1 or b.nbytes <= most_bytes:
            yield b
            continue
        step = max(1, int(b.num_rows * most_bytes / b.nbytes))
        for i in range(0, b.num_rows, step):
            yield b.slice(i, step)
    trim()
