"""Helpers shared by the operators: shared-folder checkpoints, sizes and Arrow batches."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words of a text: maximal runs without ASCII white space.
WORD_GAP = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster shares for checkpoints.

    It is the session's ``spark.checkpoint.dir``; only on one machine (tests) may that be unset, and a
    temporary folder takes its place.
    """
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder:
            if not sc.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
            folder = tempfile.mkdtemp(prefix="checkpoint-")
        sc.setCheckpointDir(folder)
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint; Spark deletes it after use only if told to (``spark.cleaner.referenceTracking.cleanCheckpoints``)."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


@contextlib.contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Inside it, each query's shuffle files go when the query ends, not when the driver's memory happens to be cleaned."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


class Workspace:
    """Written tables in the shared folder for the steps of one operator, used by ``with``, whose end deletes them.

    Unlike a checkpoint, a written table has the sizes of what it holds, not those estimated from
    the plan that made it, so plans of later rounds stay as they are.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.root, self.n = spark, f"{shared_folder(spark)}/tables-{uuid.uuid4().hex}", 0
        #: By the identity of each table, which is held so that it stays the only one.
        self.paths: dict[int, tuple[str, DataFrame]] = {}

    def __enter__(self) -> Workspace:
        return self

    def __exit__(self, *_: object) -> None:
        self.close()

    def keep(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n}"
        with shuffles_dropped(self.spark):
            df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = path, out
        return out

    def drop(self, *tables: DataFrame) -> None:
        """Delete tables that :meth:`keep` returned and that no later step reads."""
        for t in tables:
            self._delete(self.paths.pop(id(t))[0])

    def _delete(self, path: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    def close(self) -> None:
        self._delete(self.root)


def unused(df: DataFrame, name: str) -> str:
    """``name``, lengthened until ``df`` has no such column."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def text_bytes(docs: DataFrame, column: str = "text") -> int:
    """Total bytes of a text column; one narrow scan and one row to the driver."""
    return int(docs.agg(F.sum(F.octet_length(column))).first()[0] or 0)


def parts_for(n_bytes: float, target: int = 16 << 20, least: int = 12) -> int:
    """How many groups keep each near ``target`` bytes."""
    return max(least, int(n_bytes // target) + 1)


def slices(texts: list, limit: int = 4 << 20) -> Iterator[tuple[int, int]]:
    """Index ranges of ``texts`` holding about ``limit`` characters each; a longer text stands alone."""
    return stretches([len(t) if t else 0 for t in texts], limit)


def stretches(lengths: list[int], limit: int = 4 << 20) -> Iterator[tuple[int, int]]:
    """Index ranges over texts of these lengths, as :func:`slices` has them."""
    start = size = 0
    for i, n in enumerate(lengths):
        if i > start and size + n > limit:
            yield start, i
            start, size = i, 0
        size += n
    if start < len(lengths):
        yield start, len(lengths)


def release() -> None:
    """Give freed memory back to the system: Python workers live on between tasks."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def tidy(run: Callable) -> Callable:
    """``run`` for mapInArrow, giving memory back when its task ends."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release()

    return go


def list_array(flat: np.ndarray, counts: np.ndarray, kind: pa.DataType) -> pa.Array:
    offsets = np.zeros(len(counts) + 1, np.int32)
    np.cumsum(counts, out=offsets[1:])
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat, kind))
