"""Shared helpers: shared-folder tables, table readers, plan sizes, byte planes."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
import weakref

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Words are maximal runs of anything but space and U+0009 to U+000D; ``bytes.split()`` cuts UTF-8 at exactly these.
WORD_CLASS = r"[^\x20\x09-\x0D]+"
GAP_CLASS = r"[\x20\x09-\x0D]+"
GAP_CHARS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The folder that the cluster shares; a folder of our own only where none is set and the session is local, as in tests."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.conf.get("spark.master", "local").startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    try:
        return spark.conf.get("spark.incwalk.scratch")
    except Exception:  # not set yet
        root = tempfile.mkdtemp(prefix="incwalk-scratch-")
        spark.conf.set("spark.incwalk.scratch", root)
        return root


#: Where saved tables lie; a table that is no longer referred to is forgotten, not deleted.
_PATHS: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def save(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Writes ``df`` once into the shared folder and reads it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/incwalk/{name}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _PATHS[out] = path
    return out


def discard(*tables: DataFrame | None) -> None:
    """Deletes saved tables that nothing reads any more: those of earlier rounds of a loop."""
    for df in tables:
        if df is not None and (path := _PATHS.pop(df, None)):
            spark = df.sparkSession
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def plan_bytes(df: DataFrame) -> int:
    """Catalyst's size estimate of ``df``; for file scans, the bytes of the files."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def part_count(df: DataFrame, bytes_each: int = 16 << 20, most: int = 1 << 16) -> int:
    """How many key ranges to deal out: one for each shuffle partition, more for a larger input.

    A document's entries cost an id in each range that has one of them, so ranges are few and large.
    """
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    size = plan_bytes(df)
    return max(32, min(most, max(n, size // bytes_each if size < 1 << 60 else 0)))


#: Longer pieces aren't remembered, so the entries of a memo bound its bytes.
LONGEST = 64
_MEMOS: list[dict] = []


def memo() -> dict:
    """A table that a worker keeps between tasks, until an operator that needs the memory calls ``forget``. Keys have up to ``LONGEST`` characters."""
    _MEMOS.append({})
    return _MEMOS[-1]


def forget() -> None:
    if any(_MEMOS):
        for m in _MEMOS:
            m.clear()
        gc.collect()


def release() -> None:
    """Gives what a task has freed back to the system; workers stay, and would hold it beside the next operator's memory."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def tidy(run):
    """A function over batches that releases its memory when the task ends."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped


def planes(a: np.ndarray, keep: int | None = None) -> bytes:
    """An array byte plane by byte plane: equal high bytes then lie together and compress."""
    a = np.ascontiguousarray(a)
    return a.view(np.uint8).reshape(len(a), a.itemsize).T[:keep].tobytes()


def unplanes(b: bytes, dtype, kept: int | None = None) -> np.ndarray:
    dtype = np.dtype(dtype)
    k = kept or dtype.itemsize
    n = len(b) // k
    out = np.zeros((n, dtype.itemsize), np.uint8)
    out[:, :k] = np.frombuffer(b, np.uint8).reshape(k, n).T
    return out.view(dtype).ravel()
