"""Tables in the folder that the cluster shares, and readers of the given tables."""

from __future__ import annotations

import contextlib
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a folder of our own only where that is unset and the session is local, as in tests."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.conf.get("spark.master", "local").startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = spark.conf.get("spark.incwalk.graph.scratch", None)
    if not own:
        own = tempfile.mkdtemp(prefix="incwalk-graph-")
        spark.conf.set("spark.incwalk.graph.scratch", own)
    return own


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/incwalk-graph/{name}-{uuid.uuid4().hex}"


#: With it Spark deletes the shuffle files of a query when that ends, and not when the driver happens to collect its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def _shuffles_end(spark: SparkSession):
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, before)


def save(df: DataFrame, name: str, path: str | None = None, partition_by: list[str] | None = None) -> DataFrame:
    """Writes a table once and reads it back: cuts lineage between rounds and survives lost executors."""
    path = path or fresh_path(df.sparkSession, name)
    writer = df.write.partitionBy(*partition_by) if partition_by else df.write
    with _shuffles_end(df.sparkSession):
        writer.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    _PATHS[out] = path
    return out


#: Where saved tables lie; a table that is no longer referred to is forgotten, not deleted.
_PATHS: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def _file_system(spark: SparkSession, path: str):
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark._jsc.hadoopConfiguration()), place


def discard(*tables: DataFrame | None) -> None:
    """Deletes saved tables that nothing reads any more: those of earlier rounds of a loop."""
    for df in tables:
        if df is not None and (path := _PATHS.pop(df, None)):
            fs, place = _file_system(df.sparkSession, path)
            fs.delete(place, True)


def publish(spark: SparkSession, path: str, text: str) -> None:
    """Writes a small text whole or not at all: under another name, then renamed."""
    fs, place = _file_system(spark, path)
    _, draft = _file_system(spark, f"{path}.{uuid.uuid4().hex}.draft")
    out = fs.create(draft, True)
    out.write(bytearray(text.encode()))
    out.close()
    if fs.exists(place):
        fs.delete(place, False)
    if not fs.rename(draft, place):
        raise OSError(f"could not publish {path}")


def published(spark: SparkSession, folder: str, prefix: str) -> str | None:
    """The text of the last file of that prefix, by name; None where there is none."""
    fs, place = _file_system(spark, folder)
    names = sorted(s.getPath().getName() for s in fs.listStatus(place)) if fs.exists(place) else []
    names = [n for n in names if n.startswith(prefix) and not n.endswith(".draft")]
    return "\n".join(r["value"] for r in spark.read.text(f"{folder}/{names[-1]}").collect()) if names else None


def plan_bytes(df: DataFrame) -> int:
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
