"""The folder that driver and executors share, and tables kept in it to cut lineage."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
#: Paths made inside each open `scratch`.
_MADE: list[list[str]] = []


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; only where that is unset, on a single machine, a temporary folder."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if "dir" not in _OWN:
        _OWN["dir"] = tempfile.mkdtemp(prefix="capmix_")
        atexit.register(shutil.rmtree, _OWN["dir"], True)
    return f"file://{_OWN['dir']}"


def shared_path(spark: SparkSession, name: str, kept: bool = False) -> str:
    """A fresh path below the shared folder; removed with the `scratch` that it is made in, unless kept, and at the latest
    when the application ends."""
    path = f"{shared_folder(spark).rstrip('/')}/capmix/{name}-{uuid.uuid4().hex}"
    if _MADE and not kept:
        _MADE[-1].append(path)
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    return path


@contextmanager
def scratch(spark: SparkSession, *paths: str | None):
    """What is materialised inside, and `paths`, is removed at the end. Nothing that reads it may be left undone."""
    _MADE.append([p for p in paths if p])
    try:
        yield
    finally:
        for path in _MADE.pop():
            remove(spark, path)


def materialise(df: DataFrame, name: str, kept: bool = False):
    """Cut the lineage: write df as Parquet to the shared folder and read it back; of what is kept, the path too."""
    path = shared_path(df.sparkSession, name, kept)
    schema = df.schema
    df.write.parquet(path)
    found = df.sparkSession.read.schema(schema).parquet(path)
    return (found, path) if kept else found


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path below the shared folder before the application ends."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def few(df: DataFrame, rows: int) -> bool:
    """Has df at most so many rows? Asked before a side is broadcast."""
    return df.limit(rows + 1).count() <= rows


def release() -> None:
    """Give a worker's freed memory back to the system, where the C library can: workers live on from task to task."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        return
