"""Helpers shared by the operators of this subpackage: the shared folder, partition numbers, small batches."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..storage import few, materialise, release, remove, scratch, shared_folder, shared_path

__all__ = ["few", "materialise", "release", "remove", "scratch", "shared_folder", "shared_path", "small", "width"]


def width(spark: SparkSession, rows: int = 0, rows_per_task: int = 50_000) -> int:
    """How many partitions to deal to: the session's number, and more as the rows ask for it."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), rows // rows_per_task + 1)


def small(batches, rows: int = 500):
    """Arrow batches in parts of few rows, so that few texts are Python objects at a time.

    Workers live on from task to task, so what the last task and batch left is given back to the system.
    """
    release()
    for batch in batches:
        for k in range(0, batch.num_rows, rows):
            yield batch.slice(k, rows)
        release()
