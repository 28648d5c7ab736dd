"""Encoders behind one interface: stored vectors, hashed text, and a hook for a real model.

encode(df) gives (key, vec array<double>); keys repeat as the input repeats them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as tx


class StoredEncoder:
    """Vectors kept in a table of (key, vec): a join."""

    def __init__(self, table: DataFrame, key: str, vec: str):
        self.table = table.select(F.col(key).alias("key"), F.col(vec).cast("array<double>").alias("vec"))

    def encode(self, df: DataFrame, key: str) -> DataFrame:
        return df.select(F.col(key).alias("key")).join(self.table, "key")


class HashedEncoder:
    """Hashed token counts, of unit length unless `normalise` is off; a text without tokens has the zero vector."""

    def __init__(self, width: int = 64, normalise: bool = True):
        self.width, self.normalise = width, normalise

    def encode(self, df: DataFrame, key: str, text: str) -> DataFrame:
        """In DataFrame terms: one row a text, nothing is shuffled."""
        buckets = F.transform(tx.tokens(text), lambda t: tx.bucket(t, self.width))
        counted = F.transform(F.array(buckets), lambda b: F.transform(F.sequence(F.lit(0), F.lit(self.width - 1)), lambda k: F.size(F.filter(b, lambda x: x == k)).cast("double")))[0]
        if self.normalise:
            length = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x))
            return df.select(F.col(key).alias("key"), counted.alias("vec")).withColumn("_n", length).select("key", F.when(F.col("_n") > 0, F.transform("vec", lambda x: x / F.col("_n"))).otherwise(F.col("vec")).alias("vec"))
        return df.select(F.col(key).alias("key"), counted.alias("vec"))

    def encode_arrow(self, df: DataFrame, key: str, text: str, *carry: str) -> DataFrame:
        """The same over Arrow batches, for long texts; `carry` names columns that are kept, so that nothing is joined again."""
        from .captioners import _TOKEN, WIDTH, hashed_vector

        if self.width != WIDTH:
            raise ValueError(f"the Arrow form has {WIDTH} dimensions")
        unit = self.normalise

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                vecs = np.zeros((batch.num_rows, WIDTH))
                for k, t in enumerate(batch.column(1).to_pylist()):
                    v = hashed_vector(_TOKEN.findall((t or "").lower()))
                    vecs[k] = v / n if unit and (n := np.sqrt(v @ v)) > 0 else v
                flat = pa.ListArray.from_arrays(np.arange(0, vecs.size + 1, WIDTH, dtype=np.int32), vecs.ravel())
                yield pa.RecordBatch.from_arrays([batch.column(0), *batch.columns[2:], flat], ["key", *carry, "vec"])

        rows = df.select(F.col(key).cast("bigint").alias("key"), text, *carry)
        kept = "".join(f"{c} {rows.schema[c].dataType.simpleString()}, " for c in carry)
        return rows.mapInArrow(work, f"key bigint, {kept}vec array<double>")


class ExternalEncoder:
    """A real model: `load` is called once a task and maps a list of inputs to vectors."""

    def __init__(self, load: Callable[[], Callable[[list], list]]):
        self.load = load

    def encode(self, df: DataFrame, key: str, value: str) -> DataFrame:
        load = self.load

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            model = load()
            for batch in batches:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model(batch.column(1).to_pylist()), pa.list_(pa.float64()))], ["key", "vec"])

        return df.select(F.col(key).cast("bigint").alias("key"), value).mapInArrow(work, "key bigint, vec array<double>")
