"""Bounded samples of labelled rows, and the hold-out rule of the classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def remainder(id_col: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo `modulus`; a null id counts as the empty text."""
    return (F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % modulus).cast("int")


def training_rows(docs: DataFrame, labels: DataFrame, label: str, modulus: int, held_out: int, sample_rows: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(text binary, label int): at most `sample_rows` labelled rows outside the hold-out, by hash order.

    Null labels and ids are left out; of several labels of one id the greatest counts. The ids are
    broadcast: they are at most sample_rows numbers.
    """
    known = labels.select(F.col(id_col).cast("bigint").alias("_id"), F.col(label).cast("int").alias("label")).dropna()
    known = known.filter(remainder("_id", modulus) != held_out).groupBy("_id").agg(F.max("label").alias("label"))
    drawn = known.orderBy(F.xxhash64("_id"), "_id").limit(sample_rows)
    return docs.select(F.col(id_col).cast("bigint").alias("_id"), F.col(text_col).cast("binary").alias("text")).join(F.broadcast(drawn), "_id").select("text", "label")
