"""Joins and windows that Spark has no single operator for: as-of, range and interval joins, lateral top-1."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, time: str, by: str, value: str, slices: str | None = None) -> DataFrame:
    """left with the latest `value` of right at or before each row's time, within `by`.

    Both sides are united and carried forward by one window: one shuffle, no join. At equal times the
    right side's row counts first.
    """
    lefts = left.select(F.col(by), F.col(time), F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    rights = right.select(F.col(by), F.col(time), F.lit(None).cast(lefts.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(by).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return lefts.union(rights).withColumn("_v", F.last("_v", ignorenulls=True).over(w)).filter("_side = 1").select("_row.*", F.col("_v").alias(value))


def range_join(points: DataFrame, ranges: DataFrame, x: str, low: str, high: str, width: float) -> DataFrame:
    """Points within [low, high): both sides are cut to cells of `width` and joined by equal cells.

    A range goes to every cell that it touches, a point to its own, so each match is found once.
    """
    cells = ranges.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    placed = points.withColumn("_cell", F.floor(F.col(x) / width))
    return placed.join(cells, "_cell").filter((F.col(x) >= F.col(low)) & (F.col(x) < F.col(high))).drop("_cell")


def interval_join(a: DataFrame, b: DataFrame, by: str, a_time: str, b_time: str, seconds: int) -> DataFrame:
    """Pairs with equal `by` and 0 <= b_time - a_time <= seconds, by cells of that length."""
    cell = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds)
    left = a.withColumn("_cell", F.explode(F.array(cell(a_time), cell(a_time) + 1)))
    right = b.withColumn("_cell", cell(b_time))
    gap = F.unix_micros(F.col(b_time).cast("timestamp")) - F.unix_micros(F.col(a_time).cast("timestamp"))
    return left.join(right, [by, "_cell"]).filter((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_cell")


def top_per_group(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    """The first k rows of each group; tasks keep k rows of a group before the shuffle."""
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).filter(F.col("_r") <= k).drop("_r")


def salted_sum(df: DataFrame, key: str, value: str, salts: int = 16) -> DataFrame:
    """A two-step sum that spreads a hot key over `salts` tasks before its parts meet."""
    parts = df.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts))).groupBy(key, "_salt").agg(F.sum(value).alias("_v"))
    return parts.groupBy(key).agg(F.sum("_v").alias(value))
