"""Streams of arriving pairs: admission against frozen cuts, windows, sessions, dedup, joins, live cuts."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.rank import Cut
from ..storage import remove, shared_path

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 4) -> DataFrame:
    """A file stream of events with the watermark column as a timestamp (the session's zone should be UTC).

    `path` is a folder of Parquet files, or a pattern of them.
    """
    rows = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def admitted(stream: DataFrame, sheet: DataFrame, cut: Cut, n_pairs: int) -> DataFrame:
    """Arriving pairs that clear a frozen cut on their raw or generated score: (event_id, ts, pair_id, origin).

    The pair of an event is event_id mod n_pairs; the static score sheet is joined.
    """
    pair = F.pmod("event_id", F.lit(n_pairs)).cast("bigint")
    joined = stream.withColumn("pair_id", pair).join(sheet.select("pair_id", "raw_sim", "gen_sim"), "pair_id")
    origin = F.when(cut.covers_rank(F.col("raw_sim"), F.col("pair_id")), "raw").when(cut.covers_value(F.col("gen_sim")), "gen")
    return joined.withColumn("origin", origin).filter("origin IS NOT NULL").select("event_id", "ts", "pair_id", "origin")


def tumbling(stream: DataFrame, size: str = "1 day", late: str = "2 hours") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(stream: DataFrame, size: str = "1 day", step: str = "6 hours", late: str = "2 hours") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(stream: DataFrame, late: str = "2 hours") -> DataFrame:
    """Each event id once within the watermark's reach."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def interval_join(stream: DataFrame, first: str, then: str, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pairs of events of one user: `first`, followed by `then` within an interval."""
    a = stream.filter(F.col("event_type") == first).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", late)
    b = stream.filter(F.col("event_type") == then).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", late)
    return a.join(b, F.expr(f"a_user = b_user AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {within}")).select("a_id", "b_id", F.col("a_user").alias("user_id"))


def live_histogram(stream: DataFrame, sheet: DataFrame, n_pairs: int, bins: int = 64) -> DataFrame:
    """Running counts of raw scores by bin, kept as state: (bin, n) after every batch. The live form of the cut."""
    pair = F.pmod("event_id", F.lit(n_pairs)).cast("bigint")
    number = F.least(F.floor((F.col("raw_sim") + 1) * (bins / 2)), F.lit(bins - 1)).cast("bigint")
    scored = stream.withColumn("pair_id", pair).join(sheet.select("pair_id", "raw_sim"), "pair_id").select(number.alias("bin"), F.lit(1).alias("one"))

    def count(key: tuple, pdfs: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(p) for p in pdfs)
        state.update((n,))
        yield pd.DataFrame({"bin": [key[0]], "n": [n]})

    return scored.groupBy("bin").applyInPandasWithState(count, "bin bigint, n bigint", "n bigint", "update", "NoTimeout")


def cut_from_histogram(counts: dict[int, int], x: float, bins: int = 64) -> float:
    """The lower edge of the bin that holds the x-percent cut."""
    import math

    need = math.ceil(x * sum(counts.values()) / 100)
    for b in sorted(counts, reverse=True):
        need -= counts[b]
        if need <= 0:
            return b * 2 / bins - 1
    return -1.0


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that there is now and give what it wrote (in 'update' mode: all versions).

    Executors write each batch to the shared folder, so that the driver holds no rows; a repeated batch overwrites itself. In
    'complete' mode every batch is the whole result, and the last one is kept.
    """
    spark = stream.sparkSession
    at, to = shared_path(spark, f"stream-{name}"), shared_path(spark, f"stream-{name}-rows")
    written: list[str] = []

    def write(batch: DataFrame, batch_id: int) -> None:
        path = f"{to}/batch={batch_id}"
        batch.write.mode("overwrite").parquet(path)
        if mode == "complete":
            for old in set(written) - {path}:
                remove(spark, old)
            written.clear()
        if path not in written:
            written.append(path)

    query = stream.writeStream.foreachBatch(write).queryName(f"{name}_{uuid.uuid4().hex}").outputMode(mode).option("checkpointLocation", at).trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception():
        raise RuntimeError(str(query.exception()))
    return spark.read.schema(stream.schema).parquet(*written) if written else spark.createDataFrame([], stream.schema)


def shard_sink(stream: DataFrame, path: str, checkpoint: str, transform: Callable[[DataFrame], DataFrame] = lambda d: d) -> None:
    """Write each micro-batch to a folder named by its id: a repeated batch overwrites itself, so rows land once."""

    def write(batch: DataFrame, batch_id: int) -> None:
        transform(batch).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
