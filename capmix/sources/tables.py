"""Readers of the given tables with declared schemas, and writers of training sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Declared schemas: nothing is inferred, and only asked-for columns are read.
SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "labels": "doc_id bigint, quality int, toxic int",
    "benchmark": "item_id bigint, text string",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A given table; those of SCHEMAS with their declared types."""
    found = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    if table in SCHEMAS:
        wanted = {f.name: f.dataType for f in spark.createDataFrame([], SCHEMAS[table]).schema}
        return found.select(*[F.col(c).cast(t).alias(c) for c, t in wanted.items()])
    return found


def spread(df: DataFrame, key: str) -> DataFrame:
    """A table of fewer parts than cores, dealt to all of them by `key`; any larger one stays as it is, without a shuffle."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores, key) if df.rdd.getNumPartitions() < cores else df


def write_shards(df: DataFrame, path: str, shards: int, key: str = "pair_id", partition_by: str | None = None, max_records: int = 1_000_000) -> DataFrame:
    """Write df as Parquet shards by the hash of `key`, and a manifest; gives the manifest.

    The shard of a row follows from its key alone, so a repeated task writes the same rows. Files hold
    max_records rows at most.
    """
    spark = df.sparkSession
    placed = df.withColumn("shard", F.pmod(F.xxhash64(key), F.lit(shards)).cast("int"))
    writer = placed.repartition(shards, "shard").sortWithinPartitions("shard", key).write.mode("overwrite").option("maxRecordsPerFile", max_records)
    writer.partitionBy(*([partition_by] if partition_by else []), "shard").parquet(f"{path}/data")
    manifest = spark.read.parquet(f"{path}/data").groupBy("shard").agg(F.count("*").alias("n_rows"), F.min(key).alias("first_key"), F.max(key).alias("last_key"))
    manifest.coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")
    return spark.read.parquet(f"{path}/manifest")


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "pair_id") -> None:
    """A bucketed and sorted table: later joins on `key` need no shuffle of it."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
