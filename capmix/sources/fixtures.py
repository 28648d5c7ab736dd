"""Pools built from the given tables: planted vectors (P), hashed text (H), web pages (W)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as tx
from ..functions import vectors as vx
from .tables import load

# Fixed values of the planted pool: noise weights by quality, of generated and of evaluation captions.
RAW_WEIGHT = {1: 3.5, 0: 6.0, None: 4.7}
GEN_WEIGHT, EVAL_WEIGHT = 3.85, 2.5
#: The specialised captioner: noisier captions, their noise drawn from another sequence.
TUNED_WEIGHT, TUNED_STEP, TUNED_SHIFT = 4.15, 13, 31


def centre_count(n_images: int) -> int:
    """Centres of the image gate: in proportion to the images, as the reference images are, so that the gate cuts alike
    at every size."""
    return max(16, 4 * n_images // 125)


def image_count(spark: SparkSession, sf_dir: str) -> int:
    return load(spark, sf_dir, "embeddings").count()


def images(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(image_id, vec array<double>, label) of all stored vectors."""
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("image_id"), F.col("embedding").cast("array<double>").alias("vec"), "label")


def pool_images(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = image_count(spark, sf_dir)
    return images(spark, sf_dir).filter(F.col("image_id") >= n // 5)


def reference_images(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = image_count(spark, sf_dir)
    return images(spark, sf_dir).filter((F.col("image_id") < n // 10) & (F.col("label") < 5))


def planted_pairs(spark: SparkSession, sf_dir: str, gen_step: int = 11, gen_shift: int = 29) -> DataFrame:
    """The pool without vectors: pair_id, image_id, noise vector ids, raw weight, labels, lang, source."""
    n = image_count(spark, sf_dir)
    first = n // 5
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang", "source")
    labels = load(spark, sf_dir, "labels")
    weight = F.when(F.col("quality") == 1, RAW_WEIGHT[1]).when(F.col("quality") == 0, RAW_WEIGHT[0]).otherwise(RAW_WEIGHT[None])
    return docs.join(labels, "doc_id", "left").select(
        F.col("doc_id").alias("pair_id"),
        (F.lit(first) + F.pmod("doc_id", F.lit(n - first))).cast("bigint").alias("image_id"),
        F.pmod(7 * F.col("doc_id") + 13, F.lit(n)).cast("bigint").alias("raw_noise"),
        F.pmod(gen_step * F.col("doc_id") + gen_shift, F.lit(n)).cast("bigint").alias("gen_noise"),
        weight.alias("raw_weight"), "quality", "toxic", "lang", "source",
    )


def planted_pool(spark: SparkSession, sf_dir: str, gen_weight: float = GEN_WEIGHT, gen_step: int = 11, gen_shift: int = 29) -> DataFrame:
    """P with its vectors: image_vec, raw_vec, gen_vec beside the columns of planted_pairs.

    Another weight, step and shift of the generated captions' noise plant another captioner.
    """
    pairs, vecs = planted_pairs(spark, sf_dir, gen_step, gen_shift), images(spark, sf_dir).select("image_id", "vec")

    def with_vec(df: DataFrame, key: str, name: str) -> DataFrame:
        return df.join(vecs.select(F.col("image_id").alias(key), F.col("vec").alias(name)), key)

    joined = with_vec(with_vec(with_vec(pairs, "image_id", "image_vec"), "raw_noise", "_r"), "gen_noise", "_g")
    return joined.withColumn("raw_vec", vx.add_scaled("image_vec", "_r", F.col("raw_weight"))).withColumn("gen_vec", vx.add_scaled("image_vec", "_g", gen_weight)).drop("_r", "_g")


def captioned(spark: SparkSession, sf_dir: str, low: int, high: int | None, weight: float, step: int = 11, shift: int = 29) -> DataFrame:
    """(item_id, image_vec, text_vec, label) of the images low..high with evaluation-like captions."""
    n = image_count(spark, sf_dir)
    vecs = images(spark, sf_dir)
    rows = vecs.filter((F.col("image_id") >= low) & ((F.col("image_id") < high) if high is not None else F.lit(True)))
    items = rows.select(F.col("image_id").alias("item_id"), F.col("vec").alias("image_vec"), "label", F.pmod(step * F.col("image_id") + shift, F.lit(n)).cast("bigint").alias("noise"))
    noise = vecs.select(F.col("image_id").alias("noise"), F.col("vec").alias("_n"))
    return items.join(noise, "noise").select("item_id", "image_vec", vx.add_scaled("image_vec", "_n", weight).alias("text_vec"), "label")


def evaluation_set(spark: SparkSession, sf_dir: str, weight: float = EVAL_WEIGHT, step: int = 11, shift: int = 29) -> DataFrame:
    """(item_id, image_vec, text_vec) of the evaluation slice."""
    n = image_count(spark, sf_dir)
    return captioned(spark, sf_dir, n // 10, n // 5, weight, step, shift).drop("label")


def page_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W: title as raw caption, paragraph text as content, url host as source, first path part as lang."""
    html = F.col("html")
    for tag in ("script", "style", "nav"):
        html = F.regexp_replace(html, rf"(?is)<{tag}[^>]*>.*?</{tag}>", " ")
    paragraphs = F.regexp_extract_all(html, F.lit(r"(?is)<p[^>]*>(.*?)</p>"), F.lit(1))
    return load(spark, sf_dir, "pages").select(
        F.col("page_id").alias("pair_id"),
        tx.decode_entities(F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1)).alias("raw_text"),
        F.trim(F.regexp_replace(F.array_join(paragraphs, " "), r"<[^>]*>", "")).alias("content"),
        F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("source"),
        F.regexp_extract("url", r"^[a-z]+://[^/]+/([^/]+)", 1).alias("lang"),
    )


def salted(key: Column | str, salt: str) -> Column:
    """A stable 32-bit number of a key: the same in every run, engine and partitioning."""
    return F.conv(F.substring(F.md5(F.concat((F.col(key) if isinstance(key, str) else key).cast("string"), F.lit(f":{salt}"))), 1, 8), 16, 10).cast("bigint")
