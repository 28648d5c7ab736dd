"""Alignment: cosine scores of captions against their images, and measures over them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as vx


def score_sheet(pool: DataFrame, method: str = "fold") -> DataFrame:
    """(pair_id, image_id, raw_sim, gen_sim): the narrow sheet that all recipes work on.

    A missing or zero vector gives null, never NaN (which Spark would sort as the largest number).
    """
    cos = vx.cosine if method == "fold" else vx.cosine_arrow
    return pool.select("pair_id", "image_id", cos(F.col("image_vec"), F.col("raw_vec")).alias("raw_sim"), cos(F.col("image_vec"), F.col("gen_vec")).alias("gen_sim"))


def clean_scores(sheet: DataFrame, *names: str) -> DataFrame:
    """NaN scores become null."""
    return sheet.withColumns({c: F.when(~F.isnan(c), F.col(c)) for c in names or ("raw_sim", "gen_sim")})


def long_scores(sheet: DataFrame) -> DataFrame:
    """(pair_id, origin, sim): one row for each caption."""
    return sheet.select("pair_id", F.expr("stack(2, 'raw', raw_sim, 'gen', gen_sim) AS (origin, sim)"))


def mean_similarity(long: DataFrame, *by: str) -> DataFrame:
    return long.groupBy(*(by or ("origin",))).agg(F.avg("sim").alias("mean_sim"), F.count("sim").alias("n_rows"))


def histogram(long: DataFrame, low: float = -1.0, high: float = 1.0, bins: int = 40) -> DataFrame:
    """Counts by origin and bin of equal width; bin 0 begins at `low`, the last bin takes its upper end."""
    width = (high - low) / bins
    number = F.least(F.floor((F.col("sim") - low) / width), F.lit(bins - 1)).cast("bigint")
    return long.filter(F.col("sim").isNotNull()).groupBy("origin", number.alias("bin")).agg(F.count("*").alias("n_rows"))


def quantiles(long: DataFrame, shares: tuple[float, ...] = (0.1, 0.25, 0.5, 0.75, 0.9)) -> DataFrame:
    """Exact interpolated quantiles by origin: (origin, share, value)."""
    got = long.groupBy("origin").agg(F.percentile("sim", F.array(*map(F.lit, shares))).alias("q"))
    return got.select("origin", F.explode(F.arrays_zip(F.array(*map(F.lit, shares)).alias("share"), F.col("q").alias("value"))).alias("z")).select("origin", F.col("z.share").alias("share"), F.col("z.value").alias("value"))


def reference_free(long: DataFrame, weight: float = 2.5) -> DataFrame:
    """Mean of weight * max(cosine, 0), clamped row by row before the mean."""
    return long.groupBy("origin").agg(F.avg(weight * F.greatest(F.col("sim"), F.lit(0.0))).alias("ref_free"))


def paired(sheet: DataFrame) -> DataFrame:
    """On the same images: share of rows where the generated caption is better, mean and sd of the difference."""
    d = F.col("gen_sim") - F.col("raw_sim")
    return sheet.agg(F.count(d).alias("n_rows"), F.sum(F.when(d > 0, 1).otherwise(0)).cast("bigint").alias("n_better"), F.avg(d).alias("mean_diff"), F.stddev_samp(d).alias("sd_diff"))
