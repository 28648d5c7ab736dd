"""Richness and diversity of caption sets: words, grounding, n-grams, nouns, coverage."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import text as tx


def long_captions(pool: DataFrame) -> DataFrame:
    """(pair_id, origin, words): one row for each caption of a hashed pool."""
    return pool.select("pair_id", F.explode(F.array(F.struct(F.lit("raw").alias("origin"), F.col("raw_text").alias("words")), F.struct(F.lit("gen").alias("origin"), F.col("gen_text").alias("words")))).alias("c")).select("pair_id", "c.origin", "c.words").filter(F.col("words").isNotNull())


def words_histogram(captions: DataFrame) -> DataFrame:
    return captions.groupBy("origin", F.size("words").cast("bigint").alias("n_words")).agg(F.count("*").alias("n_rows"))


def lexicon(corpus: DataFrame, min_letters: int = 4, stop_words: tuple[str, ...] = (), text_col: str = "text") -> DataFrame:
    """(token): distinct tokens of the reference caption corpus."""
    return corpus.select(F.explode(tx.tokens(text_col)).alias("token")).filter((F.length("token") >= min_letters) & ~F.col("token").isin(*stop_words) if stop_words else F.length("token") >= min_letters).distinct()


def grounding(captions: DataFrame, lexicon_: DataFrame, max_tokens: int = 5_000_000) -> DataFrame:
    """(pair_id, origin, ratio): visual tokens over tokens of each caption; null without tokens.

    The lexicon is broadcast if it has at most max_tokens tokens, else it is shuffled.
    """
    n = lexicon_.limit(max_tokens + 1).count()
    marked = lexicon_.select("token", F.lit(1).alias("visual"))
    exploded = captions.select("pair_id", "origin", F.explode_outer("words").alias("token"))
    joined = exploded.join(F.broadcast(marked) if n <= max_tokens else marked, "token", "left")
    return joined.groupBy("pair_id", "origin").agg((F.count("visual") / F.nullif(F.count("token"), F.lit(0))).alias("ratio"))


def grams(captions: DataFrame, n: int = 3, *carry: str) -> DataFrame:
    """(origin, gram, ...): a row for every n-gram occurrence."""
    return captions.select("origin", *carry, F.explode(tx.ngrams("words", n)).alias("gram"))


def unique_grams(captions: DataFrame, n: int = 3) -> DataFrame:
    """(origin, n_grams, n_unique): exact, on the grams' strings."""
    return grams(captions, n).groupBy("origin").agg(F.count("*").alias("n_grams"), F.count_distinct("gram").alias("n_unique"))


def unique_grams_hashed(captions: DataFrame, n: int = 3) -> DataFrame:
    """The same by 64-bit hashes: a shuffle of 8 bytes for each gram that a task hasn't seen."""
    seen = grams(captions, n).select("origin", F.xxhash64("gram").alias("h")).groupBy("origin", "h").agg(F.count("*").alias("n"))
    return seen.groupBy("origin").agg(F.sum("n").alias("n_grams"), F.count("*").alias("n_unique"))


def unique_grams_sketch(captions: DataFrame, n: int = 3, lg: int = 14) -> DataFrame:
    """(origin, n_unique) estimated by mergeable HLL sketches."""
    return grams(captions, n).groupBy("origin").agg(F.hll_sketch_estimate(F.hll_sketch_agg("gram", F.lit(lg))).alias("n_unique"))


def unique_nouns(captions: DataFrame, nouns: DataFrame) -> DataFrame:
    """Distinct tokens of each origin that the noun lexicon lists."""
    found = captions.select("origin", F.explode("words").alias("token")).distinct()
    return found.join(nouns, "token", "left_semi").groupBy("origin").agg(F.count("*").alias("n_nouns"))


def subset_level(key: str = "pair_id", levels: int = 4, salt: str = "subset"):
    """The smallest of the nested random subsets that a row belongs to; subset k holds a 2**(k - levels) share."""
    from ..sources.fixtures import salted

    level = F.lit(levels)
    for k in reversed(range(levels)):
        level = F.when(salted(key, salt) < (1 << 32) >> (levels - k), F.lit(k)).otherwise(level)
    return level


def _curve(placed: DataFrame, seen: DataFrame) -> DataFrame:
    """(origin, level, n_captions, n_unique) from captions with a level and (origin, term, level): each term counts from
    the smallest subset in which it occurs."""
    firsts = seen.groupBy("origin", "term").agg(F.min("level").alias("level")).groupBy("origin", "level").agg(F.count("*").alias("fresh"))
    sizes = placed.groupBy("origin", "level").agg(F.count("*").alias("own"))
    w = Window.partitionBy("origin").orderBy("level").rowsBetween(Window.unboundedPreceding, 0)
    return sizes.join(firsts, ["origin", "level"], "left").select("origin", F.col("level").cast("bigint").alias("level"), F.sum("own").over(w).alias("n_captions"), F.sum(F.coalesce("fresh", F.lit(0))).over(w).alias("n_unique"))


def diversity_curve(captions: DataFrame, levels: int = 4, salt: str = "subset", n: int = 3) -> DataFrame:
    """(origin, level, n_captions, n_unique): distinct grams of nested random subsets, in one pass."""
    placed = captions.withColumn("level", subset_level("pair_id", levels, salt))
    return _curve(placed, grams(placed, n, "level").withColumnRenamed("gram", "term"))


def noun_curve(captions: DataFrame, nouns: DataFrame, levels: int = 4, salt: str = "subset") -> DataFrame:
    """The same with the distinct tokens that the noun lexicon lists."""
    placed = captions.withColumn("level", subset_level("pair_id", levels, salt))
    tokens = placed.select("origin", "level", F.explode("words").alias("token")).groupBy("origin", "token").agg(F.min("level").alias("level"))
    return _curve(placed, tokens.join(nouns, "token", "left_semi").withColumnRenamed("token", "term"))


def diversity_slope(curve: DataFrame) -> DataFrame:
    """(origin, slope): growth exponent of distinct grams over captions, on log-log axes."""
    return curve.filter("n_unique > 0").groupBy("origin").agg(F.regr_slope(F.log("n_unique"), F.log("n_captions")).alias("slope"))


def masked_unique_grams(captions: DataFrame, names: list[str], n: int = 3) -> DataFrame:
    """(recipe, n_unique) of many recipes from one gram shuffle: captions carry a `mask` of recipes."""
    by_gram = grams(captions, n, "mask").groupBy("gram").agg(F.bit_or("mask").alias("mask"))
    wide = by_gram.agg(*[F.count_if(F.col("mask").bitwiseAND(F.lit(1 << k).cast("bigint")) != 0).alias(r) for k, r in enumerate(names)])
    return wide.unpivot([], names, "recipe", "n_unique")


def coverage(captions: DataFrame, lexicon_: DataFrame) -> DataFrame:
    """(origin, n_terms, share): lexicon terms still present."""
    total = lexicon_.agg(F.count("*").alias("total"))
    found = captions.select("origin", F.explode("words").alias("token")).distinct().join(lexicon_, "token", "left_semi").groupBy("origin").agg(F.count("*").alias("n_terms"))
    return found.crossJoin(total).select("origin", "n_terms", (F.col("n_terms") / F.col("total")).alias("share"))


def cluster_entropy(assigned: DataFrame) -> DataFrame:
    """(n_clusters, entropy in nats) of the cluster histogram."""
    sizes = assigned.groupBy("cid").agg(F.count("*").alias("n"))
    total = sizes.agg(F.sum("n").alias("total"))
    p = F.col("n") / F.col("total")
    return sizes.crossJoin(total).agg(F.count("*").alias("n_clusters"), (-F.sum(p * F.log(p))).alias("entropy"))


def retention(pool: DataFrame, kept: DataFrame, group: str) -> DataFrame:
    """(group, n_rows, n_kept, rate, disparity): kept share of each group, and over the largest share."""
    flagged = pool.join(kept.select("pair_id", F.lit(1).alias("k")), "pair_id", "left")
    rates = flagged.groupBy(F.col(group).alias("grp")).agg(F.count("*").alias("n_rows"), F.count("k").alias("n_kept")).withColumn("rate", F.col("n_kept") / F.col("n_rows"))
    best = rates.agg(F.max("rate").alias("best"))
    return rates.crossJoin(best).select("grp", "n_rows", "n_kept", "rate", (F.col("rate") / F.col("best")).alias("disparity"))
