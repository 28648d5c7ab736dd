"""Heuristic filters: rules over captions, image sizes and sources, composed and reported in one scan."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.fixtures import salted


@dataclass(frozen=True)
class Rule:
    """A named predicate over a row; null counts as failed."""

    name: str
    test: Callable[[], Column]

    def column(self) -> Column:
        return F.coalesce(self.test(), F.lit(False))

    def __and__(self, other: Rule) -> Rule:
        return Rule(f"({self.name} and {other.name})", lambda: self.column() & other.column())

    def __or__(self, other: Rule) -> Rule:
        return Rule(f"({self.name} or {other.name})", lambda: self.column() | other.column())

    def __invert__(self) -> Rule:
        return Rule(f"not {self.name}", lambda: ~self.column())


def length(low: int = 5, high: int = 40, max_chars: int = 400) -> Rule:
    return Rule("length", lambda: F.size("words").between(low, high) & (F.length(F.array_join("words", " ")) <= max_chars))


def noun(flag_col: str = "has_noun") -> Rule:
    return Rule("noun", lambda: F.col(flag_col))


def complexity(threshold: float = 5.5) -> Rule:
    """Distinct-token share, plus mean token length, plus a tenth for each token of seven letters and more."""

    def score() -> Column:
        n = F.size("words")
        letters = F.aggregate("words", F.lit(0), lambda acc, w: acc + F.length(w))
        long = F.size(F.filter("words", lambda w: F.length(w) >= 7))
        return F.when(n > 0, F.size(F.array_distinct("words")) / n + letters / n + long / 10.0)

    return Rule("complexity", lambda: score() >= threshold)


def with_sizes(df: DataFrame) -> DataFrame:
    """Synthetic width and height of each pair, from salted numbers (no pixels are given)."""
    return df.withColumns({"width": (64 + F.pmod(salted("pair_id", "width"), F.lit(961))).cast("int"), "height": (64 + F.pmod(salted("pair_id", "height"), F.lit(961))).cast("int")})


def aspect(limit: float = 3.0) -> Rule:
    return Rule("aspect", lambda: F.greatest("width", "height") / F.least("width", "height") <= limit)


def min_size(pixels: int = 200) -> Rule:
    return Rule("min_size", lambda: F.least("width", "height") >= pixels)


def source_rates(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(source, n_labelled, rate): share of quality 1 among the labelled rows of each source."""
    return docs.join(labels, "doc_id").groupBy("source").agg(F.count("quality").alias("n_labelled"), F.avg("quality").alias("rate"))


def reliable_sources(docs: DataFrame, labels: DataFrame, threshold: float = 0.85) -> DataFrame:
    rates = source_rates(docs, labels).filter(F.col("rate") >= threshold)
    return docs.join(rates, "source")


def mentions_objects(captions: DataFrame, assigned: DataFrame, concepts: int = 20) -> DataFrame:
    """(pair_id, kept): does a caption share a token with the commonest tokens of its image cluster?

    captions: (pair_id, image_id, words); assigned: (image_id, cid).
    """
    from pyspark.sql.window import Window

    placed = captions.join(assigned, "image_id")
    counts = placed.select("cid", F.explode(F.array_distinct("words")).alias("token")).filter(F.length("token") >= 4).groupBy("cid", "token").agg(F.count("*").alias("n"))
    top = counts.withColumn("r", F.row_number().over(Window.partitionBy("cid").orderBy(F.desc("n"), "token"))).filter(F.col("r") <= concepts)
    lists = top.groupBy("cid").agg(F.collect_list("token").alias("concepts"))
    return placed.join(lists, "cid", "left").select("pair_id", F.coalesce(F.arrays_overlap("words", "concepts"), F.lit(False)).alias("kept"))


def discard_rates(df: DataFrame, rules: list[Rule]) -> DataFrame:
    """(rule, n_rows, n_kept, discard_rate) of all rules in one scan."""
    wide = df.agg(F.count("*").alias("n"), *[F.count_if(r.column()).alias(f"k{i}") for i, r in enumerate(rules)])
    rows = F.explode(F.array(*[F.struct(F.lit(r.name).alias("rule"), F.col(f"k{i}").alias("n_kept")) for i, r in enumerate(rules)]))
    return wide.select("n", rows.alias("r")).select("r.rule", F.col("n").alias("n_rows"), "r.n_kept", (1 - F.col("r.n_kept") / F.col("n")).alias("discard_rate"))
