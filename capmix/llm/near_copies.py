"""The pipeline's near-dedup: components over pairs of five-word Jaccard similarity 0.8 and more.

SimHash comes first: the fingerprints of the texts' five-word shingles are linked by the tiles of `simhash.links` within
`radius` bits, and an exact Jaccard check decides each link. No radius that tiles can afford reaches all pairs at
0.8 (ten of 64 bits miss 2 % of them), so MinHash bands name the candidates beyond it, checked in the same way; a pair at
0.8 is then missed with probability 0.0002.

Defined cases: null and wordless texts are one class; equal sets are one class, whatever their number; fewer words than
a shingle has are one shingle; null ids keep their rows and never become a component's id unless all its ids are null;
rows with one id and different texts are told apart by `row_key`, the hash of the text; repeated rows all stay here;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import near_copies
from . import simhash
from .common import few, materialise
from .components import components

RADIUS = 3


def close_fingerprints(rows: DataFrame, radius: int) -> DataFrame:
    """(cls, band): classes of one fingerprint, and of fingerprints that the tiles link, share a value."""
    least = materialise(rows.filter("size > 0").groupBy(F.col("mark").alias("fp")).agg(F.min("cls").alias("cls")), "fingerprints")
    same = rows.filter("size > 0").select("cls", F.col("mark").alias("band")).distinct()
    ends = simhash.links(least.select("fp"), radius).distinct().withColumn("band", F.xxhash64("a", "b"))
    linked = ends.select(F.col("a").alias("fp"), "band").union(ends.select("b", "band")).join(least, "fp")
    return same.select("cls", F.xxhash64(F.lit("one"), "band").alias("band")).union(linked.select("cls", "band"))


def near_duplicates(df: DataFrame, shingle: int = 5, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text", block_rows: int = near_copies.BLOCK_ROWS, radius: int = RADIUS) -> DataFrame:
    """(id, row_key, component_id, component_key) of every row: the first row, by id and text key, reachable over pairs."""
    rows = materialise(near_copies.sketches(df, id_col, text_col, shingle, mark=simhash.majority), "sketches")
    links = near_copies.pairs(df, rows, materialise, text_col, shingle, threshold, True, block_rows, also=close_fingerprints(rows, radius))
    roots = materialise(components(links), "roots")
    first = F.min(F.struct(F.col("id").isNull().alias("none"), F.col("id").alias("id"), F.col("row_key").alias("row_key")))
    least = rows.groupBy("cls").agg(first.alias("least"))
    linked = least.join(roots.withColumnRenamed("node", "cls"), "cls", "left").withColumn("root", F.coalesce("root", "cls"))
    merged = linked.groupBy("root").agg(F.min("least").alias("c"))
    classes = linked.select("cls", "root").join(merged, "root").select("cls", F.col("c.id").alias("component_id"), F.col("c.row_key").alias("component_key"))
    return rows.select("id", "row_key", "cls").join(classes, "cls").select("id", "row_key", "component_id", "component_key")


def one_of_each(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = 500_000, **options) -> DataFrame:
    """df without near copies: of each component its first row stays, once.

    Of rows with one id and one text that one stays whose columns sort first. Texts are shuffled only if more than `most`
    rows go; else those are broadcast (three numbers each).
    """
    found = materialise(near_duplicates(df, id_col=id_col, text_col=text_col, **options), "near")
    stays = F.col("id").eqNullSafe(F.col("component_id")) & (F.col("row_key") == F.col("component_key"))
    # what goes, and of what stays the rows that are there several times
    marked = found.groupBy("id", "row_key").agg(F.bool_or(stays).alias("stays"), F.count("*").alias("n")).filter("NOT stays OR n > 1")
    marked = materialise(marked.select("id", "row_key", "stays"), "marked")
    marked = F.broadcast(marked) if few(marked, most) else marked
    rows = df.select(F.struct(*df.columns).alias("row"), F.col(id_col).cast("bigint").alias("own"), F.xxhash64(text_col).alias("own_key"))
    both = rows.join(marked, F.col("own").eqNullSafe(F.col("id")) & (F.col("own_key") == F.col("row_key")), "left").filter("stays IS NULL OR stays").select("row", "own", "own_key", "stays")
    several = both.filter("stays").groupBy("own", "own_key").agg(F.min("row").alias("row"))
    return both.filter("stays IS NULL").select("row").union(several.select("row")).select("row.*")
