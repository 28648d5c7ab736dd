"""Pool preparation: safety, deduplication, evaluation overlap, nested subpools, clean-up."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as tx
from ..functions import vectors as vx
from ..sources.fixtures import salted
from ..storage import few
from . import near_copies


def drop_unsafe(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows that no label marks as toxic; unlabelled rows stay."""
    return docs.join(labels.filter("toxic = 1").select("doc_id"), "doc_id", "left_anti")


def dedup_exact(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Of equal texts the row of smallest id: only (id, md5) is aggregated, before it is shuffled."""
    keepers = docs.groupBy(F.md5(F.coalesce(text_col, F.lit("")).cast("binary")).alias("h")).agg(F.min(id_col).alias(id_col))
    return docs.join(keepers.select(id_col), id_col, "left_semi")


def _classes(docs: DataFrame, shingle: int, bands: int, rows: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The tokens as text, the sketches of documents with an id and a token, and (cls, rep) of their classes."""
    texts = docs.select("doc_id", F.array_join(tx.tokens("text"), " ").alias("text")).filter("doc_id IS NOT NULL")
    own = near_copies.sketches(texts, shingle=shingle, bands=bands, rows=rows).filter("size > 0").cache()
    return texts, own, own.groupBy("cls").agg(F.min("id").alias("rep"))


def near_duplicates(docs: DataFrame, shingle: int = 5, bands: int = 16, rows: int = 4, threshold: float = 0.8) -> DataFrame:
    """(a, b, jaccard): MinHash-banded pairs of documents whose shingle sets have similarity >= threshold.

    Documents of equal shingle sets are a class, its smallest id stands for it: all pairs between classes are
    given by these, and each other member with its own at 1. A text shorter than a shingle is one shingle.
    """
    texts, own, reps = _classes(docs, shingle, bands, rows)
    found = near_copies.pairs(texts, own, lambda df, _: df.cache(), shingle=shingle, threshold=threshold)
    named = found.join(reps.select(F.col("cls").alias("a"), F.col("rep").alias("x")), "a").join(reps.select(F.col("cls").alias("b"), F.col("rep").alias("y")), "b")
    copies = own.join(reps, "cls").filter("id <> rep").select("rep", "id", F.lit(1.0))
    return named.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "jaccard").union(copies)


def near_duplicate_members(docs: DataFrame, shingle: int = 5) -> DataFrame:
    """(doc_id, rep): the document that stands for each one in the pairs of near_duplicates."""
    _, own, reps = _classes(docs, shingle, near_copies.BANDS, near_copies.ROWS)
    return own.join(reps, "cls").select(F.col("id").alias("doc_id"), "rep")


def overlapping(docs: DataFrame, items: DataFrame, n: int = 13, most: int = 2_000_000) -> DataFrame:
    """(doc_id) of documents that share a token n-gram with an evaluation item.

    Grams are compared by 64-bit hashes, the items' broadcast if they are at most `most`; the few documents with a
    hit are then compared by the grams themselves.
    """
    grams = items.select(F.explode(tx.ngrams(tx.tokens("text"), n)).alias("gram")).distinct()
    hashes = grams.select(F.xxhash64("gram").alias("h")).distinct()
    hashes = F.broadcast(hashes) if few(hashes, most) else hashes
    # no filter on the number of tokens: it would cut the texts a second time, and short ones have no grams anyway
    held = docs.select("doc_id", F.explode(F.transform(tx.ngrams(tx.tokens("text"), n), lambda g: F.xxhash64(g))).alias("h"))
    likely = held.join(hashes, "h", "left_semi").select("doc_id").distinct()
    exact = docs.join(likely, "doc_id", "left_semi").select("doc_id", F.explode(tx.ngrams(tx.tokens("text"), n)).alias("gram"))
    return exact.join(grams, "gram", "left_semi").select("doc_id").distinct()


def decontaminate(docs: DataFrame, items: DataFrame, n: int = 13) -> DataFrame:
    return docs.join(overlapping(docs, items, n), "doc_id", "left_anti")


def near_evaluation_images(images: DataFrame, evaluation: DataFrame, threshold: float) -> DataFrame:
    """(image_id, best): pool images whose best cosine with an evaluation image reaches the threshold."""
    from .gate import assign

    centres = evaluation.select(F.col("image_id").cast("int").alias("cid"), F.col("vec").alias("centre"))
    near = assign(images, centres).join(images.select("image_id", "vec"), "image_id").join(centres, "cid")
    return near.select("image_id", vx.cosine("vec", "centre").alias("best")).filter(F.col("best") >= threshold)


def subpool(pool: DataFrame, share: float, salt: str = "pool", id_col: str = "pair_id") -> DataFrame:
    """A nested random subpool: the threshold on a salted number, so smaller shares lie within larger ones."""
    return pool.filter(salted(id_col, salt) < int(share * (1 << 32)))


def sample_exact(pool: DataFrame, n: int, salt: str = "sample", id_col: str = "pair_id") -> DataFrame:
    """Exactly n rows (all, if fewer), in salted order."""
    return pool.orderBy(salted(id_col, salt), id_col).limit(n)
