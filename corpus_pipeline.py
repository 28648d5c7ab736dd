"""The corpus pipeline: five stages over documents, each by one of the operators of capmix.llm.

Every stage takes (spark, docs, sf_dir) and gives a DataFrame, which is written as Parquet and read again
as the next stage's docs. All stages but the last return the columns of documents.

Defined cases, for every stage: a null or empty text stays unless a rule below takes it; very long texts are judged whole;
null ids and ids that several rows share are told apart by their texts, so no row is judged by another's; rows are
carried as one struct, so extra columns of any name pass unchanged; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from capmix.llm import decontamination, near_copies, packing, repeats, toxicity
from capmix.llm.common import materialise, scratch


def _as_row(docs: DataFrame) -> DataFrame:
    """Each row as one struct beside its text, so that no column's name can clash with a result's."""
    return docs.select(F.struct(*docs.columns).alias("_row"), "text")


def _without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is 0.5 or more go. Null and empty texts have no hits and stay; repeated rows fare alike."""
    lexicon = toxicity.train(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.score_toxicity(_as_row(docs), lexicon, keep=["_row"]).filter("predicted = 0").select("_row.*")


def _without_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by a five-word Jaccard similarity of 0.8 and more the first by id and text key stays, once.

    Null and wordless texts are one group. Of ties in id and text the row whose columns sort first stays.
    """
    return near_copies.one_of_each(docs)


def _without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 50 words and more stay where they occur first; later occurrences are cut out, and a document that
    loses all its words goes. Null, empty and short texts stay; a repeated row keeps its text."""
    return repeats.remove_repeats(docs)


def _without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of whose words a twentieth or more lies in benchmark windows go; of the others the spans of 13 words and
    more that windows cover are cut out. Null and wordless texts hit nothing and stay."""
    judged = decontamination.decontaminate(_as_row(docs), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), keep=["_row"], clean=True)
    return judged.filter("NOT contaminated").select(*[F.col("clean_text").alias(c) if c == "text" else F.col(f"_row.`{c}`") for c in docs.columns])


def _packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each kept document lies: bins without two documents of a source or of equal text. Null and empty texts have the
    size of their end mark; a null source conflicts with nothing; repeated rows lie in different bins."""
    return packing.pack(docs)


STAGES = [
    ("toxicity", _without_toxic),
    ("simhash_near_dedup", _without_near_duplicates),
    ("suffix_array_dedup", _without_repeats),
    ("benchmark_decontamination", _without_benchmark),
    ("best_fit_packing", _packed),
]

#: No SQL: fingerprints, rolling hashes and a learned lexicon have no form in it; see tests/llm/test_pipeline.py.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what each returns lies as Parquet in the shared folder until the next one is done."""
    docs, path = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES:
        with scratch(spark, path):
            docs, path = materialise(stage(spark, docs, sf_dir), f"stage_{name}", kept=True)
    return docs
