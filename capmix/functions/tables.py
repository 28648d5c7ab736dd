"""Table functions: n-grams and sentences as rows, for lateral joins in SQL."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class NGrams:
    """ngrams(text, n): one row (position, gram) for each run of n tokens."""

    def eval(self, text: str, n: int):
        words = re.findall(r"[^\W\d_]+", (text or "").lower())
        for k in range(len(words) - n + 1):
            yield k, " ".join(words[k : k + n])


class Sentences:
    """sentences(text): one row (position, sentence) for each part between full stops and newlines."""

    def eval(self, text: str):
        for k, part in enumerate(re.split(r"[.\n]", text or "")):
            if part.strip():
                yield k, part.strip()


def register(spark: SparkSession) -> None:
    spark.udtf.register("capmix_ngrams", udtf(NGrams, returnType="position int, gram string"))
    spark.udtf.register("capmix_sentences", udtf(Sentences, returnType="position int, sentence string"))
