"""Tokens, n-grams, sentences and clean-up as Catalyst expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Entities decoded in captions, in this order; patterns of personal data and their masks.
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&"))
PERSONAL = (
    (r"[A-Za-z0-9._+-]+@[A-Za-z0-9-]+\.[A-Za-z0-9.-]+", "<mail>"),
    (r"\b[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\b", "<address>"),
    (r"\+?[0-9][0-9 -]{7,}[0-9]", "<number>"),
)
STOP_WORDS = ("that", "this", "with", "from", "have", "they", "which", "their", "there", "were", "been", "them", "then")


def tokens(text: Column | str) -> Column:
    """Lower-cased runs of Unicode letters; null text has none."""
    text = F.col(text) if isinstance(text, str) else text
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"\p{L}+"), F.lit(0))


def ngrams(words: Column | str, n: int, joiner: str = " ") -> Column:
    """All runs of n tokens of one caption, with repeats; empty if it is shorter."""
    words = F.col(words) if isinstance(words, str) else words

    def runs(w: Column) -> Column:
        last = F.size(w) - F.lit(n - 1)
        return F.when(last >= 1, F.transform(F.sequence(F.lit(1), last), lambda k: F.array_join(F.slice(w, k, n), joiner))).otherwise(F.array().cast("array<string>"))

    # bound once by a lambda: an expression in `words` must not be evaluated again for each run
    return F.transform(F.array(words), runs)[0]


def sentences(text: Column | str) -> Column:
    """Parts between full stops and newlines."""
    return F.split(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), r"[.\n]")


def first_line(text: Column | str) -> Column:
    return F.split_part(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), F.lit("\n"), F.lit(1))


def decode_entities(text: Column) -> Column:
    for a, b in ENTITIES:
        text = F.replace(text, F.lit(a), F.lit(b))
    return text


def clean_caption(text: Column) -> Column:
    """Entities decoded, symbols stripped, white space collapsed."""
    plain = F.regexp_replace(decode_entities(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N} .,'-]+", " ")
    return F.trim(F.regexp_replace(plain, r" +", " "))


def mask_personal(text: Column) -> Column:
    for pattern, mask in PERSONAL:
        text = F.regexp_replace(text, pattern, mask)
    return text


def bucket(token: Column, width: int = 64) -> Column:
    """The hashed dimension of a token: the first eight hex digits of its md5, modulo width."""
    return (F.conv(F.substring(F.md5(token), 1, 8), 16, 10).cast("bigint") % width).cast("int")
