"""Toxicity: a weighted lexicon matched by Aho-Corasick after folding, normalised by length.

Folding lower-cases, maps digits that stand for letters and look-alikes of other alphabets to the Latin
letter, drops invisible characters and turns every other ASCII sign into a space, so that lexicon entries
begin (and whole words end) at a space. Phrases listed as exceptions are matched by the same
automaton; a hit inside one doesn't count.

The lexicon is learned: word beginnings (`prefix_chars`) and whole words whose document frequency is far
higher in toxic than in clean training documents; of nested entries that hit the same documents the
longest stays. Weights are log odds. A logistic model over the weighted hits and their rate per word gives
the score. Everything is learned from at most `sample_rows` labelled rows outside the hold-out.

Defined cases: null and empty texts have no hits and get the lowest score; without training rows of both
kinds the lexicon is empty and every score is the share of toxic rows (0 without rows); repeated rows get
equal scores; a column of documents with the name of a result is replaced; empty tables work.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass, field

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise, small
from .labelled import remainder, training_rows

MODULUS, HELD_OUT, SAMPLE_ROWS = 5, 0, 20_000
ADDED = ("score", "predicted", "hits", "n_words")

# Digits and signs read as letters; look-alikes of Latin letters; invisible characters.
_DIGITS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a"}
_LOOKALIKES = dict(zip("аеорсухіјѕԁԛԝһկοαερτυνικгтмнвкз", "aeopcyxijsdqwhqoaeptuvikrtmhbkz", strict=False))
_INVISIBLE = "​‌‍⁠﻿­"
EXCEPTIONS = ("trash can", "trash bin", "clown fish", "clown car", "pathetic fallacy")

_STR_TABLE = {ord(a): b for a, b in _LOOKALIKES.items()} | {ord(c): None for c in _INVISIBLE} | {0xFF01 + k: chr(0x21 + k) for k in range(94)}
_BYTE_TABLE = bytes(
    ord(_DIGITS[chr(b)]) if chr(b) in _DIGITS else b + 32 if 65 <= b <= 90 else b if b >= 128 or 97 <= b <= 122 or 48 <= b <= 57 else 32 for b in range(256)
)
_RARE = re.compile(rb"[\xcd-\xd5\xe2\xef]|\xc2\xad")
_DOLLAR = re.compile(rb"(?<=[A-Za-z0-9])\$(?=[A-Za-z0-9])")


def fold(text: str | None) -> bytes:
    """The folded text as words between single spaces, in UTF-8."""
    if not text:
        return b" "
    raw = text.lower().encode()
    if _RARE.search(raw):
        raw = text.lower().translate(_STR_TABLE).encode()
    if b"$" in raw:
        raw = _DOLLAR.sub(b"s", raw)
    words = raw.translate(_BYTE_TABLE).split()
    return b" " + b" ".join(words) + b" " if words else b" "


@dataclass
class Lexicon:
    """Entries are folded: " begin" matches words that begin so, " word " whole words."""

    weights: dict[str, float]
    exceptions: tuple[str, ...] = EXCEPTIONS
    coefficients: tuple[float, float, float] = (-4.0, 1.0, 1.0)
    constant: float | None = None
    _automaton: object = field(default=None, repr=False, compare=False)

    def __getstate__(self):
        return {**self.__dict__, "_automaton": None}

    def automaton(self):
        if self._automaton is None:
            a = ahocorasick.Automaton()
            for entry, w in self.weights.items():
                key = entry.encode().decode("latin-1")
                a.add_word(key, (len(key), w))
            for phrase in self.exceptions:
                key = fold(phrase).decode("latin-1")
                if len(key) > 1:
                    a.add_word(key, (len(key), None))
            a.make_automaton()
            self._automaton = a
        return self._automaton

    def weigh(self, folded: bytes) -> tuple[float, int, int]:
        """(sum of weights, hits, words); of entries that begin at one word the heaviest counts."""
        n = folded.count(b" ") - 1
        if n <= 0 or not self.weights:
            return 0.0, 0, max(n, 0)
        best: dict[int, float] = {}
        spared = []
        for end, (size, w) in self.automaton().iter(folded.decode("latin-1")):
            begin = end - size + 1
            if w is None:
                spared.append((begin, end))
            elif w > best.get(begin, 0.0):
                best[begin] = w
        for a, b in spared:
            for begin in [x for x in best if a <= x < b]:
                del best[begin]
        return sum(best.values()), len(best), n

    def score(self, total: float, n: int) -> float:
        if self.constant is not None:
            return self.constant
        a, b, c = self.coefficients
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, a + b * math.log1p(total) + c * math.log1p(100 * total / (n + 20))))))


def _fit(total: np.ndarray, n: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> tuple[float, float, float]:
    """Logistic regression by Newton steps on the two length-normalised features."""
    x = np.stack([np.ones(len(y)), np.log1p(total), np.log1p(100 * total / (n + 20))], axis=1)
    w = np.zeros(3)
    penalty = np.diag([1e-6, ridge * len(y) / 100, ridge * len(y) / 100])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty, x.T @ (y - p) - penalty @ w)
        w += np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    return tuple(float(v) for v in w)


def learn_lexicon(rows: DataFrame, min_documents: int = 3, min_ratio: float = 30.0, prefix_chars: tuple[int, int] = (4, 9)) -> Lexicon:
    """Learn entries, weights and the logistic model from (text, label) rows of bounded number, which bound the lexicon."""
    low, high = prefix_chars

    def count(batches):
        kinds = ["gram", "toxic", "clean"]
        toxic, clean = Counter(), Counter()

        def out():
            grams = list(toxic.keys() | clean.keys())
            yield pa.RecordBatch.from_arrays([pa.array(grams, pa.string()), pa.array([toxic[g] for g in grams], pa.int64()), pa.array([clean[g] for g in grams], pa.int64())], kinds)

        for batch in small(batches):
            for text, label in zip(batch.column(0).cast(pa.string()).to_pylist(), batch.column(1).to_pylist(), strict=True):
                grams = set()
                for w in set(fold(text).decode().split()):
                    grams.update(w[:k] for k in range(low, min(high, len(w)) + 1))
                    if len(w) > 2:
                        grams.add(w + " ")
                (toxic if label else clean).update(grams)
                if len(toxic) + len(clean) > 300_000:
                    yield from out()
                    toxic, clean = Counter(), Counter()
        yield from out()

    sizes = {r["label"]: r["n"] for r in rows.groupBy((F.col("label") != 0).alias("label")).agg(F.count("*").alias("n")).collect()}
    bad, good = sizes.get(True, 0), sizes.get(False, 0)
    if not bad or not good:
        return Lexicon({}, constant=float(bad > 0))
    counts = rows.mapInArrow(count, "gram string, toxic bigint, clean bigint").groupBy("gram").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
    odds = (F.col("toxic") + 0.5) / (bad + 1) / ((F.col("clean") + 0.5) / (good + 1))
    # Evidence that a gram's documents aren't toxic at the base rate, in nats; as many grams are tried, at
    # most about one of those kept is there by chance.
    n, p = F.col("toxic") + F.col("clean"), bad / (bad + good)
    evidence = F.col("toxic") * F.log(F.col("toxic") / (n * p)) + F.when(F.col("clean") > 0, F.col("clean") * F.log(F.col("clean") / (n * (1 - p)))).otherwise(0.0)
    tried = materialise(counts.filter(F.col("toxic") >= min_documents).withColumn("odds", odds).withColumn("evidence", evidence), "grams")
    enough = math.log(max(tried.count(), 1))
    found = tried.filter((F.col("odds") >= min_ratio) & (F.col("evidence") >= enough)).orderBy(F.desc("toxic"), F.desc("odds"), "gram").collect()  # of the bounded sample's grams
    entries = {r["gram"]: (r["toxic"], math.log(r["odds"])) for r in found}
    longest = {}
    for gram, (n, _) in entries.items():
        for k in range(low, min(len(gram), high + 1)):
            if gram[:k] in entries and entries[gram[:k]][0] <= 1.03 * n:
                longest[gram[:k]] = gram  # hits the same documents as a longer one
    kept: dict[str, float] = {}
    for gram, (_, w) in entries.items():
        shorter = [gram[:k] for k in range(low, min(len(gram), high + 1)) if gram[:k] in entries and gram[:k] not in longest]
        if gram not in longest and not any(entries[s][1] >= w - 0.7 for s in shorter):
            kept[" " + gram] = w
    lexicon = Lexicon(kept)

    def weigh(batches):
        for batch in small(batches):
            got = [lexicon.weigh(fold(t)) for t in batch.column(0).cast(pa.string()).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([g[0] for g in got], pa.float64()), pa.array([g[2] for g in got], pa.int64()), batch.column(1)], ["total", "n", "label"])

    seen = rows.mapInArrow(weigh, "total double, n bigint, label int").collect()  # as many as the bounded sample has
    total, n, y = (np.array([float(r[k]) for r in seen]) for k in range(3))
    lexicon.coefficients = _fit(total, n, (y != 0).astype(float))
    return lexicon


def one_of_each_family(rows: DataFrame, shingle: int = 5) -> DataFrame:
    """Training rows without most near copies: rows that share the least hash of their shingles, under either
    of two hashes, count once. Copies would pass for evidence that each of their words is toxic."""

    def least(text: bytes | None, seed: int) -> int:
        words = fold((text or b"").decode()).split()
        grams = [b" ".join(words[k : k + shingle]) for k in range(max(1, len(words) - shingle + 1))]
        return min(xxhash.xxh64_intdigest(g, seed) for g in grams) - (1 << 63)

    def keyed(batches):
        for batch in small(batches):
            texts = batch.column(0).to_pylist()
            yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array([least(t, s) for t in texts], pa.int64()) for s in (1, 2))], ["text", "label", "k1", "k2"])

    keys = rows.mapInArrow(keyed, "text binary, label int, k1 bigint, k2 bigint")
    first = keys.groupBy("label", "k1").agg(F.min(F.struct("k2", "text")).alias("r")).select("label", "r.*")
    return first.groupBy("label", "k2").agg(F.min("text").alias("text")).select("text", "label")


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, modulus: int = MODULUS, held_out: int = HELD_OUT, id_col: str = "doc_id", text_col: str = "text", label: str = "toxic") -> Lexicon:
    drawn = training_rows(docs, labels, label, modulus, held_out, sample_rows, id_col, text_col)
    rows = materialise(one_of_each_family(drawn), "toxicity").repartition(docs.sparkSession.sparkContext.defaultParallelism)
    return learn_lexicon(rows)


def score_toxicity(docs: DataFrame, lexicon: Lexicon, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Add score double, predicted int, hits bigint and n_words bigint to docs; `keep` names what to carry."""
    keep = [c for c in (docs.columns if keep is None else keep) if c not in ADDED]
    source = text_col if text_col in keep else "_text"
    rows = docs.select(*keep, *([] if source in keep else [F.col(text_col).alias("_text")]))

    def work(batches):
        for batch in small(batches):
            got = [lexicon.weigh(fold(t)) for t in batch.column(source).to_pylist()]
            scores = [lexicon.score(total, n) for total, _, n in got]
            table = {n: batch.column(n) for n in keep} | {"score": pa.array(scores, pa.float64()), "predicted": pa.array([int(s >= 0.5) for s in scores], pa.int32()), "hits": pa.array([g[1] for g in got], pa.int64()), "n_words": pa.array([g[2] for g in got], pa.int64())}
            yield pa.RecordBatch.from_arrays(list(table.values()), list(table))

    results = [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType()), T.StructField("hits", T.LongType()), T.StructField("n_words", T.LongType())]
    schema = T.StructType([*rows.select(*keep).schema, *results])
    return rows.mapInArrow(work, schema)


def held_out_column(id_col: str = "doc_id", modulus: int = MODULUS, held_out: int = HELD_OUT):
    return remainder(id_col, modulus) == held_out
