"""Captioners: an extractive one, and an n-gram sampler with top-K, temperature and length bounds.

They stand in for neural captioners behind one interface; `ExternalCaptioner` takes a real model.
"""

from __future__ import annotations

import functools
import hashlib
import itertools
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import text as tx
from ..storage import materialise, release

WIDTH = 64
START, END = "<s>", "</s>"
#: Contexts that are broadcast, with at most top_k successors each.
CORE = 65_536
#: Tokens of which a task counts bigrams at once, and rows that it gives at once.
COUNTED, GIVEN = 3_000_000, 100_000


@dataclass(frozen=True)
class GenConfig:
    top_k: int = 50
    temperature: float = 0.75
    min_len: int = 5
    max_len: int = 40
    seed: str = "capmix"


# A token is a run of Unicode letters: word characters but digits and the underscore.
_TOKEN = re.compile(r"[^\W\d_]+")
#: Tokens and the marks that end a sentence.
_PARTS = re.compile(r"[^\W\d_]+|[.\n]")


class _Buckets(dict):
    """The hashed dimension of each token; marks have one more."""

    def __missing__(self, token: str) -> int:
        if len(self) > 250_000:
            self.clear()
        b = self[token] = WIDTH if token in (".", "\n") else int(hashlib.md5(token.encode()).hexdigest()[:8], 16) % WIDTH
        return b


_BUCKETS = _Buckets()


def token_bucket(token: str) -> int:
    return _BUCKETS[token]


def token_buckets(tokens: list[str]) -> np.ndarray:
    return np.fromiter(map(_BUCKETS.__getitem__, tokens), np.int64, len(tokens))


def hashed_vector(tokens: list[str]) -> np.ndarray:
    return np.bincount(token_buckets(tokens), minlength=WIDTH).astype(float)


def _cos(a: np.ndarray, b: np.ndarray) -> float | None:
    size = np.sqrt((a @ a) * (b @ b))
    return float(a @ b / size) if size > 0 else None


def _best_sentence(codes: np.ndarray, content: np.ndarray, cfg: GenConfig) -> tuple[slice | None, float | None]:
    """Where the first sentence of the highest cosine lies, and its cosine. Sums are of whole numbers, so their order is free."""
    ends = np.append(np.flatnonzero(codes == WIDTH), len(codes))
    starts = np.append(0, ends[:-1] + 1)
    fit = np.flatnonzero((ends - starts >= max(cfg.min_len, 1)) & (ends - starts <= cfg.max_len))
    if not len(fit):
        return None, None
    starts, sizes = starts[fit], (ends - starts)[fit]
    at = np.arange(sizes.sum()) + np.repeat(starts - (sizes.cumsum() - sizes), sizes)
    vecs = np.bincount(np.repeat(np.arange(len(fit)) * WIDTH, sizes) + codes[at], minlength=len(fit) * WIDTH).reshape(-1, WIDTH).astype(float)
    sims = (vecs @ content / np.sqrt((vecs * vecs).sum(axis=1) * (content @ content))).tolist()
    rounded = [round(x, 6) for x in sims]
    k = rounded.index(max(rounded))
    return slice(int(starts[k]), int(starts[k] + sizes[k])), sims[k]


def hashed_pool(docs: DataFrame, cfg: GenConfig = GenConfig(), raw_limit: int | None = None) -> DataFrame:
    """H: raw and extractive captions of each document with their hashed-text cosines to its content.

    raw_text: the first line's tokens (all, unless raw_limit is given); gen_text: the sentence of min_len..max_len
    tokens of highest cosine (compared after rounding at 6; ties to the earliest), null if there is none.
    One Arrow pass, nothing is shuffled.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raws, gens, raw_sims, gen_sims, contents = [], [], [], [], np.zeros((batch.num_rows, WIDTH))
            for row, text in enumerate(batch.column(1).to_pylist()):
                parts = _PARTS.findall((text or "").lower())  # cut once: a text's tokens are those of its sentences
                codes = token_buckets(parts)
                contents[row] = content = np.bincount(codes, minlength=WIDTH + 1)[:WIDTH].astype(float)
                line = parts.index("\n") if "\n" in parts else len(parts)
                raw = [w for w in parts[:line] if w != "."][:raw_limit]
                best, sim = _best_sentence(codes, content, cfg)
                raws.append(raw)
                raw_sims.append(_cos(np.bincount(codes[:line][codes[:line] < WIDTH][:raw_limit], minlength=WIDTH).astype(float), content) if raw else None)
                gens.append(parts[best] if best else None)
                gen_sims.append(sim)
            words = pa.list_(pa.string())
            vectors = pa.ListArray.from_arrays(np.arange(0, contents.size + 1, WIDTH, dtype=np.int32), contents.ravel())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(raws, words), pa.array(gens, words), pa.array(raw_sims, pa.float64()), pa.array(gen_sims, pa.float64()), vectors], ["pair_id", "raw_text", "gen_text", "raw_sim", "gen_sim", "content_vec"])

    return docs.select(F.col("doc_id").alias("pair_id"), "text").mapInArrow(work, "pair_id bigint, raw_text array<string>, gen_text array<string>, raw_sim double, gen_sim double, content_vec array<double>")


_SIGMA = "\u03a3"


def _lowered(text: str) -> str:
    """A capital sigma is lowered by what stands beside it in its own sentence."""
    return text.lower() if _SIGMA not in text else "".join(p.lower() for p in re.split(r"([.\n])", text))


class _Numbers(dict):
    """Numbers of tokens from 1 on; both marks are 0. `odd` has those of tokens that aren't of letters (category L) alone."""

    def __init__(self):
        super().__init__({".": 0, "\n": 0})
        self.odd: set[int] = set()

    def __missing__(self, token: str) -> int:
        k = self[token] = len(self) - 1
        if not token.isalpha():
            self.odd.add(k)
        return k

    def of(self, text: str) -> np.ndarray:
        """The numbers of a text's tokens and marks."""
        parts = _PARTS.findall(_lowered(text))
        found = np.fromiter(map(self.__getitem__, parts), np.int64, len(parts))
        if self.odd and not self.odd.isdisjoint(found.tolist()):
            parts = [w for p in parts for w in ([p] if p.isalpha() or p in ".\n" else ["".join(g) for letters, g in itertools.groupby(p, str.isalpha) if letters])]
            found = np.fromiter(map(self.__getitem__, parts), np.int64, len(parts))
        return found


def bigram_parts(docs: DataFrame, min_len: int = 1) -> DataFrame:
    """(w1, w2, n) over the sentences of all texts, with start and end marks: counts of parts of the texts, to be added up."""

    def rows(numbers: _Numbers, codes: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        found, n = np.unique(np.concatenate(codes), return_counts=True)
        words = list(numbers)[2:]
        firsts, seconds = pa.array([START, *words], pa.string()), pa.array([END, *words], pa.string())
        for k in range(0, len(found), GIVEN):
            part = found[k : k + GIVEN]
            yield pa.RecordBatch.from_arrays([firsts.take(pa.array(part >> 32)), seconds.take(pa.array(part & 0xFFFFFFFF)), pa.array(n[k : k + GIVEN], pa.int64())], ["w1", "w2", "n"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers, codes, counted = _Numbers(), [], 0
        for batch in batches:
            for text in batch.column(0):
                ids = np.pad(numbers.of(text.as_py() or ""), 1)
                marks = np.flatnonzero(ids == 0)
                sizes = np.diff(marks)  # a sentence of n tokens has n + 1 pairs
                codes.append((ids[:-1] << 32 | ids[1:])[np.repeat(sizes > min_len, sizes)])
                counted += len(ids)
                if counted > COUNTED:
                    yield from rows(numbers, codes)
                    numbers, codes, counted = _Numbers(), [], 0
        if codes:
            yield from rows(numbers, codes)
        numbers, codes = _Numbers(), []
        release()

    return docs.select("text").mapInArrow(work, "w1 string, w2 string, n bigint")


def bigrams(docs: DataFrame, min_len: int = 1) -> DataFrame:
    """(w1, w2, n) over the sentences of all texts, with start and end marks."""
    return bigram_parts(docs, min_len).groupBy("w1", "w2").agg(F.sum("n").alias("n"))


def mixed_bigrams(pool: DataFrame, tuned: DataFrame, weight: float = 20.0) -> DataFrame:
    """A specialised captioner's table: pool counts plus weighted counts of the caption corpus."""
    return pool.select("w1", "w2", F.col("n").cast("double").alias("n")).union(tuned.select("w1", "w2", (F.col("n") * weight).alias("n"))).groupBy("w1", "w2").agg(F.sum("n").alias("n"))


def top_successors(table: DataFrame, k: int) -> DataFrame:
    """(w1, w2, n, rank): the k commonest successors of each word; ties in word order."""
    w = Window.partitionBy("w1").orderBy(F.desc("n"), "w2")
    return table.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


class _Choice:
    """Successors of a context and their weights; words are given, or numbers of words in a vocabulary."""

    __slots__ = ("end", "names", "other", "sums", "total", "weights", "words")

    def __init__(self, words, weights: np.ndarray, names: pa.Array | None = None, end: int | None = None):
        self.words, self.weights, self.names = words, weights, names
        self.sums, self.total, self.other = weights.cumsum(), weights.sum(), None
        if names is None:
            self.end = words.index(END) if END in words else None
        else:
            at = np.flatnonzero(words == end) if end is not None else ()
            self.end = int(at[0]) if len(at) else None

    def without_end(self) -> _Choice:
        if self.other is None:
            k = self.end
            words = self.words[:k] + self.words[k + 1 :] if self.names is None else np.delete(self.words, k)
            self.other = _Choice(words, np.delete(self.weights, k), self.names)
        return self.other

    def pick(self, u: float) -> str:
        word = self.words[min(int(self.sums.searchsorted(u * self.total, side="right")), len(self.words) - 1)]
        return word if self.names is None else self.names[int(word)].as_py()


class _Core:
    """The commonest contexts in flat arrays: words, where each one's successors lie, their numbers and counts."""

    def __init__(self, words: pa.ChunkedArray, successors: pa.ChunkedArray, counts: pa.ChunkedArray):
        coded = successors.combine_chunks()
        flat = coded.flatten().dictionary_encode()
        self.contexts, self.names = words.combine_chunks(), flat.dictionary
        self.ends = np.cumsum(coded.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))
        self.words = flat.indices.to_numpy()
        self.counts = counts.combine_chunks().flatten().to_numpy()
        end = self.names.index(END).as_py()
        self.end = end if end >= 0 else None

    def choice(self, k: int, heat: float) -> _Choice | None:
        a, b = int(self.ends[k - 1]) if k else 0, int(self.ends[k])
        return _Choice(self.words[a:b], self.counts[a:b] ** (1 / heat), self.names, self.end) if b > a else None


class NgramSampler:
    """Draws captions from the whole bigram table: the top_k successors of every context.

    The model is a table of one row for each context and grows with the corpus. Only its `core`, the commonest contexts, of a
    bounded number, is broadcast: a caption is drawn on while its words are in there, and joined with the table for any other.

    table: (w1, w2, n); the counts of a pair that comes again are added up. With `tuned`, bigrams of a caption corpus, the rows
    also hold a specialised captioner's successors, of mixed counts (as mixed_bigrams), where they differ: they do for its
    contexts alone. The mixed top_k are among the top_k and that corpus's pairs, since no other count grows.
    """

    def __init__(self, table: DataFrame, cfg: GenConfig = GenConfig(), core: int = CORE, tuned: DataFrame | None = None, weight: float = 20.0):
        self.cfg, self.all, spark = cfg, None, table.sparkSession
        self.parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
        none = F.lit(None).cast("double")
        rows = table.select("w1", "w2", F.col("n").cast("double").alias("n"), none.alias("more"))
        if tuned is not None:
            rows = rows.union(tuned.select("w1", "w2", none, (F.col("n") * weight).cast("double")))
        # dealt by the context once: sums, ranks and rows of the model, and later joins with it, stay there
        pairs = rows.repartition(self.parts, "w1").groupBy("w1", "w2").agg(F.sum("n").alias("n"), F.sum("more").alias("more"))
        ranked = pairs.withColumn("rank", F.row_number().over(Window.partitionBy("w1").orderBy(F.desc("n"), "w2")))
        kept = ranked.filter((F.col("rank") <= cfg.top_k) | F.col("more").isNotNull()).groupBy("w1").agg(F.array_sort(F.collect_list(F.struct("rank", "w2", "n", "more"))).alias("s"))
        own = F.filter("s", lambda x: (x["rank"] <= cfg.top_k) & x["n"].isNotNull()) if tuned is not None else F.col("s")
        mixed = F.slice(F.array_sort(F.transform("s", lambda x: F.struct((-F.coalesce(x["n"], F.lit(0.0)) - F.coalesce(x["more"], F.lit(0.0))).alias("less"), x["w2"].alias("w2")))), 1, cfg.top_k)
        lists = kept.select("w1", own.alias("s"), (F.when(F.exists("s", lambda x: x["more"].isNotNull()), mixed) if tuned is not None else F.lit(None).cast("array<struct<less:double,w2:string>>")).alias("m"))
        model = lists.select("w1", F.col("s.w2").alias("words"), F.col("s.n").alias("counts"), F.col("m.w2").alias("tuned_words"), F.transform("m.less", lambda x: -x).alias("tuned_counts"))
        total = lambda c: F.aggregate(F.coalesce(c, F.array().cast("array<double>")), F.lit(0.0), lambda a, n: a + n)
        self.model = model.withColumn("weight", F.greatest(total(F.col("counts")), total(F.col("tuned_counts")))).cache()  # at most top_k entries a list
        first = self.model.filter(F.col("w1") == START).first()
        self.first = [(first["words"], first["counts"]) if first else None, (first["tuned_words"], first["tuned_counts"]) if first and first["tuned_words"] else None]
        self.core = self._core(core)

    def _core(self, most: int) -> list[_Core | None]:
        """The contexts of the greatest weight, at most so many: their weights are cut first, then their rows fetched."""
        rest = self.model.filter(F.col("w1") != START)
        cut = rest.select("weight").orderBy(F.desc("weight")).limit(most + 1).agg(F.count("*").alias("n"), F.min("weight").alias("least")).first()
        rows = (rest if cut["n"] <= most else rest.filter(F.col("weight") > cut["least"])).drop("weight").toArrow()  # at most `most` rows
        return [_Core(rows.column("w1"), rows.column(f"{k}words"), rows.column(f"{k}counts")) if rows.num_rows else None for k in ("", "tuned_")]

    def _start(self, heat: float, tuned: bool) -> _Choice:
        """What a caption starts with; successors of words without any."""
        words, counts = (self.first[1] if tuned else None) or self.first[0] or ([], [])
        return _Choice(list(words), np.array(counts, float) ** (1 / heat))

    @staticmethod
    def _draw(cfg: GenConfig, start: _Choice, key: int, at: int, own: _Choice) -> str | None:
        """The word at position `at`; END or None: the caption is over."""
        while True:
            if at < cfg.min_len and own.end is not None:
                own = own.without_end()
                if not len(own.words):
                    own = start
                    if own.words == [END]:
                        return None
            if not len(own.words):
                return None
            word = own.pick(int(hashlib.md5(f"{key}:{at}:{cfg.seed}".encode()).hexdigest()[:12], 16) / 16**12)
            if word != END or at >= cfg.min_len:
                return word
            own = start

    def caption(self, key: int) -> list[str]:
        """The caption of a pair: the same whenever and wherever it is drawn. For tests: it collects the model."""
        start, heat = self._start(self.cfg.temperature, False), 1 / self.cfg.temperature
        if self.all is None:
            self.all = {r["w1"]: _Choice(list(r["words"]), np.array(r["counts"], float) ** heat) for r in self.model.collect() if r["words"]}
        out: list[str] = []
        while len(out) < self.cfg.max_len:
            word = self._draw(self.cfg, start, key, len(out), self.all.get(out[-1], start) if out else start)
            if word is None or word == END:
                break
            out.append(word)
        return out

    def generate(self, pairs: DataFrame, captioner: str = "sampler", temperatures: tuple[float, ...] = (), tuned: tuple[bool, ...] = (False,)) -> DataFrame:
        """CaptionSheet: pair_id, captioner, temperature, text, of a DataFrame with pair_id.

        All of several temperatures are drawn in the same rounds, and so are the plain and the specialised captioner, whose name
        ends in _ft, if `tuned` asks for both.
        """
        cfg, draw = self.cfg, self._draw
        heats = temperatures or (cfg.temperature,)
        starts = {(t, k): self._start(t, k) for t in heats for k in tuned}
        sent = pairs.sparkSession.sparkContext.broadcast(self.core)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            plain, special = sent.value
            places = {w: k for k, w in enumerate(plain.contexts.to_pylist())} if plain else {}
            hot: dict[tuple, _Choice | None] = {}

            def known(word: str, heat: float, ft: bool) -> _Choice | None:
                """The choice after a word of the core; the specialised captioner's own only where it has one."""
                found = hot.get((word, heat, ft), hot)
                if found is hot:
                    k = places.get(word)
                    found = None if k is None else (ft and special.choice(k, heat)) or plain.choice(k, heat) or starts[heat, ft]
                    hot[word, heat, ft] = found
                return found

            for batch in batches:
                texts, last, sizes = [], [], []
                for key, t, ft, text, at, words, counts in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    own = _Choice(words, np.array(counts, float) ** (1 / t)) if words else starts[t, ft]
                    made = [text] if text else []
                    while own is not None:
                        word = draw(cfg, starts[t, ft], key, at, own)
                        if word is None or word == END:
                            word = None
                            break
                        made.append(word)
                        at += 1
                        if at >= cfg.max_len:
                            word = None
                            break
                        own = known(word, t, ft)
                    texts.append(" ".join(made))
                    last.append(word)
                    sizes.append(at)
                if len(hot) > 4 * CORE:
                    hot.clear()
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(texts, pa.string()), pa.array(last, pa.string()), pa.array(sizes, pa.int32())], ["pair_id", "temperature", "tuned", "text", "word", "size"])
            hot.clear()
            release()

        schema, none = "pair_id bigint, temperature double, tuned boolean, text string, word string, size int", F.lit(None).cast("array<string>")
        runs = F.explode(F.array(*[F.struct(F.lit(float(t)).alias("temperature"), F.lit(k).alias("tuned")) for t in heats for k in tuned])).alias("run")
        given = pairs.select(F.col("pair_id").cast("bigint")).repartition(self.parts, "pair_id").select("pair_id", runs)
        given = given.select("pair_id", "run.temperature", "run.tuned", F.lit("").alias("text"), F.lit(0).alias("size"), none.alias("words"), F.lit(None).cast("array<double>").alias("counts"))
        done, model = [], self.model.withColumnRenamed("w1", "word")
        for _ in range(max(cfg.max_len, 1)):
            state = materialise(given.mapInArrow(work, schema), "captions")
            done.append(state.filter("word IS NULL").select("pair_id", "temperature", "tuned", "text"))
            going = state.filter("word IS NOT NULL")
            if going.isEmpty():
                break
            # the captions are hashed, and the model, dealt by its contexts already, streams past them
            met = going.hint("shuffle_hash").join(model, "word", "left")
            pick = lambda c: F.when(F.col("tuned") & F.col(f"tuned_{c}").isNotNull(), F.col(f"tuned_{c}")).otherwise(F.col(c)).alias(c)
            given = met.select("pair_id", "temperature", "tuned", "text", "size", pick("words"), pick("counts"))
        every = functools.reduce(DataFrame.union, done)  # all are drawn by now
        return every.select("pair_id", F.concat(F.lit(captioner), F.when(F.col("tuned"), "_ft").otherwise("")).alias("captioner"), "temperature", "text")


class ExternalCaptioner:
    """A hook for a real model: `load` is called once for each task, the result with lists of inputs."""

    def __init__(self, load: Callable[[], Callable[[list], list[str]]], name: str):
        self.load, self.name = load, name

    def generate(self, pairs: DataFrame, input_col: str) -> DataFrame:
        load, name = self.load, self.name

        def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            model = load()
            for pdf in batches:
                yield pd.DataFrame({"pair_id": pdf.pair_id, "captioner": name, "temperature": 1.0, "text": model(pdf[input_col].tolist())})

        return pairs.select("pair_id", input_col).mapInPandas(work, "pair_id bigint, captioner string, temperature double, text string")
