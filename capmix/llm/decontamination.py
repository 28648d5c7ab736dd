"""Benchmark decontamination by a generalised suffix automaton of the normalised test items.

One automaton over words holds every substring of every item. Document words stream through it; the
state and the longest matching length are tracked, so whether the last 13 words occur in an item is
read off at each word (length >= 13). For each state the one that holds its last 13 words, and the nearest whole
short item on its suffix links, are known beforehand, so a scan is linear in the document however
repetitive items and document are. Items of fewer words count only as a whole. Words outside the items'
vocabulary reset the match, so only runs of known words of at least the shortest window's length are followed.

An automaton lies in flat arrays, with a table of the states that have several successors, and is built of at most
about `max_bytes` of item text (some 100 bytes for each byte of text while the driver builds it, a tenth of that
when broadcast). A larger benchmark is dealt to several by the hash of its item_id; up to `pass_parts` are scanned in
one pass over the documents, and only a benchmark beyond that takes further passes.

Defined cases: null or wordless texts and items have no words and hit nothing; repeated items and rows
all stay; rows are carried as one struct, so no column's name can clash with a result's, and a column of documents
with the name of a result is replaced; empty tables work.
"""

from __future__ import annotations

import hashlib
from array import array
from fractions import Fraction
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, small
from .words import alnum_bounds, alnum_words

WINDOW = 13
#: Bytes of item text in one automaton, and automata scanned in one pass.
MAX_BYTES, PASS_PARTS = 2 << 20, 8
ADDED = ("n_words", "n_hit", "n_items", "item_ids", "items_sha256", "contaminated", "hit_spans", "clean_text")


class _Growing:
    """The automaton while it is built: a dictionary of successors for each state."""

    def __init__(self):
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]

    def extend(self, last: int, w: int) -> int:
        if (old := self.next[last].get(w)) is not None:
            return old if self.length[old] == self.length[last] + 1 else self._split(last, w, old)
        new = self._state(self.length[last] + 1, {})
        p = last
        while p >= 0 and w not in self.next[p]:
            self.next[p][w] = new
            p = self.link[p]
        if p < 0:
            self.link[new] = 0
        else:
            q = self.next[p][w]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, w, q)
        return new

    def _state(self, length: int, edges: dict[int, int]) -> int:
        self.next.append(edges)
        self.link.append(0)
        self.length.append(length)
        return len(self.length) - 1

    def _split(self, p: int, w: int, q: int) -> int:
        copy = self._state(self.length[p] + 1, dict(self.next[q]))
        self.link[copy], self.link[q] = self.link[q], copy
        while p >= 0 and self.next[p].get(w) == q:
            self.next[p][w] = copy
            p = self.link[p]
        return copy


class Automaton:
    """A generalised suffix automaton over word ids in flat arrays, with the items at each window's state."""

    def __init__(self, items: list[tuple[object, bytes | None]], window: int = WINDOW):
        self.window, self.vocabulary = window, {}
        self.items = [str(i) for i, _ in items]
        coded = []
        for _, text in items:
            words = alnum_words(text)
            coded.append([self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words])
        grown = _Growing()
        for words in coded:
            last = 0
            for w in words:
                last = grown.extend(last, w)
        self.shortest = min((min(len(c), window) for c in coded if c), default=window)
        self.link, self.length = array("i", grown.link), array("i", grown.length)
        n, self.size = len(grown.next), max(len(self.vocabulary), 1)
        # a state's only successor and its word; states with several are in one table
        self.word, self.then, self.more = array("i", [-1]) * n, array("i", [0]) * n, {}
        for s, edges in enumerate(grown.next):
            if len(edges) == 1:
                [(self.word[s], self.then[s])] = edges.items()
            else:
                self.more.update((s * self.size + w, t) for w, t in edges.items())
        del grown
        order = np.argsort(np.asarray(self.length), kind="stable").tolist()
        # the state that holds the last `window` words of a longer match
        self.held = array("i", [0]) * n
        for s in order:
            up = self.link[s]
            self.held[s] = self.held[up] if up >= 0 and self.length[up] >= window else s
        full: dict[int, set[int]] = {}  # state of a window of full length -> items
        short: dict[int, set[int]] = {}  # state of a whole short item -> items
        for k, words in enumerate(coded):
            state, size = 0, 0
            for w in words:
                state, size = self.step(state, size, w)
                if size >= window:
                    full.setdefault(self.held[state], set()).add(k)
            if 0 < len(words) < window:
                short.setdefault(state, set()).add(k)
        self.full, self.short = ({s: array("i", sorted(v)) for s, v in d.items()} for d in (full, short))
        # the nearest whole short item at or above a state; such chains are shorter than a window
        self.nearest = array("i", [-1]) * n if short else None
        if short:
            for s in order:
                up = self.link[s]
                self.nearest[s] = s if s in short else self.nearest[up] if up >= 0 else -1

    def step(self, state: int, size: int, w: int) -> tuple[int, int]:
        """The state and the longest matching length after one more word."""
        while True:
            if self.word[state] == w:
                return self.then[state], size + 1
            if (t := self.more.get(state * self.size + w)) is not None:
                return t, size + 1
            if not state:
                return 0, 0
            state = self.link[state]
            size = self.length[state]

    def scan(self, words: list[bytes]) -> tuple[np.ndarray, set[int]]:
        """Spans (start, end) of windows that occur in `words`, and the items that they are of."""
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(-1)), np.int64, len(words))
        edge = np.diff(np.concatenate([[False], ids >= 0, [False]]).astype(np.int8))
        begins, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        long = ends - begins >= self.shortest
        window, word, then, more, width, link, length = self.window, self.word, self.then, self.more.get, self.size, self.link, self.length
        spans, whole, parts = array("q"), set(), set()
        for begin, end in zip(begins[long].tolist(), ends[long].tolist(), strict=True):
            state, size = 0, 0
            for at, w in enumerate(ids[begin:end].tolist(), begin + 1):
                while True:
                    if word[state] == w:
                        state, size = then[state], size + 1
                        break
                    if (t := more(state * width + w)) is not None:
                        state, size = t, size + 1
                        break
                    if not state:
                        size = 0
                        break
                    state = link[state]
                    size = length[state]
                if size >= window:
                    spans.extend((at - window, at))
                    whole.add(self.held[state])
                if self.nearest is not None:
                    s = self.nearest[state]
                    if s >= 0 and length[s] > size:
                        s = self.nearest[link[s]]
                    if s >= 0:
                        spans.extend((at - length[s], at))
                        parts.add(s)
        found = {k for s in whole for k in self.full[s]}
        while parts:
            s = parts.pop()
            found.update(self.short[s])
            if (up := self.nearest[self.link[s]]) >= 0:
                parts.add(up)
        return np.array(spans, np.int64).reshape(-1, 2), found


def merged(spans: np.ndarray) -> np.ndarray:
    """The union of spans as disjoint ascending spans."""
    if not len(spans):
        return spans
    spans = spans[np.argsort(spans[:, 0], kind="stable")]
    reach = np.maximum.accumulate(spans[:, 1])
    new = np.concatenate([[True], spans[1:, 0] > reach[:-1]])
    first = np.flatnonzero(new)
    return np.stack([spans[first, 0], reach[np.concatenate([first[1:], [len(spans)]]) - 1]], axis=1)


def automata(benchmark: DataFrame, window: int = WINDOW, item_col: str = "item_id", text_col: str = "text", max_bytes: int = MAX_BYTES) -> list[Automaton]:
    """Automata over all items; none is built of more than about max_bytes of text."""
    size = benchmark.select(F.sum(F.octet_length(text_col))).first()[0] or 0
    parts = size // max_bytes + 1
    out = []
    for k in range(parts):
        part = benchmark.filter(F.pmod(F.xxhash64(item_col), F.lit(parts)) == k) if parts > 1 else benchmark
        rows = part.select(F.col(item_col).cast("string"), F.col(text_col).cast("binary")).collect()  # size checked above
        out.append(Automaton([(r[0], bytes(r[1]) if r[1] is not None else None) for r in rows], window))
    return out


def cut_spans(text: bytes, spans: np.ndarray) -> bytes:
    """The text without the words of the spans, and without the separators between them."""
    starts, ends = alnum_bounds(text)
    out, at = [], 0
    for a, b in spans.tolist():
        out.append(text[at : starts[a]])
        at = int(ends[b - 1])
    return b"".join([*out, text[at:]])


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, coverage: float = 0.05, min_span: int = WINDOW, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", keep: list[str] | None = None, clean: bool = False, max_bytes: int = MAX_BYTES, pass_parts: int = PASS_PARTS) -> DataFrame:
    """Add to docs what the benchmark's windows hit in each whole text.

    n_words, n_hit, n_items bigint; item_ids array<string>, sorted; items_sha256 of them, comma-joined;
    contaminated: n_hit > 0 and n_hit >= coverage * n_words, by the decimal fraction that `coverage` reads as;
    hit_spans: merged spans as word positions. With `clean`: clean_text, null where contaminated (the document goes),
    else the text without the merged spans of at least `min_span` words. `keep` names the columns of docs to carry (all).
    """
    share = Fraction(str(coverage))
    added = ADDED if clean else ADDED[:-1]
    names = docs.columns if keep is None else keep
    carried = F.struct(*[docs[c] for c in names if c.lower() not in added] or [F.lit(0).alias("_")]).alias("row")
    state = docs.select(carried, F.col(text_col).cast("binary").alias("text"), F.lit(0).cast("bigint").alias("n"), F.array().cast("array<bigint>").alias("spans"), F.array().cast("array<string>").alias("items"))
    spark = docs.sparkSession
    parts = automata(benchmark, window, item_col, item_text, max_bytes)
    for k in range(0, len(parts), pass_parts):
        sent = spark.sparkContext.broadcast(parts[k : k + pass_parts])  # of pass_parts * max_bytes of item text

        def scan(batches, sent=sent):
            for batch in small(batches):
                sizes, spans, items = [], [], []
                for text, old, had in zip(batch.column(1).to_pylist(), batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True):
                    words, got, found = alnum_words(text), [np.array(old, np.int64).reshape(-1, 2)], set(had)
                    for own in sent.value:
                        some, which = own.scan(words)
                        got.append(some)
                        found.update(own.items[i] for i in which)
                    sizes.append(len(words))
                    spans.append(merged(np.concatenate(got)).ravel())
                    items.append(sorted(found))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sizes, pa.int64()), pa.array(spans, pa.list_(pa.int64())), pa.array(items, pa.list_(pa.string()))], batch.schema.names)

        state = state.mapInArrow(scan, state.schema)
        if k + pass_parts < len(parts):
            state = materialise(state, "decontamination")

    results = "n_words bigint, n_hit bigint, n_items bigint, item_ids array<string>, items_sha256 string, contaminated boolean, hit_spans array<struct<start:bigint,end:bigint>>" + (", clean_text string" if clean else "")
    kinds = {"n_words": pa.int64(), "n_hit": pa.int64(), "n_items": pa.int64(), "item_ids": pa.list_(pa.string()), "items_sha256": pa.string(), "contaminated": pa.bool_(), "hit_spans": pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))} | ({"clean_text": pa.string()} if clean else {})

    def judge(batches):
        for batch in small(batches):
            rows = []
            texts = batch.column("text").to_pylist() if clean else repeat(None, batch.num_rows)
            for text, n, flat, items in zip(texts, batch.column("n").to_pylist(), batch.column("spans").to_pylist(), batch.column("items").to_pylist(), strict=True):
                spans = np.array(flat, np.int64).reshape(-1, 2)
                hit = int((spans[:, 1] - spans[:, 0]).sum())
                bad = hit > 0 and hit * share.denominator >= share.numerator * n
                row = {"n_words": n, "n_hit": hit, "n_items": len(items), "item_ids": items, "items_sha256": hashlib.sha256(",".join(items).encode()).hexdigest(), "contaminated": bad, "hit_spans": [{"start": a, "end": b} for a, b in spans.tolist()]}
                if clean:
                    row["clean_text"] = None if bad or text is None else cut_spans(text, spans[spans[:, 1] - spans[:, 0] >= min_span]).decode()
                rows.append(row)
            yield pa.RecordBatch.from_arrays([batch.column("row"), *(pa.array([r[c] for r in rows], kinds[c]) for c in kinds)], ["row", *kinds])

    schema = state.select("row").schema
    for f in spark.createDataFrame([], results).schema:
        schema = schema.add(f)
    judged = (state if clean else state.drop("text")).mapInArrow(judge, schema)
    return judged.select(*[F.col(f"row.`{c}`") for c in names if c.lower() not in added], *kinds)
