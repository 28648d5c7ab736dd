"""Suffix-array dedup of passages, on sparse suffixes kept at content-selected minimisers.

A repeated passage is a run of at least `min_words` words (white-space words, lower-cased in A-Z) that
occurs more than once in the corpus, in one document or several. All occurrences but the first (in order
of document id, text key and position) are redundant.

1. Anchors. Every anchor_words-gram is hashed; of the anchors inside each window of min_words words the
   least hash is kept. The choice depends on the window's content alone, so equal windows keep the same
   anchor at the same offset: no repeat is lost though only about 2 in 44 suffixes are retained.
2. A first pass counts anchors (each task's distinct ones with their number). A Bloom filter of those that occur
   twice and more, of bounded size, is broadcast; whatever it lets through needlessly costs work, not results.
3. A second pass retains the suffixes at such anchors, each with the words that its windows hold to the left
   and to the right of the anchor. A task first compares its own; what is redundant there is settled, and only first
   occurrences are sent on, so a passage in a third of all documents travels once for each map chunk.
4. The suffixes of an anchor meet in one task. They are sorted by the words that follow and by those that precede,
   and neighbours' common lengths to the right and to the left tell which windows agree and how far (`compare`).
5. Matches of one document on one diagonal (same source, same distance) are joined across anchors: that extends
   them to the left and to the right, to their full length.

An anchor with more than `heavy` distinct surroundings (a common phrase) isn't held in one task: its windows are
dealt by the 64-bit hash of their whole content, and equal neighbours are found in a stream.

Words are compared by 32 bits of their hash, 50 words and more in a row, beside 64 bits of the anchor.

Defined cases: null or short texts have no windows; null ids sort first; rows with one id and different texts are
different documents, told apart by `row_key`, the hash of the text; a repeated row (same id, same text) is no second
occurrence of itself and stays; very long texts are held one at a time; no rows, no output; extra columns are
carried by `remove_repeats` in one struct, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import few, materialise, release, small, width
from .words import spaced_bounds, spaced_words

MIN_WORDS, ANCHOR_WORDS = 50, 8
#: Words of a map chunk, in which copies are settled before anything is sent.
CHUNK_WORDS = 400_000
#: Distinct surroundings of an anchor beyond which its windows are dealt one by one; suffixes compared at a time.
HEAVY, ROWS = 20_000, 20_000
#: The greatest number of bits of a Bloom filter, as a power of two; so many repeats of a span are broadcast at most.
BLOOM_BITS, BROADCAST_ROWS = 28, 100_000
_CACHE_WORDS = 150_000
_P, _Q = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)  # fixed odd multipliers
_NULL = np.iinfo(np.int64).min

_NAMES = ("doc_id", "row_key", "start", "n_words", "source_doc_id", "source_row_key", "source_start")
MATCH = ", ".join(f"{n} bigint" for n in _NAMES)
_MATCH = pa.schema([(n, pa.int64()) for n in _NAMES])
_SENT = "key bigint, doc_id bigint, row_key bigint, start bigint, low int, high int, words binary, n_words bigint, source_doc_id bigint, source_row_key bigint, source_start bigint"


class _WordHash(dict):
    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word)
        if len(word) <= 64:
            if len(self) >= _CACHE_WORDS:
                self.clear()
            self[word] = h
        return h


_HASHES = _WordHash()


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * _Q
    return x ^ (x >> np.uint64(29))


def rolling(hashes: np.ndarray, size: int) -> np.ndarray:
    """A 64-bit hash of every run of `size` word hashes, by doubling: O(log size) passes."""
    n = len(hashes) - size + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    power, span, done, total = hashes, 1, 0, None
    left = size
    while left:
        if left & 1:
            part = power[done : done + n]
            total = part.copy() if total is None else _mix(total * _P + part + np.uint64(done))
            done += span
        left >>= 1
        if left:
            power = _mix(power[: len(power) - span] * _P + power[span:] + np.uint64(span))
            span *= 2
    return total


def window_anchors(hashes: np.ndarray, min_words: int, anchor_words: int) -> tuple[np.ndarray, np.ndarray]:
    """For every window of one document: its anchor's hash and its anchor's position, which never goes back.

    Of equal least hashes the leftmost is the anchor.
    """
    n = len(hashes) - min_words + 1
    if n <= 0:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    grams = _mix(rolling(hashes, anchor_words))
    reach = min_words - anchor_words + 1
    # least of each run of `reach`, by doubling; positions ride along, the left one wins ties
    least, at, span = grams, np.arange(len(grams)), 1
    while span * 2 <= reach:
        take = least[span:] < least[: len(least) - span]
        least, at, span = np.where(take, least[span:], least[: len(least) - span]), np.where(take, at[span:], at[: len(at) - span]), span * 2
    shift = reach - span
    take = least[shift : shift + n] < least[:n]
    return np.where(take, least[shift : shift + n], least[:n]), np.where(take, at[shift : shift + n], at[:n])


class Suffixes:
    """Retained suffixes: their place, their windows and the words around their anchors.

    A suffix at word `at` of a document owns the windows that begin at at + low .. at + high (both at most 0). `words`
    has a row of 32-bit word hashes for each: min_words to the right from the anchor on, then to the left,
    the nearest first; words outside its windows are 0.
    """

    def __init__(self, key, doc, row, at, low, high, words):
        self.key, self.doc, self.row, self.at, self.low, self.high, self.words = key, doc, row, at, low, high, words

    def take(self, which: np.ndarray) -> Suffixes:
        return Suffixes(*(v[which] for v in (self.key, self.doc, self.row, self.at, self.low, self.high, self.words)))


def _held(low: np.ndarray, high: np.ndarray, min_words: int, left: int) -> np.ndarray:
    """Which columns of `words` lie in a suffix's windows."""
    return np.concatenate([np.arange(min_words) < (min_words + high)[:, None], np.arange(left) < -low[:, None]], axis=1)


def _ordered(key: np.ndarray, words: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The order by key and words, and how many words each shares with the one before it (-1: another key)."""
    n, w = words.shape
    raw = np.empty((n, 8 + 4 * w), np.uint8)
    raw[:, :8] = key.astype(">u8").view(np.uint8).reshape(n, 8)
    raw[:, 8:] = words.astype(">u4").view(np.uint8).reshape(n, 4 * w)
    order = np.argsort(raw.view(f"S{8 + 4 * w}").ravel(), kind="stable")
    sorted_, sizes, keys = words[order], size[order], key[order]
    unlike = sorted_[1:] != sorted_[:-1]
    common = np.where(unlike.any(axis=1), unlike.argmax(axis=1), w)
    common = np.minimum(common, np.minimum(sizes[1:], sizes[:-1]))
    return order, np.concatenate([[-1], np.where(keys[1:] == keys[:-1], common, -1)])


def places(doc: np.ndarray, row: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Ranks of places in order of document, text key and position; equal places have equal ranks."""
    order = np.lexsort((at, row, doc))
    d, r, a = doc[order], row[order], at[order]
    rank = np.empty(len(order), np.int64)
    rank[order] = np.cumsum(np.concatenate([[0], (d[1:] != d[:-1]) | (r[1:] != r[:-1]) | (a[1:] != a[:-1])]))
    return rank


def compare(s: Suffixes, min_words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(suffix, window offset, earliest suffix with the same window) of every redundant window.

    Suffixes are sorted by what follows their anchors and by what precedes them; neighbours' common lengths split both
    orders into classes for each length. A window `o` words before the anchor agrees between two suffixes if they are of one
    class to the right for min_words - o words and of one class to the left for o words.
    """
    none = np.empty(0, np.int64)
    _, back, count = np.unique(s.key, return_inverse=True, return_counts=True)
    some = np.flatnonzero(count[back] > 1)
    if not len(some):
        return none, none, none
    t, n = s.take(some), len(some)
    right, common_right = _ordered(t.key, t.words[:, :min_words], min_words + t.high)
    left, common_left = _ordered(t.key, t.words[:, min_words:], -t.low)
    rank = places(t.doc, t.row, t.at)
    found = []
    for offset in range(int(t.low.min()), int(t.high.max()) + 1):
        here = np.flatnonzero((t.low <= offset) & (offset <= t.high))
        if len(here) < 2:
            continue
        after, before = np.empty(n, np.int64), np.empty(n, np.int64)
        after[right] = np.cumsum(common_right < min_words + offset)
        before[left] = np.cumsum(common_left < -offset)
        pair = after[here] * (n + 1) + before[here]
        order = np.lexsort((rank[here], pair))
        own, first = pair[order], np.arange(len(order))
        new = np.concatenate([[True], own[1:] != own[:-1]])
        first = np.flatnonzero(new)[np.cumsum(new) - 1]
        i, j = here[order], here[order[first]]
        again = rank[i] != rank[j]  # the same place twice is a repeated row
        found.append((i[again], np.full(int(again.sum()), offset), j[again]))
    if not found:
        return none, none, none
    i, o, j = (np.concatenate(x) for x in zip(*found, strict=True))
    return some[i], o, some[j]


def settle(windows: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """By their hashes: for every window the first equal one in order of rank, and whether it comes after that."""
    order = np.lexsort((rank, windows))
    new = np.concatenate([[True], windows[order][1:] != windows[order][:-1]])[: len(order)]
    first = np.empty(len(order), np.int64)
    first[order] = order[np.flatnonzero(new)[np.cumsum(new) - 1]] if len(order) else 0
    return first, rank != rank[first]


def joined(m: np.ndarray) -> np.ndarray:
    """Matches (columns of MATCH) of one diagonal that overlap become one: extension to the left and to the right."""
    if not len(m):
        return m
    shift = m[:, 6] - m[:, 2]
    order = np.lexsort((m[:, 2], shift, m[:, 5], m[:, 4], m[:, 1], m[:, 0]))
    m, shift = m[order], shift[order]
    fresh = np.concatenate([[True], (m[1:, [0, 1, 4, 5]] != m[:-1, [0, 1, 4, 5]]).any(axis=1) | (shift[1:] != shift[:-1])])
    end = m[:, 2] + m[:, 3]
    group = np.cumsum(fresh) * (int(end.max()) + 1)
    reach = np.maximum.accumulate(end + group) - group
    new = fresh | np.concatenate([[True], m[1:, 2] > reach[:-1]])
    at = np.flatnonzero(new)
    last = np.concatenate([at[1:], [len(m)]]) - 1
    out = m[at]
    out[:, 3] = reach[last] - out[:, 2]
    return out


def _runs(doc, row, start, src_doc, src_row, src_start, min_words: int) -> np.ndarray:
    """Redundant windows and where each is from, as matches."""
    return joined(np.stack([doc, row, start, np.full(len(doc), min_words, np.int64), src_doc, src_row, src_start], axis=1).astype(np.int64))


def _batch(m: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(m[:, k], mask=m[:, k] == _NULL if k in (0, 4) else None) for k in range(7)], schema=_MATCH)


class Bloom:
    """A set of 64-bit numbers that may hold more than it was given, never less."""

    def __init__(self, numbers: DataFrame, most_bits: int = BLOOM_BITS):
        n = numbers.count()
        self.log = min(most_bits, max(16, (12 * n).bit_length()))
        log = self.log

        def work(batches):
            for batch in batches:
                for k in range(0, batch.num_rows, 100_000):
                    at = np.concatenate(Bloom.places(batch.column(0).slice(k, 100_000).to_numpy().view(np.uint64), log))
                    slot, back = np.unique(at >> np.uint64(6), return_inverse=True)
                    bits = np.zeros(len(slot), np.uint64)
                    np.bitwise_or.at(bits, back, np.uint64(1) << (at & np.uint64(63)))
                    yield pa.RecordBatch.from_arrays([pa.array(slot.astype(np.int32)), pa.array(bits.view(np.int64))], ["slot", "bits"])

        rows = numbers.mapInArrow(work, "slot int, bits bigint").groupBy("slot").agg(F.bit_or("bits").alias("bits")).toArrow()  # at most 2 ** most_bits bits
        self.bits = np.zeros(1 << (log - 6), np.uint64)
        self.bits[rows.column("slot").to_numpy()] = rows.column("bits").to_numpy().view(np.uint64)

    @staticmethod
    def places(x: np.ndarray, log: int) -> list[np.ndarray]:
        return [_mix(x * _P + np.uint64(k)) >> np.uint64(64 - log) for k in (1, 2, 3)]

    def holds(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for at in self.places(x, self.log):
            out &= (self.bits[at >> np.uint64(6)] >> (at & np.uint64(63))) & np.uint64(1) != 0
        return out


class _Chunk:
    """Words of some documents, and the suffixes at their anchors."""

    def __init__(self, min_words: int, anchor_words: int):
        self.min_words, self.anchor_words = min_words, anchor_words
        self.docs, self.size = [], 0

    def add(self, doc: int, row: int, text: bytes | None) -> None:
        words = spaced_words(text)
        if len(words) >= self.min_words:
            hashes = np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))
            keys, at = window_anchors(hashes, self.min_words, self.anchor_words)
            head = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
            last = np.concatenate([head[1:], [len(at)]]) - 1
            self.docs.append((doc, row, hashes, keys[head], at[head], head - at[head], last - at[head]))
            self.size += len(words)

    def anchors(self) -> np.ndarray:
        return np.concatenate([d[3] for d in self.docs])

    def surroundings(self) -> np.ndarray:
        """A hash of what surrounds each anchor: min_words // 2 words on either side, fewer where the text ends."""
        out, reach = [], self.min_words // 2
        for _, _, hashes, _, at, _, _ in self.docs:
            runs = rolling(hashes, reach)
            runs = np.concatenate([runs, np.zeros(len(hashes) - len(runs), np.uint64)])
            out.append(_mix(runs[at] * _P + runs[np.maximum(at - reach, 0)]))
        return np.concatenate(out)

    def flat(self):
        """(doc, row, at, low, high, base) of all suffixes, and all words in a row."""
        sizes = np.array([len(d[2]) for d in self.docs])
        base = np.cumsum(sizes) - sizes
        many = [len(d[3]) for d in self.docs]
        spread = lambda v: np.repeat(np.array(v, np.int64), many)
        return spread([d[0] for d in self.docs]), spread([d[1] for d in self.docs]), *(np.concatenate([d[k] for d in self.docs]) for k in (4, 5, 6)), spread(base)


def _around(words: np.ndarray, at: np.ndarray, low: np.ndarray, high: np.ndarray, min_words: int, left: int) -> np.ndarray:
    """The words of each suffix's windows: to the right, then to the left, 0 elsewhere."""
    reach = np.concatenate([np.arange(min_words), -1 - np.arange(left)])
    out = words[np.clip(at[:, None] + reach, 0, len(words) - 1)]
    return np.where(_held(low, high, min_words, left), out, np.uint32(0))


def repeated_passages(df: DataFrame, min_words: int = MIN_WORDS, anchor_words: int = ANCHOR_WORDS, id_col: str = "doc_id", text_col: str = "text", chunk_words: int = CHUNK_WORDS, heavy: int = HEAVY) -> DataFrame:
    """MATCH rows: redundant occurrences, and where each is from, at their full length.

    Positions count words from 0; row_key is the hash of the document's text. Matches of one document may overlap, and
    a source may itself be a copy of a still earlier occurrence; together they cover each word of every window
    that occurred before, and no other word.
    """
    spark = df.sparkSession
    left = min_words - anchor_words
    texts = df.select(F.col(id_col).cast("bigint").alias("doc_id"), F.xxhash64(text_col).alias("row_key"), F.col(text_col).cast("binary").alias("text"))

    def chunks(batches):
        held = _Chunk(min_words, anchor_words)
        for batch in small(batches):
            for doc, row, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.add(_NULL if doc is None else doc, row, text)
                if held.size >= chunk_words:
                    yield held
                    held = _Chunk(min_words, anchor_words)
                    release()
        if held.docs:
            yield held

    def count(batches):
        for chunk in chunks(batches):
            keys, back, n = np.unique(chunk.anchors(), return_inverse=True, return_counts=True)
            follow = chunk.surroundings()
            order = np.lexsort((follow, back))
            new = np.concatenate([[True], (back[order][1:] != back[order][:-1]) | (follow[order][1:] != follow[order][:-1])])
            distinct = np.bincount(back[order][new], minlength=len(keys))
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(n), pa.array(distinct)], ["key", "n", "distinct"])

    counts = texts.mapInArrow(count, "key bigint, n bigint, distinct bigint").groupBy("key").agg(F.sum("n").alias("n"), F.sum("distinct").alias("distinct"))
    counts = materialise(counts.filter("n > 1").select("key", (F.col("distinct") > heavy).alias("heavy")), "anchors")
    repeated, common = Bloom(counts.select("key")), Bloom(counts.filter("heavy").select("key"))
    sent = spark.sparkContext.broadcast((repeated, common))

    def rows(cols: list, kind: tuple) -> pa.RecordBatch:
        """A batch of _SENT: `cols` where `kind` names them, null elsewhere."""
        n, given = len(cols[0]), dict(zip(kind, cols, strict=True))
        types = {f.split()[0]: {"bigint": pa.int64(), "int": pa.int32(), "binary": pa.binary()}[f.split()[1]] for f in _SENT.split(", ")}
        return pa.RecordBatch.from_arrays([given[c].cast(t) if c in given else pa.nulls(n, t) for c, t in types.items()], list(types))

    def settled(m: np.ndarray):
        batch = _batch(m)
        return rows(batch.columns, _NAMES)

    def ids(v: np.ndarray) -> pa.Array:
        return pa.array(v, mask=v == _NULL)

    def retain(batches):
        """Rows of three kinds: matches settled here (key null), suffixes with their words, and single windows."""
        for chunk in chunks(batches):
            doc, row, at, low, high, base = chunk.flat()
            keys = chunk.anchors()
            want = sent.value[0].holds(keys)
            single = want & sent.value[1].holds(keys)
            # a key with too many suffixes in this chunk alone is compared here by hashes, too
            _, back, n = np.unique(keys, return_inverse=True, return_counts=True)
            crowded = want & (single | (n[back] > ROWS))
            usual = np.flatnonzero(want & ~crowded)
            words = np.concatenate([d[2] for d in chunk.docs]).astype(np.uint32)
            words[words == 0] = 1
            done = []
            order = usual[np.argsort(keys[usual], kind="stable")]
            k = keys[order]
            edge = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]])) if len(k) else np.empty(0, np.int64)
            begin = 0
            while begin < len(order):  # whole keys, some ROWS suffixes at a time
                stop = int(edge[np.searchsorted(edge, begin + ROWS)]) if begin + ROWS <= edge[-1] else len(order)
                stop = stop if stop > begin else len(order)
                part = order[begin:stop]
                begin = stop
                s = Suffixes(keys[part], doc[part], row[part], at[part], low[part], high[part], _around(words, base[part] + at[part], low[part], high[part], min_words, left))
                i, o, j = compare(s, min_words)
                done.append(_runs(s.doc[i], s.row[i], s.at[i] + o, s.doc[j], s.row[j], s.at[j] + o, min_words))
                first = _first_runs(s, i, o)
                if len(first):
                    which, lows, highs = first.T
                    held = _held(lows, highs, min_words, left)
                    flat = s.words[which][held]
                    ends = np.concatenate([[0], np.cumsum(held.sum(axis=1))]) * 4
                    packed = pa.Array.from_buffers(pa.binary(), len(which), [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(flat.tobytes())])
                    yield rows([pa.array(s.key[which].view(np.int64)), ids(s.doc[which]), pa.array(s.row[which]), pa.array(s.at[which]), pa.array(lows), pa.array(highs), packed], ("key", "doc_id", "row_key", "start", "low", "high", "words"))
            if crowded.any():
                hashes = np.concatenate([np.concatenate([r, np.zeros(len(d[2]) - len(r), np.uint64)]) for d in chunk.docs for r in (rolling(d[2], min_words),)])
                which = np.flatnonzero(crowded)
                many = (high - low + 1)[which]
                inner = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                of = np.repeat(which, many)
                start = at[of] + low[of] + inner
                windows, d, r = _mix(hashes[base[of] + start] ^ keys[of]), doc[of], row[of]
                first, again = settle(windows, places(d, r, start))
                done.append(_runs(d[again], r[again], start[again], d[first[again]], r[first[again]], start[first[again]], min_words))
                keep = np.flatnonzero(~again)
                yield rows([pa.array(windows[keep].view(np.int64)), ids(d[keep]), pa.array(r[keep]), pa.array(start[keep])], ("key", "doc_id", "row_key", "start"))
            if done and len(found := joined(np.concatenate(done))):
                yield settled(found)

    def _first_runs(s: Suffixes, i: np.ndarray, o: np.ndarray) -> np.ndarray:
        """(suffix, low, high): runs of the windows that aren't redundant."""
        many = s.high - s.low + 1
        begin = np.cumsum(many) - many
        left_over = np.ones(int(many.sum()), bool)
        left_over[begin[i] + o - s.low[i]] = False
        at = np.flatnonzero(left_over)
        of = np.repeat(np.arange(len(many)), many)[at]
        if not len(at):
            return np.empty((0, 3), np.int64)
        new = np.concatenate([[True], (np.diff(at) != 1) | (np.diff(of) != 0)])
        head = np.flatnonzero(new)
        last = np.concatenate([head[1:], [len(at)]]) - 1
        offset = at - begin[of] + s.low[of]
        return np.stack([of[head], offset[head], offset[last]], axis=1)

    def meet(batches):
        """Rows in order of their keys: whole keys are compared, single windows only with the first of their key."""
        release()
        held, size = [], 0
        first_window = None

        def flush(tables):
            t = pa.Table.from_batches(tables)
            low, high = (t.column(c).to_numpy().astype(np.int64) for c in ("low", "high"))
            words = np.zeros((t.num_rows, min_words + left), np.uint32)
            words[_held(low, high, min_words, left)] = np.frombuffer(b"".join(t.column("words").to_pylist()), np.uint32)
            s = Suffixes(t.column("key").to_numpy().view(np.uint64), t.column("doc_id").fill_null(_NULL).to_numpy(), t.column("row_key").to_numpy(), t.column("start").to_numpy(), low, high, words)
            i, o, j = compare(s, min_words)
            return _batch(_runs(s.doc[i], s.row[i], s.at[i] + o, s.doc[j], s.row[j], s.at[j] + o, min_words))

        for batch in batches:
            there = batch.column("key").is_valid()
            own = batch.filter(pc.invert(there))
            if own.num_rows:
                yield pa.RecordBatch.from_arrays([own.column(n) for n in _NAMES], schema=_MATCH)
            rest = batch.filter(there)
            spread = rest.filter(rest.column("words").is_null())
            if spread.num_rows:
                k, d, r, a = (spread.column(c).fill_null(_NULL).to_numpy() for c in ("key", "doc_id", "row_key", "start"))
                if first_window is not None:
                    k, d, r, a = (np.concatenate([[f], v]) for f, v in zip(first_window, (k, d, r, a), strict=True))
                new = np.concatenate([[True], k[1:] != k[:-1]])
                lead = np.flatnonzero(new)[np.cumsum(new) - 1]
                again = (d != d[lead]) | (r != r[lead]) | (a != a[lead])
                first_window = tuple(v[lead[-1]] for v in (k, d, r, a))
                if again.any():
                    yield _batch(_runs(d[again], r[again], a[again], d[lead[again]], r[lead[again]], a[lead[again]], min_words))
            usual = rest.filter(rest.column("words").is_valid())
            if not usual.num_rows:
                continue
            keys = usual.column("key").to_numpy()
            cut = int(np.searchsorted(keys, keys[-1]))
            if cut and size + cut >= ROWS // 2:
                yield flush([*held, usual.slice(0, cut)])
                held, size, cut = [], 0, cut
                held.append(usual.slice(cut))
            else:
                held.append(usual)
            size = sum(b.num_rows for b in held)
        if held:
            yield flush(held)

    order = ["key", F.col("words").isNull(), F.col("doc_id").asc_nulls_first(), "row_key", "start"]
    # One shuffle carries all kinds; settled matches are spread over all tasks by their own place.
    dealt = texts.mapInArrow(retain, _SENT).withColumn("to", F.coalesce("key", F.xxhash64("doc_id", "row_key")))
    met = dealt.repartition(width(spark), "to").drop("to").sortWithinPartitions(*order).mapInArrow(meet, MATCH)

    def extend(batches):
        """Matches in order of their documents: those of a document are joined across anchors."""
        release()
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            m = np.stack([c.fill_null(_NULL).to_numpy() for c in batch.columns], axis=1)
            m = m if held is None else np.concatenate([held, m])
            own = np.flatnonzero((m[:, 0] != m[-1, 0]) | (m[:, 1] != m[-1, 1]))
            cut = int(own[-1]) + 1 if len(own) else 0
            if cut:
                yield _batch(joined(m[:cut]))
            held = joined(m[cut:])
        if held is not None:
            yield _batch(held)

    return met.repartition(width(spark), "doc_id", "row_key").sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "row_key").mapInArrow(extend, MATCH)


def redundant_spans(matches: DataFrame) -> DataFrame:
    """(doc_id, row_key, spans): the union of each document's matches, as disjoint ascending word spans."""

    def work(batches):
        release()
        held = np.empty((0, 4), np.int64)

        def emit(m):
            m = m[np.lexsort((m[:, 2], m[:, 1], m[:, 0]))]
            end = m[:, 2] + m[:, 3]
            fresh = np.concatenate([[True], (m[1:, :2] != m[:-1, :2]).any(axis=1)])
            group = np.cumsum(fresh) * (int(end.max()) + 1)
            reach = np.maximum.accumulate(end + group) - group
            at = np.flatnonzero(fresh | np.concatenate([[True], m[1:, 2] > reach[:-1]]))
            last = np.concatenate([at[1:], [len(m)]]) - 1
            docs = np.flatnonzero(fresh[at])
            spans = pa.StructArray.from_arrays([pa.array(m[at, 2]), pa.array(reach[last])], ["start", "end"])
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([docs, [len(at)]]), pa.int32()), spans)
            ids = m[at[docs], 0]
            return pa.RecordBatch.from_arrays([pa.array(ids, mask=ids == _NULL), pa.array(m[at[docs], 1]), lists], ["doc_id", "row_key", "spans"])

        for batch in batches:
            if not batch.num_rows:
                continue
            held = np.concatenate([held, np.stack([c.fill_null(_NULL).to_numpy() for c in batch.columns], axis=1)])
            own = np.flatnonzero((held[:, :2] != held[-1, :2]).any(axis=1))
            if len(own):
                yield emit(held[: int(own[-1]) + 1])
                held = held[int(own[-1]) + 1 :]
        if len(held):
            yield emit(held)

    rows = matches.select("doc_id", "row_key", "start", "n_words").repartition(width(matches.sparkSession), "doc_id", "row_key")
    return rows.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "row_key").mapInArrow(work, "doc_id bigint, row_key bigint, spans array<struct<start:bigint,end:bigint>>")


def cut_words(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    """The text without the words of the spans; what separates the rest stays."""
    starts, ends = spaced_bounds(text)
    out, at = [], 0
    for a, b in spans:
        out.append(text[at : starts[a]])
        at = int(ends[min(b, len(ends)) - 1])
    return b"".join([*out, text[at:]])


def remove_repeats(df: DataFrame, min_words: int = MIN_WORDS, anchor_words: int = ANCHOR_WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """df without redundant occurrences; the first occurrence of each passage stays where it is.

    A document that loses all its words goes; one without repeats is returned as it is. Spans belong to a row by its id and
    its text's hash, so rows that share an id, or have none, lose nothing of each other's.
    """
    spark = df.sparkSession
    spans = materialise(redundant_spans(repeated_passages(df, min_words, anchor_words, id_col, text_col)), "spans")
    spans = F.broadcast(spans) if few(spans, BROADCAST_ROWS) else spans
    rows = df.select(F.struct(*df.columns).alias("row"), F.col(id_col).cast("bigint").alias("id"), F.xxhash64(text_col).alias("own_key"), F.col(text_col).cast("binary").alias("text"))
    both = rows.join(spans, F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("own_key") == F.col("row_key")), "left").select("row", "text", "spans")

    def cut(batches):
        for batch in small(batches):
            keep, out = [], []
            for text, own in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist(), strict=True):
                if own and text is not None:
                    text = cut_words(text, [(s["start"], s["end"]) for s in own])
                keep.append(not own or bool(text and text.strip()))
                out.append(text)
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(out, pa.binary()).cast(pa.string())], ["row", "text"]).filter(pa.array(keep, pa.bool_()))

    done = both.mapInArrow(cut, both.select("row", F.col("text").cast("string")).schema)
    return done.select(*[F.col("text").alias(c) if c == text_col else F.col(f"row.`{c}`") for c in df.columns])
