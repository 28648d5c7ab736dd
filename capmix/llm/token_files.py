"""Token-ID / binary output: zstandard frames, one for each document, under a shared dictionary.

File format (a block, all little endian):

    magic b"CMTK", version u8, id width u8 (2 or 4), reserved u16, dictionary hash u64,
    document count u32, then count + 1 offsets u64 into the frames, then the frames.

A frame is one document's ids, zstandard-compressed on its own with the dictionary whose hash the
block carries, so a short document is read by its offset without touching its neighbours. Blocks lie
as rows of Parquet files, written by Spark's own committed writer: a lost executor or a repeated task
leaves no half files, any store that Spark can write holds them, and the columns first_id / last_id
let a lookup skip the files that can't hold an id.

The dictionary serves short documents, so it is trained on a bounded sample of them: the `sample_docs` documents of at
most SAMPLE_BYTES with the smallest hash of their id. Every document, short or long, is encoded and written whole.

Defined cases: null text is an empty document (the end id alone); null ids come first; rows with equal
ids all stay, ordered by their frames; an empty table gives a folder without blocks, read as no rows;
extra columns are ignored. Where the tokenizer's own file says that it splits at white space and at the end
of a run of letters (`word_splitter`), distinct words are encoded once; every other tokenizer gets whole texts.
"""

from __future__ import annotations

import json
import os
import re
import struct
import zlib
from array import array
from string import punctuation

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import width

MAGIC, VERSION = b"CMTK", 1
HEAD = struct.Struct("<4sBBHQI")
LEVEL = 3
#: At most so many bytes of frames, or documents, in a block.
BLOCK_BYTES, BLOCK_DOCS = 4 << 20, 4096
#: Pieces kept by a worker's cache, and the longest piece that stays there.
CACHE_PIECES, CACHE_CHARS = 400_000, 48
#: A document of the dictionary's sample has so many bytes at most, which bounds what the driver fetches.
SAMPLE_BYTES = 1 << 16

ENCODED = "bucket int, id bigint, n_tokens bigint, frame binary"
BLOCKS = "bucket int, block int, first_id bigint, last_id bigint, n_docs int, start_in_bucket bigint, n_tokens bigint, ids array<bigint>, sizes array<bigint>, payload binary"


def _byte_alphabet() -> list[str]:
    """The letter of each byte in byte-level tokenizers: itself where it prints, else the next one from 256."""
    prints = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters = {b: chr(b) for b in prints}
    for k, b in enumerate(b for b in range(256) if b not in letters):
        letters[b] = chr(256 + k)
    return [letters[b] for b in range(256)]


_ALPHABET = _byte_alphabet()
#: Letters whose normal form and lower case are one letter each, at every place in a word.
_SAFE = "^[A-Za-zÀ-ÖØ-öø-ÿ]+$"
_LOWER_SAFE = re.compile("[a-zß-öø-ÿ]+")


def word_splitter(spec: dict) -> bool:
    """Does a tokenizer file state that white space is dropped and letters are a piece of their own?

    Only then are words, and words without the ASCII punctuation behind them, encoded apart: NFC and lower case (which
    never cross white space), a split that keeps runs of letters, single numbers and runs of other signs, bytes as letters
    without an added space, plain BPE, and no added token that swallows the space around it or holds one.
    """
    normal = (spec.get("normalizer") or {}).get("normalizers") or []
    steps = (spec.get("pre_tokenizer") or {}).get("pretokenizers") or []
    model = spec.get("model") or {}
    if [n.get("type") for n in normal] != ["NFC", "Replace", "Lowercase"] or [s.get("type") for s in steps] != ["Split", "ByteLevel"]:
        return False
    split, octets = steps
    pattern = (split.get("pattern") or {}).get("Regex", "").split("|")
    runs = pattern[-3:] == [r"[\p{L}]+", r"[\p{N}]", r"[^\s\p{L}\p{N}]+"] and all(p[:1] == "'" and p[1:].isalpha() for p in pattern[:-3])
    spaces = (normal[1].get("pattern") or {}).get("Regex") == r"\s+" and normal[1].get("content") == " "
    plain = model.get("type") == "BPE" and not model.get("dropout") and not model.get("unk_token") and not model.get("ignore_merges") and not model.get("continuing_subword_prefix")
    tokens = all(not (t["lstrip"] or t["rstrip"] or t["single_word"]) and not t["normalized"] and t["content"].isascii() and not any(c.isspace() for c in t["content"]) and t["content"][-1] in punctuation and not t["content"].rstrip(punctuation).isalpha() for t in spec.get("added_tokens", []))
    return runs and spaces and plain and tokens and split.get("behavior") == "Removed" and split.get("invert") is True and not octets.get("add_prefix_space") and octets.get("use_regex") is False


class Encoder:
    """Whole texts to serialized ids, by the tokenizers library, with a bounded cache of pieces.

    Of a word splitter, a batch is cut at white space and its distinct words are found by Arrow; only those are looked
    up, and the documents' ids are gathered from them in one pass. Words of safe letters lose the ASCII punctuation behind
    them, which is a piece of its own; every other word is given to the tokenizer as it is.
    """

    def __init__(self, path: str, end_id: int | None, splits_on_space: bool | None = None):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.width = 2 if max(self.tokenizer.get_vocab_size(), (end_id or 0) + 1) <= 1 << 16 else 4
        self.code = "H" if self.width == 2 else "I"
        self.end = b"" if end_id is None else array(self.code, [end_id]).tobytes()
        if splits_on_space is None:
            with open(path, encoding="utf-8") as f:
                splits_on_space = word_splitter(json.load(f))
        self.splits = splits_on_space
        self.pieces: dict[str, bytes] = {}

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [array(self.code, e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: list[str]) -> None:
        """Encode pieces. A lower-case word of safe letters is one piece that only changes its byte alphabet."""
        model, rest = self.tokenizer.model.tokenize, []
        for p in pieces:
            if _LOWER_SAFE.fullmatch(p):
                word = p if p.isascii() else "".join([_ALPHABET[b] for b in p.encode()])
                self.pieces[p] = array(self.code, [t.id for t in model(word)]).tobytes()
            else:
                rest.append(p)
        for k in range(0, len(rest), 10_000):
            part = rest[k : k + 10_000]
            self.pieces.update(zip(part, self._ids(part), strict=True))

    def _known(self, pieces: pa.Array) -> pa.Array:
        """The ids of pieces, by their distinct ones."""
        coded = pieces.dictionary_encode()
        distinct = coded.dictionary.to_pylist()
        if len(self.pieces) > CACHE_PIECES:
            self.pieces.clear()
        ids = list(map(self.pieces.get, distinct))
        if missing := [k for k, v in enumerate(ids) if v is None]:
            self._learn([distinct[k] for k in missing])
            for k in missing:
                ids[k] = self.pieces[distinct[k]]
                if len(distinct[k]) > CACHE_CHARS:
                    del self.pieces[distinct[k]]
        return pa.array(ids, pa.large_binary()).take(coded.indices)

    def _words(self, words: pa.Array) -> pa.Array:
        """The ids of distinct words. Safe letters before ASCII punctuation are a piece to the tokenizer."""
        base = pc.utf8_rtrim(words, punctuation)
        safe = pc.match_substring_regex(base, _SAFE)
        head = self._known(pc.if_else(safe, pc.utf8_lower(base), words))
        cut = pc.and_(safe, pc.greater(pc.binary_length(words), pc.binary_length(base)))
        if not pc.any(cut).as_py():
            return head
        tails = pc.if_else(cut, pc.replace_substring_regex(words, r"^[^!-/:-@\[-`{-~]*", ""), "")
        return pc.binary_join_element_wise(head, self._known(tails), pa.scalar(b"", pa.large_binary()))

    def __call__(self, texts: pa.Array) -> list[bytes]:
        texts = texts.fill_null("")
        if not self.splits:
            return [b + self.end for b in self._ids(texts.to_pylist())]
        # Arrow also cuts at four separators that aren't white space to tokenizers: such texts go whole
        odd = pc.match_substring_regex(texts, "[\\x1c-\\x1f]")
        lists = pc.utf8_split_whitespace(pc.if_else(odd, "", texts))
        coded = lists.flatten().dictionary_encode()
        ids = self._words(coded.dictionary).take(coded.indices)
        data = ids.buffers()[2]
        data = memoryview(data) if data is not None else memoryview(b"")
        at = np.frombuffer(ids.buffers()[1], np.int64, len(ids) + 1, 8 * ids.offset)[np.asarray(lists.offsets)].tolist()
        out = [bytes(data[a:b]) + self.end for a, b in zip(at[:-1], at[1:], strict=True)]
        for k in np.flatnonzero(odd.to_numpy(zero_copy_only=False)).tolist():
            out[k] = self._ids([texts[k].as_py()])[0] + self.end
        return out


def slices(batch: pa.RecordBatch, column: int, size: int = 8 << 20):
    """Parts of a batch with at most about `size` bytes in a string column each."""
    ends = np.cumsum(pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
    begin = 0
    while begin < batch.num_rows:
        done = ends[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(ends, done + size, side="right")))
        yield batch.slice(begin, end - begin)
        begin = end


_ENCODERS: dict[tuple, Encoder] = {}


def encoder(path: str, end_id: int | None, splits_on_space: bool | None = None) -> Encoder:
    """The worker's encoder: kept, with its cache, from task to task."""
    key = (path, end_id, splits_on_space)
    if key not in _ENCODERS:
        _ENCODERS[key] = Encoder(*key)
    return _ENCODERS[key]


def dictionary_hash(raw: bytes) -> int:
    return xxhash.xxh64_intdigest(raw) if raw else 0


def train_dictionary(df: DataFrame, id_col: str, text_col: str, tokenizer: str, end_id: int | None, splits_on_space: bool | None, sample_docs: int, size: int) -> bytes:
    """A zstandard dictionary of at most `size` bytes from the ids of `sample_docs` documents; empty if they are too few."""
    short = df.filter((F.octet_length(text_col) > 0) & (F.octet_length(text_col) <= SAMPLE_BYTES))
    n = short.select(F.lit(1)).count()
    if n == 0:
        return b""
    share = min(1.0, 2.0 * sample_docs / n)
    drawn = F.pmod(F.xxhash64(id_col), F.lit(1 << 30))
    rows = short.select(F.col(text_col).alias("t"), drawn.alias("h")).filter(F.col("h") < int(share * (1 << 30)) + 1).orderBy("h").limit(sample_docs).collect()
    texts = pa.array([r["t"] for r in rows if r["t"]], pa.string())
    samples = [x for x in encoder(tokenizer, end_id, splits_on_space)(texts) if len(x) >= 8]
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


def pack_block(frames: list[bytes], id_width: int, dict_hash: int) -> bytes:
    offsets = np.zeros(len(frames) + 1, dtype="<u8")
    np.cumsum([len(f) for f in frames], out=offsets[1:])
    return HEAD.pack(MAGIC, VERSION, id_width, 0, dict_hash, len(frames)) + offsets.tobytes() + b"".join(frames)


class Block:
    """Read access to one block's documents."""

    def __init__(self, payload: bytes, dictionaries: dict[int, bytes]):
        magic, version, self.width, _, self.hash, self.n = HEAD.unpack_from(payload)
        if magic != MAGIC or version != VERSION:
            raise ValueError("not a token block")
        if self.hash and self.hash not in dictionaries:
            raise ValueError(f"the dictionary {self.hash:016x} is missing")
        self.payload = memoryview(payload)
        self.offsets = np.frombuffer(payload, "<u8", self.n + 1, HEAD.size).astype(np.int64)
        self.base = HEAD.size + 8 * (self.n + 1)
        raw = dictionaries.get(self.hash)
        self.reader = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(raw)) if raw else zstandard.ZstdDecompressor()

    def ids(self, k: int) -> np.ndarray:
        frame = self.payload[self.base + int(self.offsets[k]) : self.base + int(self.offsets[k + 1])]
        return np.frombuffer(self.reader.decompress(frame), "<u2" if self.width == 2 else "<u4").astype("<u4")


def write_tokens(df: DataFrame, path: str, tokenizer: str, end_id: int | None = None, id_col: str = "doc_id", text_col: str = "text", splits_on_space: bool | None = None, sample_docs: int = 500, dictionary_bytes: int = 1 << 16) -> None:
    """Encode df's texts and write them below `path` in ascending id order: blocks/ and dictionary/."""
    spark = df.sparkSession
    raw = train_dictionary(df, id_col, text_col, tokenizer, end_id, splits_on_space, sample_docs, dictionary_bytes)
    h = dictionary_hash(raw)
    spark.createDataFrame([(h - (1 << 64) if h >> 63 else h, bytearray(raw))], "hash bigint, raw binary").coalesce(1).write.parquet(f"{path}/dictionary")
    buckets = width(spark, df.select(F.lit(1)).count(), 500_000)
    cuts = df.select(F.percentile_approx(F.col(id_col).cast("bigint"), [k / buckets for k in range(1, buckets)], max(10_000, 20 * buckets))).first()[0] if buckets > 1 else None
    cuts = np.array(sorted(set(cuts or [])), dtype=np.int64)
    sent = spark.sparkContext.broadcast(raw)  # of dictionary_bytes at most

    def encode(batches):
        enc = encoder(tokenizer, end_id, splits_on_space)
        writer = zstandard.ZstdCompressor(level=LEVEL, dict_data=zstandard.ZstdCompressionDict(sent.value)) if sent.value else zstandard.ZstdCompressor(level=LEVEL)
        for batch in batches:
            for part in slices(batch, 1):
                ids = part.column(0).to_pylist()
                raws = enc(part.column(1))
                pa.default_memory_pool().release_unused()
                place = [0 if i is None else int(np.searchsorted(cuts, i, side="left")) for i in ids]
                yield pa.RecordBatch.from_arrays([pa.array(place, pa.int32()), pa.array(ids, pa.int64()), pa.array([len(r) // enc.width for r in raws], pa.int64()), pa.array([writer.compress(r) for r in raws], pa.binary())], ["bucket", "id", "n_tokens", "frame"])

    id_width = Encoder(tokenizer, end_id, splits_on_space).width

    def pack(batches):
        bucket, block, start, held, size = None, 0, 0, [], 0

        def flush():
            ids = [x[0] for x in held]
            there = [i for i in ids if i is not None]
            n = sum(x[1] for x in held)
            return pa.RecordBatch.from_pylist([{"bucket": bucket, "block": block, "first_id": min(there, default=None), "last_id": max(there, default=None), "n_docs": len(held), "start_in_bucket": start, "n_tokens": n, "ids": ids, "sizes": [x[1] for x in held], "payload": pack_block([x[2] for x in held], id_width, h)}], schema=out), n

        out = pa.schema([("bucket", pa.int32()), ("block", pa.int32()), ("first_id", pa.int64()), ("last_id", pa.int64()), ("n_docs", pa.int32()), ("start_in_bucket", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.list_(pa.int64())), ("sizes", pa.list_(pa.int64())), ("payload", pa.binary())])
        for batch in batches:
            for b, i, n, frame in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if held and (b != bucket or size + len(frame) > BLOCK_BYTES or len(held) == BLOCK_DOCS):
                    done, count = flush()
                    yield done
                    block, start, held, size = block + 1, start + count, [], 0
                if b != bucket:
                    bucket, block, start = b, 0, 0
                held.append((i, n, frame))
                size += len(frame)
        if held:
            yield flush()[0]

    frames = df.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text")).mapInArrow(encode, ENCODED)
    ordered = frames.repartition(buckets, "bucket").sortWithinPartitions("bucket", F.col("id").asc_nulls_first(), "frame")
    ordered.mapInArrow(pack, BLOCKS).write.parquet(f"{path}/blocks")


def read_tokens(spark: SparkSession, path: str, ids: list[int] | None = None, digest: bool = False) -> DataFrame:
    """Read token files back: (id, start, n_tokens, tokens array<bigint>), or with `digest` (…, ids_crc32).

    start counts the ids of all documents before it. `ids` looks single documents up: files and blocks
    that can't hold one are skipped by their first and last id, and only the wanted frames are read.
    """
    dictionaries = {r["hash"] % (1 << 64): bytes(r["raw"]) for r in spark.read.schema("hash bigint, raw binary").parquet(f"{path}/dictionary").collect()}
    blocks = spark.read.schema(BLOCKS).parquet(f"{path}/blocks")
    counts = blocks.groupBy("bucket").agg(F.sum("n_tokens").alias("n")).collect()  # a row for each bucket
    base, total = {}, 0
    for r in sorted(counts, key=lambda r: r["bucket"]):
        base[r["bucket"]] = total
        total += r["n"]
    if ids is not None:
        wanted = F.lit(False)
        for i in ids:
            wanted = wanted | ((F.col("first_id") <= i) & (F.col("last_id") >= i))
        blocks = blocks.filter(wanted)
    keep = None if ids is None else set(ids)

    def read(batches):
        for batch in batches:
            for row in batch.to_pylist():
                block = Block(row["payload"], dictionaries)
                at = base[row["bucket"]] + row["start_in_bucket"]
                found = []
                for k, (i, n) in enumerate(zip(row["ids"], row["sizes"], strict=True)):
                    if keep is None or i in keep:
                        t = block.ids(k)
                        found.append((i, at, len(t), zlib.crc32(t.tobytes()) if digest else t.tolist()))
                    at += n
                cols = list(zip(*found, strict=True)) if found else [[], [], [], []]
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64() if digest else pa.list_(pa.int64()))], ["id", "start", "n_tokens", "ids_crc32" if digest else "tokens"])

    return blocks.select("bucket", "start_in_bucket", "ids", "sizes", "payload").mapInArrow(read, "id bigint, start bigint, n_tokens bigint, " + ("ids_crc32 bigint" if digest else "tokens array<bigint>"))
