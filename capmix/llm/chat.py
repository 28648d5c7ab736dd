r"""Chat formatting at token level.

Every turn becomes

    START role-ids SEP text-ids END

START, SEP and END are reserved ids beyond the tokenizer's vocabulary; role and text are encoded apart,
so no text can yield a reserved id. Rendered as text the marks read <|im_start|>, <|im_sep|>,
<|im_end|>; a text that holds such a string is escaped before it is encoded by one more backslash
behind "<|" (`<|im_end|>` -> `<|\im_end|>`, `<|\im_end|>` -> `<|\\im_end|>`), which `unescape` undoes
exactly. The loss mask follows from prefix sums of the segment lengths: positions from the text's
first id to its last in turns of the trained roles.

`format_chat` gives one row for each turn: conv_id, seq, token_start (ids of all earlier turns), ids,
mask. A conversation is the concatenation of its rows in order of seq, so no row grows with a conversation's length.
`read_back` takes such rows in any order and partitioning, as a stored table gives them, reads only ids and masks,
and rebuilds turns and digests in one streaming pass; a conversation of any length needs the memory of
one batch (its SHA-256 is sequential by nature, so one task must see the turns in order, but encoding is
done before, wherever the rows lie). Between tasks ids travel packed to their width and masks as the text's bounds.

A byte-level tokenizer with a rank file of the same name beside it is run by tiktoken, which gives the same ids
(texts with very long runs of white space, on which it fails, go to the tokenizers library).

Defined cases: null role or text is empty; null turns come first; equal turns are ordered by role and
ids and repeated rows all count; rows with null conv_id form one conversation; no rows, no output;
extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import width

# The marks of the template, in the order of their ids.
MARKS = ("<|im_start|>", "<|im_sep|>", "<|im_end|>")

# Fixed value: the public pattern by which byte-level tokenizers of this kind cut a text.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_LONG_SPACE = re.compile(r"\s{10000}")

_NAMES = "im_start|im_sep|im_end|endoftext"
_ESCAPE = re.compile(rf"<\|(\\*)({_NAMES})\|>")
_UNESCAPE = re.compile(rf"<\|\\(\\*)({_NAMES})\|>")


def escape(text: str) -> str:
    return _ESCAPE.sub(r"<|\\\1\2|>", text) if "<|" in text else text


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"<|\1\2|>", text) if "<|\\" in text else text


class ChatTokenizer:
    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        first = self.tokenizer.get_vocab_size()
        self.start, self.sep, self.end = range(first, first + len(MARKS))
        self.kind = np.dtype("<u2") if self.end < 1 << 16 else np.dtype("<u4")
        self.ranks = None
        ranks = os.path.splitext(path)[0] + ".tiktoken"
        if os.path.exists(ranks):
            import tiktoken

            with open(ranks, "rb") as f:
                table = {base64.b64decode(piece): int(rank) for piece, rank in map(bytes.split, f)}
            self.ranks = tiktoken.Encoding("chat", pat_str=PIECES, mergeable_ranks=table, special_tokens={})

    def encode(self, texts: list[str]) -> list[list[int]]:
        if self.ranks is None:
            return [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        plain = self.ranks.encode_ordinary
        return [self.tokenizer.encode(t, add_special_tokens=False).ids if len(t) > 10_000 and _LONG_SPACE.search(t) else plain(t) for t in texts]

    def decode(self, parts: list[list[int]]) -> list[str]:
        if self.ranks is None:
            return self.tokenizer.decode_batch(parts, skip_special_tokens=False)
        return [self.ranks.decode_bytes(p).decode("utf-8", "replace") for p in parts]


_LOADED: dict[str, ChatTokenizer] = {}


def tokenizer_at(path: str) -> ChatTokenizer:
    if path not in _LOADED:
        _LOADED[path] = ChatTokenizer(path)
    return _LOADED[path]


def assemble(role_ids: list[int], text_ids: list[int], trained: bool, tok: ChatTokenizer) -> tuple[np.ndarray, np.ndarray]:
    """Splice one turn's ids; of its segments' prefix sums, (begin, end) of what the loss covers."""
    segments = ([tok.start], role_ids, [tok.sep], text_ids, [tok.end])
    ends = np.cumsum([len(s) for s in segments])
    out = np.empty(ends[-1], tok.kind)
    for segment, end in zip(segments, ends.tolist(), strict=True):
        out[end - len(segment) : end] = segment
    return out, ends[2:4] if trained else ends[[2, 2]]


def format_chat(df: DataFrame, tokenizer: str, trained_roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """(conv_id, seq, token_start, ids array<int>, mask array<boolean>) from (conv_id, turn, role, text)."""
    trained = frozenset(trained_roles)

    def encode(batches):
        tok = tokenizer_at(tokenizer)
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                conv, turn, roles, texts = (part.column(c) for c in range(4))
                raw_roles = [r or "" for r in roles.to_pylist()]
                known = {r: ids for r, ids in zip(dict.fromkeys(raw_roles), tok.encode([escape(r) for r in dict.fromkeys(raw_roles)]), strict=True)}
                rows = [assemble(known[r], ids, r in trained, tok) for r, ids in zip(raw_roles, tok.encode([escape(t or "") for t in texts.to_pylist()]), strict=True)]
                bounds = np.array([r[1] for r in rows], np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([conv, turn, pa.array([r[0].tobytes() for r in rows], pa.binary()), pa.array(bounds[:, 0]), pa.array(bounds[:, 1]), pa.array(raw_roles, pa.string())], ["conv_id", "turn", "packed", "begin", "end", "role"])

    def number(batches):
        kind = tokenizer_at(tokenizer).kind
        conv, seq, start, begun = None, 0, 0, False
        for whole in batches:
            for k in range(0, whole.num_rows, 512):
                batch = whole.slice(k, 512)
                sizes = np.asarray(pc.binary_length(batch.column(1))).astype(np.int64) // kind.itemsize
                begins, ends = batch.column(2).to_numpy(), batch.column(3).to_numpy()
                seqs, starts = [], []
                for c, n in zip(batch.column(0).to_pylist(), sizes.tolist(), strict=True):
                    if not begun or c != conv:
                        conv, seq, start, begun = c, 0, 0, True
                    seqs.append(seq)
                    starts.append(start)
                    seq, start = seq + 1, start + n
                offsets = np.concatenate([[0], np.cumsum(sizes)])
                flat = np.frombuffer(b"".join(batch.column(1).to_pylist()), kind).astype(np.int32)
                at = np.arange(len(flat)) - np.repeat(offsets[:-1], sizes)
                mask = (at >= np.repeat(begins, sizes)) & (at < np.repeat(ends, sizes))
                ids = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(seqs, pa.int64()), pa.array(starts, pa.int64()), ids, pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(mask))], ["conv_id", "seq", "token_start", "ids", "mask"])

    rows = df.select(F.col("conv_id").cast("bigint"), F.col("turn").cast("bigint"), F.col("role").cast("string"), F.col("text").cast("string"))
    encoded = rows.mapInArrow(encode, "conv_id bigint, turn bigint, packed binary, begin bigint, end bigint, role string")
    ordered = encoded.repartition(width(df.sparkSession), "conv_id").sortWithinPartitions(F.col("conv_id").asc_nulls_first(), F.col("turn").asc_nulls_first(), "role", "packed")
    return ordered.select("conv_id", "packed", "begin", "end").mapInArrow(number, "conv_id bigint, seq bigint, token_start bigint, ids array<int>, mask array<boolean>")


def parse_turns(rows: list[np.ndarray], bounds: list[tuple[int, int]], tok: ChatTokenizer) -> list[tuple[str, str, str, int]]:
    """(role, text, masked text, rendered length) of each turn, from ids and the mask's bounds alone."""
    roles, texts, masked = [], [], []
    for ids, (begin, end) in zip(rows, bounds, strict=True):
        cut = int(np.flatnonzero(ids == tok.sep)[0])
        if ids[0] != tok.start or ids[-1] != tok.end:
            raise ValueError("a turn must begin and end with its marks")
        roles.append(tuple(ids[1:cut].tolist()))
        texts.append(ids[cut + 1 : -1].tolist())
        # the mask's ids are decoded on their own unless they are exactly the text's
        masked.append(None if (begin, end) == (cut + 1, len(ids) - 1) else ids[begin:end].tolist())
    out = []
    marks = sum(map(len, MARKS))
    names = dict(zip(names := list(dict.fromkeys(roles)), tok.decode([list(r) for r in names]), strict=True))
    for role, text, some in zip(roles, tok.decode(texts), masked, strict=True):
        plain, shown = unescape(text), names[role]
        loss = plain if some is None else unescape(tok.decode([some])[0]) if some else ""
        out.append((unescape(shown), plain, loss, marks + len(shown) + len(text)))
    return out


def render(ids: list[int], tok: ChatTokenizer) -> str:
    """The formatted text of a row of ids."""
    names, out, part = dict(zip((tok.start, tok.sep, tok.end), MARKS, strict=True)), [], []
    for i in [*ids, None]:
        if i is None or i in names:
            out += [*tok.decode([part]), names.get(i, "")]
            part = []
        else:
            part.append(i)
    return "".join(out)


def read_back(formatted: DataFrame, tokenizer: str, in_order: bool = False) -> DataFrame:
    """Digests of each conversation, rebuilt from the rows that format_chat gave, wherever and in whatever order they lie.

    `in_order` says that the rows come straight from format_chat, together and in order of seq, and spares a
    shuffle; rows that don't raise an error.
    """

    def packed(batches):
        """Ids to their width, the mask as (begin, end) of its one run."""
        kind = tokenizer_at(tokenizer).kind
        for whole in batches:
            for k in range(0, whole.num_rows, 512):
                batch = whole.slice(k, 512)
                ids, masks = batch.column(2), batch.column(3)
                offsets = np.asarray(ids.offsets).astype(np.int64)
                flat = np.asarray(ids.values)[offsets[0] : offsets[-1]].astype(kind).tobytes()
                bounds = (offsets - offsets[0]).tolist()
                rows = [flat[a * kind.itemsize : b * kind.itemsize] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
                on = masks.values.to_numpy(zero_copy_only=False)[offsets[0] : offsets[-1]].astype(bool)
                at, row = np.flatnonzero(on), np.repeat(np.arange(len(rows)), np.diff(offsets))
                held = np.bincount(row[at], minlength=len(rows))
                begin = np.zeros(len(rows), np.int64)
                first = at[np.concatenate([[True], np.diff(row[at]) > 0])] if len(at) else at
                begin[row[first]] = first - (offsets[:-1] - offsets[0])[row[first]]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(rows, pa.binary()), pa.array(begin), pa.array(begin + held)], ["conv_id", "seq", "packed", "begin", "end"])

    def digest(batches):
        tok = tokenizer_at(tokenizer)
        conv, state = None, None
        fields = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_tokens", "n_loss_tokens"]

        def emit():
            turns, loss = state["turns"].hexdigest(), state["loss"].hexdigest()
            return [conv, state["n"], turns, state["chars"], loss, state["formatted"], state["tokens"], state["masked"]]

        for batch in batches:
            done = []
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                ids = [np.frombuffer(x, tok.kind) for x in part.column(2).to_pylist()]
                bounds = list(zip(part.column(3).to_pylist(), part.column(4).to_pylist(), strict=True))
                for c, seq, i, (a, b), (role, text, loss, chars) in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), ids, bounds, parse_turns(ids, bounds, tok), strict=True):
                    if seq != (0 if state is None or c != conv else state["n"]):
                        raise ValueError("the turns of a conversation must lie together in order of seq")
                    if state is None or c != conv:
                        if state is not None:
                            done.append(emit())
                        conv, state = c, {"turns": hashlib.sha256(), "loss": hashlib.sha256(), "n": 0, "chars": 0, "formatted": 0, "tokens": 0, "masked": 0}
                    state["turns"].update(f"{role}\n{text}\n".encode())
                    state["loss"].update(loss.encode())
                    for name, v in (("n", 1), ("chars", len(loss)), ("formatted", chars), ("tokens", len(i)), ("masked", b - a)):
                        state[name] += v
            if done:
                yield pa.RecordBatch.from_pylist([dict(zip(fields, d, strict=True)) for d in done], schema=schema)
        if state is not None:
            yield pa.RecordBatch.from_pylist([dict(zip(fields, emit(), strict=True))], schema=schema)

    schema = pa.schema([(n, pa.string() if n.endswith("sha256") else pa.int64()) for n in ("conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_tokens", "n_loss_tokens")])
    rows = formatted.select("conv_id", "seq", "ids", "mask").mapInArrow(packed, "conv_id bigint, seq bigint, packed binary, begin bigint, end bigint")
    ordered = rows if in_order else rows.repartition(width(formatted.sparkSession), "conv_id").sortWithinPartitions(F.col("conv_id").asc_nulls_first(), "seq")
    return ordered.mapInArrow(digest, "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint, n_tokens bigint, n_loss_tokens bigint")
