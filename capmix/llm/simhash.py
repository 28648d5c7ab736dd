"""SimHash near-duplicates: tiled exact comparison with numpy exclusive-or and bit counts.

1. Every whole text gets a 64-bit fingerprint: XXH64 (seed 42) of each word shingle, repeats included;
   a bit is set if more than half of the hashes have it. No shingle, fingerprint zero.
2. Equal fingerprints are one class. Only distinct fingerprints are compared.
3. Two fingerprints within `radius` bits agree under one of the masks of `band_masks`, so only fingerprints with a
   common masked value meet; no pair is lost, and masks get longer as there are more fingerprints. Within such a
   block, rows lie in order of their bit counts and are compared in tiles of numpy arrays by exclusive-or and bit counts;
   tiles, and in short blocks pairs, whose counts differ beyond the radius are skipped. A block larger than
   `block_rows` is dealt to tasks by pairs of sub-blocks instead (each of one bit count and bounded size), again only
   for counts within the radius.
4. What a task links becomes a spanning forest (at most one edge for each row it has), and the forests
   are joined by connected components on the cluster.

Defined cases: null and wordless texts have fingerprint zero, linked like any other; fewer words than a
shingle has: one shingle of them all; null ids keep their rows and never become a component's id unless
all its ids are null; repeated rows all stay; an empty table gives no rows.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, small, width
from .components import components
from .words import SPACED

BITS = 64
TILE = 2048
BLOCK_ROWS = 16_384
#: Runs of so many rows at most are compared together.
SHORT_RUN = 64
_TABLE = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in more than half of 64-bit hashes, unsigned; 0 without any."""
    octets = hashes.view(np.uint8).reshape(-1, 8)  # little endian: octet k holds bits 8k..8k+7
    out = 0
    for k in range(8):
        ones = np.bincount(octets[:, k], minlength=256) @ _TABLE
        for bit in np.flatnonzero(2 * ones > len(hashes)).tolist():
            out |= 1 << (8 * k + bit)
    return out


def fingerprint(text: bytes | None, shingle: int = 3) -> int:
    """The SimHash of one text, unsigned."""
    words = text.translate(SPACED).split() if text else []
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= shingle:
        return majority(np.array([xxhash.xxh64_intdigest(line, 42)], np.uint64))
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    starts = (ends - sizes)[: len(words) - shingle + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return majority(np.array([digest(line[a:b], 42) for a, b in zip(starts, ends[shingle - 1 :].tolist(), strict=True)], np.uint64))


def fingerprints(df: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp bigint: the fingerprint as a signed number) for every row."""

    def work(batches):
        for batch in small(batches):
            fps = np.array([fingerprint(t, shingle) for t in batch.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64())], ["id", "fp"])

    return df.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("binary").alias("text")).mapInArrow(work, "id bigint, fp bigint")


class _Forest:
    """Union-find over positions; yields an edge only where it joins two trees."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        if x == y:
            return False
        self.up[max(x, y)] = min(x, y)
        return True


def tiled_links(left: np.ndarray, right: np.ndarray | None, radius: int, tile: int = TILE) -> list[tuple[int, int]]:
    """A spanning forest of the pairs within `radius` bits among `left`, or between left and right.

    Positions in right count on from len(left). Both arrays must be in order of their bit counts.
    """
    same = right is None
    right = left if same else right
    base = 0 if same else len(left)
    forest, out = _Forest(len(left) + (0 if same else len(right))), []
    lc, rc = np.bitwise_count(left).astype(np.int64), np.bitwise_count(right).astype(np.int64)
    for i in range(0, len(left), tile):
        a, first, last = left[i : i + tile], lc[i], lc[min(i + tile, len(left)) - 1]
        for j in range(i if same else 0, len(right), tile):
            if rc[j] - last > radius or first - rc[min(j + tile, len(right)) - 1] > radius:
                continue
            b = right[j : j + tile]
            near = np.bitwise_count(a[:, None] ^ b[None, :]) <= radius
            if same and i == j:
                near = np.triu(near, 1)
            for x, y in np.argwhere(near).tolist():
                if forest.join(i + x, base + j + y):
                    out.append((i + x, base + j + y))
    return out


def _small_blocks(keys: np.ndarray, fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal keys, each in order of bit counts: tiles, for many short runs one diagonal at a time.

    On a diagonal rows are compared with those d places on, in all short runs at once; pairs whose counts differ
    beyond the radius are left out, and later diagonals only hold pairs that differ more.
    """
    ones = np.bitwise_count(fps).astype(np.int64)
    order = np.lexsort((ones, keys))
    keys, fps, ones = keys[order], fps[order], ones[order]
    edge = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    sizes = np.diff(np.concatenate([edge, [len(keys)]]))
    a, b = [], []
    x = np.flatnonzero(np.repeat(sizes, sizes) <= SHORT_RUN)
    for d in range(1, SHORT_RUN):
        x = x[x + d < len(keys)]
        x = x[(keys[x] == keys[x + d]) & (ones[x + d] - ones[x] <= radius)]
        if not len(x):
            break
        y = x[np.bitwise_count(fps[x] ^ fps[x + d]) <= radius]
        a.append(fps[y])
        b.append(fps[y + d])
    for at, n in zip(edge[sizes > SHORT_RUN].tolist(), sizes[sizes > SHORT_RUN].tolist(), strict=True):
        own = fps[at : at + n]
        if pairs := np.array(tiled_links(own, None, radius), np.int64).reshape(-1, 2).tolist():
            i, j = zip(*pairs, strict=True)
            a.append(own[list(i)])
            b.append(own[list(j)])
    empty = np.empty(0, np.uint64)
    return np.concatenate([empty, *a]), np.concatenate([empty, *b])


def band_masks(n: int, radius: int) -> list[int]:
    """Masks of bits such that any two numbers within `radius` bits agree under one of them.

    64 bits are cut into m parts, of which a pair can differ in `radius`; every choice of the other m - radius is a mask. More
    fingerprints take more parts: longer masks, so that a block of unlike fingerprints stays at a few rows.
    """
    m = radius + 1
    while m < radius + 8 and n >> (BITS * (m - radius) // m) > 4:
        m += 1
    cuts = [BITS * k // m for k in range(m + 1)]
    parts = [(1 << cuts[k + 1]) - (1 << cuts[k]) for k in range(m)]
    return [sum(c) for c in combinations(parts, m - radius)]


def links(distinct: DataFrame, radius: int = 2, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(a, b): spanning links between distinct fingerprints (column fp) within `radius` bits."""
    masks = [m - (1 << 64) if m >> 63 else m for m in band_masks(distinct.count(), radius)]
    keys = F.array(*[F.struct(F.lit(k).alias("band"), F.col("fp").bitwiseAND(F.lit(m).cast("bigint")).alias("value")) for k, m in enumerate(masks)])
    rows = distinct.select("fp", F.explode(keys).alias("v")).select("fp", F.xxhash64("v.band", "v.value").alias("block"), F.bit_count("fp").alias("ones"))
    # How many rows a block and bit count has, counted before the shuffle; only large blocks are kept.
    counts = rows.groupBy("block", "ones").count()
    large = counts.groupBy("block").agg(F.sum("count").alias("n")).filter(F.col("n") > block_rows).select("block")
    large = materialise(counts.join(large, "block").select("block", "ones", F.ceil(F.col("count") / block_rows).cast("int").alias("subs")), "blocks")
    out_schema = "a bigint, b bigint"
    kinds = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def compare(batches):
        held_k, held_f = np.empty(0, np.int64), np.empty(0, np.uint64)
        for batch in batches:
            k = np.concatenate([held_k, batch.column(0).to_numpy()])
            f = np.concatenate([held_f, batch.column(1).to_numpy().view(np.uint64)])
            cut = int(np.searchsorted(k, k[-1])) if len(k) else 0  # the last block may go on
            a, b = _small_blocks(k[:cut], f[:cut], radius) if cut else ([], [])
            held_k, held_f = k[cut:], f[cut:]
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], schema=kinds)
        if len(held_k):
            a, b = _small_blocks(held_k, held_f, radius)
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], schema=kinds)

    n = width(distinct.sparkSession)
    small = rows.join(large.select("block").distinct(), "block", "left_anti") if large.limit(1).count() else rows
    found = small.select("block", "fp").repartition(n, "block").sortWithinPartitions("block", "fp").mapInArrow(compare, out_schema)
    if not large.limit(1).count():
        return found

    # Large blocks: each row goes to the pairs of sub-blocks that its own may link with. Their number
    # is bounded by the number of rows over block_rows, so `large` is far smaller than the input.
    sub = rows.join(large, ["block", "ones"]).withColumn("sub", F.pmod(F.xxhash64("fp"), F.col("subs")).cast("int"))
    mine = F.struct(F.col("ones").alias("ones"), F.col("sub").alias("sub"))
    other = large.select("block", F.col("ones").alias("ones2"), F.explode(F.sequence(F.lit(0), F.col("subs") - 1)).alias("sub2"))
    theirs = F.struct(F.col("ones2").alias("ones"), F.col("sub2").alias("sub"))
    pairs = sub.join(other, "block").filter(F.abs(F.col("ones") - F.col("ones2")) <= radius)
    pairs = pairs.select("block", F.least(mine, theirs).alias("x"), F.greatest(mine, theirs).alias("y"), (mine == F.least(mine, theirs)).alias("first"), "fp")

    def pair_links(table: pa.Table) -> pa.Table:
        fps, first = table.column("fp").to_numpy().view(np.uint64), table.column("first").to_numpy()
        one = table.slice(0, 1).to_pylist()[0]
        if one["x"] == one["y"]:
            left, right = np.unique(fps), None
        else:
            left, right = np.unique(fps[first]), np.unique(fps[~first])
        both = left if right is None else np.concatenate([left, right])
        got = np.array(tiled_links(left, right, radius), np.int64).reshape(-1, 2)
        return pa.Table.from_arrays([pa.array(both[got[:, 0]].view(np.int64)), pa.array(both[got[:, 1]].view(np.int64))], schema=kinds)

    return found.union(pairs.groupBy("block", "x", "y").applyInArrow(pair_links, out_schema))


def near_duplicates(df: DataFrame, radius: int = 2, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(id, fp, component_id) of every row; component_id is the smallest id reachable over links."""
    rows = materialise(fingerprints(df, shingle, id_col, text_col), "fingerprints")
    least = materialise(rows.groupBy("fp").agg(F.min("id").alias("least")), "classes")
    roots = materialise(components(links(least.select("fp"), radius, block_rows)), "roots")
    linked = least.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    merged = linked.groupBy("root").agg(F.min("least").alias("component_id"))
    classes = linked.select("fp", "root").join(merged, "root").select("fp", "component_id")
    return rows.join(classes, "fp").select("id", "fp", "component_id")
