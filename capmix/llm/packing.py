"""Conflict-constrained best-fit packing of documents into bins of fixed capacity.

Two documents of one source, or of one duplicate cluster, must not share a bin. Documents are placed
largest first. Open bins lie in order of their residual capacity; each carries a bitmap of the
sources and duplicate clusters that it holds. A document starts at the least residual that holds it and
the successor search goes on through larger ones until the first bin without a conflict: the tightest
compatible bin. Without any, it opens a new one.

A document longer than the capacity fills bins of its own; what remains of it is placed like any other.

Rows are dealt by their hash to packing groups of about `group_rows` rows, each packed on its own, so
memory and time of a task don't grow with the input, and a hot source, cluster or row is spread evenly. Only ids,
sizes, and hashes of source and cluster are shuffled. A piece sees the bins of its own group only, which
costs a few bins: larger groups come closer to one best-fit run over everything.

Sizes are white-space words of the text plus one for the end mark, or a given column. Duplicate clusters are equal
texts, or a given column.

Defined cases: null text is a document of size one; a null source conflicts with nothing; null ids are
dealt and kept like others; repeated rows are all packed (never together, being equal texts); an empty
table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import width

CAPACITY, GROUP_ROWS = 4096, 8192
PLACED = "doc_id bigint, piece int, piece_start bigint, size bigint, bin_group int, bin int, bin_offset bigint"
_PLACED = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("piece_start", pa.int64()), ("size", pa.int64()), ("bin_group", pa.int32()), ("bin", pa.int32()), ("bin_offset", pa.int64())])
_SEARCH = 256


class Bins:
    """Open bins in order of residual (then of age), with conflict bitmaps."""

    def __init__(self, capacity: int, bits: int, room: int = 1024):
        self.capacity = capacity
        self.count = 0
        self.residual = np.zeros(room, np.int64)  # ascending, of open bins
        self.order = np.zeros(room, np.int64)  # the bin at each place of residual
        self.open = 0
        self.words = max(1, -(-bits // 64))
        self.bitmap = np.zeros((room, self.words), np.uint64)

    def _grow(self) -> None:
        if self.count == len(self.bitmap):
            self.bitmap = np.concatenate([self.bitmap, np.zeros_like(self.bitmap)])
        if self.open + 1 >= len(self.residual):
            self.residual, self.order = (np.concatenate([x, np.zeros_like(x)]) for x in (self.residual, self.order))

    def _insert(self, residual: int, which: int) -> None:
        at = int(np.searchsorted(self.residual[: self.open], residual, side="right"))
        for x, v in ((self.residual, residual), (self.order, which)):
            x[at + 1 : self.open + 1] = x[at : self.open].copy()
            x[at] = v
        self.open += 1

    def find(self, size: int, bits: list[int]) -> int:
        """The place of the tightest open bin that holds `size` and has none of `bits`; -1 if none."""
        at = int(np.searchsorted(self.residual[: self.open], size))
        while at < self.open:
            some = self.order[at : min(at + _SEARCH, self.open)]
            clash = np.zeros(len(some), np.uint64)
            for b in bits:
                clash |= self.bitmap[some, b >> 6] & np.uint64(1 << (b & 63))
            free = np.flatnonzero(clash == 0)
            if len(free):
                return at + int(free[0])
            at += _SEARCH
        return -1

    def place(self, size: int, bits: list[int]) -> tuple[int, int]:
        """Put one piece; gives (bin, offset in it)."""
        at = self.find(size, bits)
        if at < 0:
            self._grow()
            which, left = self.count, self.capacity
            self.count += 1
        else:
            which, left = int(self.order[at]), int(self.residual[at])
            for x in (self.residual, self.order):
                x[at : self.open - 1] = x[at + 1 : self.open].copy()
            self.open -= 1
        for b in bits:
            self.bitmap[which, b >> 6] |= np.uint64(1 << (b & 63))
        if left > size:
            self._grow()
            self._insert(left - size, which)
        return which, self.capacity - left


def pack_group(ids, sizes, sources, clusters, capacity: int) -> list[tuple[int, int, int, int, int, int]]:
    """Pack one group: (row, piece, piece_start, size, bin, offset) for every piece.

    sources and clusters are hashes; None conflicts with nothing.
    """
    bit: dict[tuple[str, int], int] = {}
    for kind, values in (("s", sources), ("c", clusters)):
        seen: set = set()
        for v in values:
            if v is not None and v in seen:
                bit.setdefault((kind, v), len(bit))  # what occurs once can't conflict
            seen.add(v)
    bins, out, rest = Bins(capacity, len(bit)), [], []
    full = []
    for row, size in enumerate(sizes):
        whole, left = divmod(size, capacity)
        full += [(row, p) for p in range(whole)]
        if left:
            rest.append((-left, -(2**63) if ids[row] is None else ids[row], row, whole))
    for left, _, row, piece in sorted(rest):
        bits = [bit[k] for k in (("s", sources[row]), ("c", clusters[row])) if k in bit]
        which, at = bins.place(-left, bits)
        out.append((row, piece, piece * capacity, -left, which, at))
    for k, (row, piece) in enumerate(full):
        out.append((row, piece, piece * capacity, capacity, bins.count + k, 0))
    return out


def pack(df: DataFrame, capacity: int = CAPACITY, group_rows: int = GROUP_ROWS, id_col: str = "doc_id", text_col: str = "text", source_col: str | None = "source", cluster_col: str | None = None, size_col: str | None = None) -> DataFrame:
    """Where each document (or piece of one) lies: doc_id, piece, piece_start, size, bin_group, bin, bin_offset.

    A bin is named by (bin_group, bin). With cluster_col None equal texts are a cluster.
    """
    spark = df.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    size = F.col(size_col).cast("bigint") if size_col else F.size(F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")) + 1
    narrow = df.select(
        F.col(id_col).cast("bigint").alias("doc_id"),
        F.greatest(F.coalesce(size, F.lit(1)), F.lit(1)).cast("bigint").alias("size"),
        (F.when(F.col(source_col).isNotNull(), F.xxhash64(source_col)) if source_col else F.lit(None).cast("bigint")).alias("source"),
        (F.xxhash64(cluster_col) if cluster_col else F.xxhash64(text)).alias("cluster"),
    )
    groups = df.select(F.lit(1)).count() // group_rows + 1
    # the group follows from the row alone, so a repeated task agrees; identical rows are counted off before the shuffle and
    # then dealt by their number, too, so that they don't meet in one group
    same = narrow.groupBy("doc_id", "size", "source", "cluster").agg(F.count("*").alias("times"))
    each = same.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("times")))).drop("times")
    dealt = each.withColumn("bin_group", F.pmod(F.xxhash64("doc_id", "size", "cluster", "copy"), F.lit(groups)).cast("int")).drop("copy")

    def work(batches):
        held, group = [], None

        def flush():
            ids, sizes, sources, clusters = ([v for t in held for v in t.column(k).to_pylist()] for k in range(4))
            rows = pack_group(ids, sizes, sources, clusters, capacity)
            cols = list(zip(*rows, strict=True))
            return pa.RecordBatch.from_arrays([pa.array([ids[r] for r in cols[0]], pa.int64()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64()), pa.array([group] * len(rows), pa.int32()), pa.array(cols[4], pa.int32()), pa.array(cols[5], pa.int64())], schema=_PLACED)

        for batch in batches:
            groups_here = batch.column(4).to_numpy()
            cuts = np.flatnonzero(np.concatenate([[True], groups_here[1:] != groups_here[:-1]])).tolist() if len(groups_here) else []
            for a, b in zip(cuts, [*cuts[1:], len(groups_here)], strict=True):
                if held and groups_here[a] != group:
                    yield flush()
                    held = []
                group = int(groups_here[a])
                held.append(batch.slice(a, b - a))
        if held:
            yield flush()

    ordered = dealt.repartition(max(groups, width(spark)), "bin_group").sortWithinPartitions("bin_group", F.desc("size"), "doc_id", "cluster")
    return ordered.mapInArrow(work, PLACED)
