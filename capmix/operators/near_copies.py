"""Near copies: MinHash bands name the candidates, the exact Jaccard similarity of shingle sets decides.

1. A text becomes the set of 64-bit hashes of its runs of `shingle` words; a shorter text is one shingle of
   all its words, a wordless one the empty set. Equal sets are one class.
2. Only classes meet, one representative each, where a band of MinHash values is equal. With 16 bands of
   four, a pair of similarity 0.8 shares no band with probability 0.0002, a closer pair less often. Of band values with
   exactly the same classes one is kept, so a set isn't sent once for each band that copies share.
3. Within a band value every pair of sizes that allow the threshold is compared by the sets themselves. A
   band value of more than `block_rows` classes is dealt by pairs of salted sub-blocks.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import few, release

SHINGLE, BANDS, ROWS, THRESHOLD = 5, 16, 4, 0.8
BLOCK_ROWS = 512
#: So many classes (one number each) are broadcast at most.
FEW_CLASSES = 1_000_000
_STEP = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _odd(n: int, seed: int) -> np.ndarray:
    return _mix(np.arange(1, n + 1, dtype=np.uint64) * _STEP + np.uint64(seed)) | np.uint64(1)


def shingle_set(text: bytes | None, shingle: int = SHINGLE) -> np.ndarray:
    """The sorted distinct hashes of a text's shingles; words are split by white space, A-Z lower-cased."""
    words = text.lower().split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(w) for w in words], np.uint64)
    take = min(shingle, len(words))
    run = np.full(len(words) - take + 1, take, np.uint64)
    for k in range(take):
        run = run * _STEP + hashes[k : k + len(run)]
    return np.unique(_mix(run))


def band_keys(own: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """One number for each band of MinHash values of a set that isn't empty."""
    factor, low = _odd(bands * rows, 1), None
    for k in range(0, len(own), 4096):
        part = (own[k : k + 4096, None] * factor).min(axis=0)
        low = part if low is None else np.minimum(low, part)
    low = _mix(low).reshape(bands, rows)
    return _mix((low * _odd(rows, 2)).sum(axis=1, dtype=np.uint64) + _odd(bands, 3))


def _texts(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return df.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("binary").alias("text"), F.xxhash64(text_col).alias("row_key"))


def _class(own: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(own.tobytes(), 7) - (1 << 63)


def sketches(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, mark: Callable[[np.ndarray], int] | None = None) -> DataFrame:
    """(id, row_key, cls, size, keys, mark) of every row: the hash of its text, its class, the size of its set, its band
    values, and a number that `mark` makes of its set (0 without)."""

    def work(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                batch = whole.slice(at, 500)
                sets = [shingle_set(t, shingle) for t in batch.column(1).to_pylist()]
                keys = [band_keys(s, bands, rows).view(np.int64) if len(s) else [] for s in sets]
                marks = np.array([mark(s) if mark else 0 for s in sets], np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([_class(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int32()), pa.array(keys, pa.list_(pa.int64())), pa.array(marks)], ["id", "row_key", "cls", "size", "keys", "mark"])
            release()

    return _texts(df, id_col, text_col).mapInArrow(work, "id bigint, row_key bigint, cls bigint, size int, keys array<bigint>, mark bigint")


def _sets(df: DataFrame, text_col: str, shingle: int) -> DataFrame:
    """(cls, hashes) of every class, once for each task that has it; the sorted set as bytes."""

    def work(batches):
        seen: set[int] = set()
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                fresh = {}
                for text in whole.slice(at, 500).column(0).to_pylist():
                    own = shingle_set(text, shingle)
                    if (cls := _class(own)) not in seen:
                        seen.add(cls)
                        fresh[cls] = own.tobytes()
                yield pa.RecordBatch.from_arrays([pa.array(list(fresh), pa.int64()), pa.array(list(fresh.values()), pa.binary())], ["cls", "hashes"])
            release()

    return df.select(F.col(text_col).cast("binary").alias("text")).mapInArrow(work, "cls bigint, hashes binary")


def similar(sets: list[np.ndarray], side: np.ndarray | None, threshold: float, spanning: bool) -> list[tuple[int, int, float]]:
    """(i, j, jaccard) of the pairs that reach the threshold, among all or between the two sides.

    With `spanning` a pair whose ends are linked already isn't compared.
    """
    size = np.array([len(s) for s in sets])
    order = np.argsort(size, kind="stable")
    size, tree, out = size[order], np.arange(len(sets)), []
    for x in range(len(order)):
        others = np.arange(x + 1, np.searchsorted(size, size[x] / threshold + 1e-9, side="right"))
        if side is not None:
            others = others[side[order[others]] != side[order[x]]]
        if spanning:
            others = others[tree[others] != tree[x]]
        for y in others.tolist():
            if spanning and tree[x] == tree[y]:
                continue
            both = len(np.intersect1d(sets[order[x]], sets[order[y]], assume_unique=True))
            jaccard = both / (size[x] + size[y] - both)
            if jaccard >= threshold:
                out.append((int(order[x]), int(order[y]), float(jaccard)))
                tree[tree == tree[y]] = tree[x]
    return out


def pairs(df: DataFrame, rows: DataFrame, keep: Callable[[DataFrame, str], DataFrame], text_col: str = "text", shingle: int = SHINGLE, threshold: float = THRESHOLD, spanning: bool = False, block_rows: int = BLOCK_ROWS, *, also: DataFrame | None = None) -> DataFrame:
    """(a, b, jaccard): pairs of classes whose sets reach the threshold; `rows` are the sketches of df.

    With `spanning`, of each block only as many pairs as join what it links. `keep` holds a table that is read twice.
    `also` names further candidates: (cls, band), classes with a common value are compared.
    """
    classes = rows.groupBy("cls").agg(F.first("keys").alias("keys"))
    keyed = classes.select("cls", F.explode("keys").alias("band"))
    keyed = keyed if also is None else keyed.union(also.select("cls", "band")).distinct()
    # band values with the same classes (most copies share many) name the same pairs: one of them is kept
    alike = keyed.groupBy("band").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("cls")).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "cls")).alias("y"))
    shared = alike.filter("n > 1").groupBy("n", "x", "y").agg(F.min("band").alias("band")).select("band", F.ceil(F.col("n") / block_rows).cast("int").alias("subs"))
    members = keep(keyed.join(shared, "band"), "members")
    sub = F.pmod(F.xxhash64("cls"), F.col("subs")).cast("int")
    dealt = members.withColumn("sub", sub).select("cls", "band", "sub", F.explode(F.sequence(F.lit(0), F.col("subs") - 1)).alias("other"))
    low, high = F.least("sub", "other"), F.greatest("sub", "other")
    dealt = dealt.select("cls", F.xxhash64("band", low, high).alias("block"), (F.col("sub") != F.col("other")).alias("mixed"), (F.col("sub") < F.col("other")).alias("first"))
    wanted = members.select("cls").distinct()
    wanted = F.broadcast(wanted) if few(wanted, FEW_CLASSES) else wanted
    sets = keep(_sets(df, text_col, shingle).join(wanted, "cls", "left_semi").dropDuplicates(["cls"]), "sets")
    kinds = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("jaccard", pa.float64())])

    def block(held: pa.Table) -> pa.RecordBatch:
        cls = held.column("cls").to_numpy()
        own = [np.frombuffer(b, np.uint64) for b in held.column("hashes").to_pylist()]
        side = held.column("first").to_numpy() if held.column("mixed")[0].as_py() else None
        found = similar(own, side, threshold, spanning)
        ends = [(min(cls[i], cls[j]), max(cls[i], cls[j]), v) for i, j, v in found]
        return pa.RecordBatch.from_arrays([pa.array([e[k] for e in ends], t.type) for k, t in enumerate(kinds)], schema=kinds)

    def work(batches):
        release()
        held: list[pa.RecordBatch] = []
        for batch in batches:
            keys = batch.column(0).to_numpy()
            edges = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])).tolist() + [len(keys)] if len(keys) else []
            for s, e in zip(edges, edges[1:]):
                if held and held[-1].column(0)[0].as_py() != int(keys[s]):
                    yield block(pa.Table.from_batches(held))
                    held = []
                held.append(batch.slice(s, e - s))
        if held:
            yield block(pa.Table.from_batches(held))

    met = dealt.join(sets, "cls").select("block", "cls", "mixed", "first", "hashes")
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = met.repartition(n, "block").sortWithinPartitions("block").mapInArrow(work, "a bigint, b bigint, jaccard double")
    return found.dropDuplicates(["a", "b"])
