"""Approximate nearest neighbours by inner product: inverted file, product-quantised residuals,
asymmetric distance tables, exact reranking; bounds say which lists and entries can't be among the nearest.

Index: coarse centroids and the sub-space codebooks are fitted on at most `sample_rows` vectors (least
hash of their components); every row is indexed. Rows with equal vectors are one entry that names
its `top + 1` smallest ids: no further one can be among anybody's nearest, since ties go to smaller ids.

Search: a query's `top`-th best score within the sample is its floor. It visits each list whose bound (the centroid's
score, and the query's length times the list's radius over all rows) reaches that: few where vectors cluster, most where they
are spread evenly. Lists are cut into, or share, blocks of about `block_rows` entries. An entry is shuffled once, to its
block; a query goes to the blocks of its lists and streams past the block, which alone is held. Lookup tables of a batch of
queries' inner products with all codewords rank a block's entries (asymmetric: queries aren't quantised); the best `shortlist`
are scored exactly on the original vectors in double precision and raise the floor. Of the other entries those are scored
too whose code's score, and the query's length times the length of what the code leaves out, reach the floor. The block's
`top` best at or above the floor are sent on. So the result is exact on any rows. With `recall` under 1 it is approximate: a query visits as
many lists as hold that part of the nearest neighbours within the sample, and scores shortlists alone.

Scores are sums in component order, so equal vectors have equal scores and ties go to smaller ids.

Defined cases: vectors that are null, empty, zero, of another dimension than most of the sample, or hold null
or non-finite components take no part, as queries or candidates; ids that repeat keep one entry for each
distinct vector; null ids take no part; fewer candidates than `top`: all that were found; no rows, no
output; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import materialise, width

SAMPLE_ROWS, BLOCK_ROWS, QUERY_ROWS = 8_192, 4_096, 128
#: Rounding of a product in any order of summation, as a part of both lengths, is less.
SLACK = 1e-11
FOUND = "query_id bigint, vec_id bigint, score double"


def exact_scores(queries: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Inner products along the last axis in double precision, summed in component order."""
    total = np.zeros(np.broadcast_shapes(queries.shape, vectors.shape)[:-1])
    for k in range(queries.shape[-1]):
        total += queries[..., k] * vectors[..., k]
    return total


def lengths(x: np.ndarray) -> np.ndarray:
    return np.sqrt((x**2).sum(axis=-1))


def k_means(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    """Lloyd's centroids; an empty cluster keeps its old centre."""
    rng = np.random.default_rng(seed)
    centres = x[rng.permutation(len(x))[: min(k, len(x))]].copy()
    for _ in range(rounds):
        near = (x @ centres.T - 0.5 * (centres**2).sum(axis=1)).argmax(axis=1)
        sums = np.zeros_like(centres)
        np.add.at(sums, near, x)
        n = np.bincount(near, minlength=len(centres))
        centres[n > 0] = sums[n > 0] / n[n > 0, None]
    return centres


@dataclass
class Index:
    """What every task needs: centroids and codebooks, and how many lists a query visits."""

    centroids: np.ndarray  # lists x dimensions
    codebooks: np.ndarray  # parts x words x part dimensions
    probes: int | None  # None: as many as the bounds ask for
    sample: np.ndarray  # distinct vectors, rows x dimensions

    def assign(self, x: np.ndarray) -> np.ndarray:
        return (x @ self.centroids.T - 0.5 * (self.centroids**2).sum(axis=1)).argmax(axis=1)

    def encode(self, x: np.ndarray, lists: np.ndarray) -> np.ndarray:
        parts, _, d = self.codebooks.shape
        rest = np.zeros((len(x), parts * d))
        rest[:, : x.shape[1]] = x - self.centroids[lists]
        out = np.empty((len(x), parts), np.uint8)
        for p in range(parts):
            book = self.codebooks[p]
            out[:, p] = (rest[:, p * d : (p + 1) * d] @ book.T - 0.5 * (book**2).sum(axis=1)).argmax(axis=1)
        return out

    def left_out(self, x: np.ndarray, lists: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Lengths of what lists and codes leave out of x."""
        parts, words, d = self.codebooks.shape
        known = self.codebooks[np.arange(parts), codes].reshape(len(x), parts * d)[:, : x.shape[1]]
        return lengths(x - self.centroids[lists] - known)

    def floors(self, queries: np.ndarray, top: int) -> np.ndarray:
        """For each query a score that its `top` nearest reach: top + 1 of the sample do, one of which may be its own."""
        if len(self.sample) <= top:
            return np.full(len(queries), -np.inf)
        scores = queries @ self.sample.T
        return np.partition(scores, -top - 1, axis=1)[:, -top - 1] - SLACK * lengths(queries) * lengths(self.sample).max()

    def tables(self, queries: np.ndarray) -> np.ndarray:
        """Asymmetric tables: queries x parts x words inner products."""
        parts, _, d = self.codebooks.shape
        padded = np.zeros((len(queries), parts * d))
        padded[:, : queries.shape[1]] = queries
        return np.einsum("qpd,pwd->qpw", padded.reshape(len(queries), parts, d), self.codebooks)


def valid_vectors(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, v) of the rows that take part, whatever their dimension; v keeps floats as floats."""
    kind = "array<float>" if df.schema[vector_col].dataType == T.ArrayType(T.FloatType()) else "array<double>"
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return df.select(F.col(id_col).cast("bigint").alias("vec_id"), F.col(vector_col).cast(kind).alias("v")).filter(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & (F.size("v") > 0)).filter(finite & F.exists("v", lambda x: x != 0))


def probes_for(x: np.ndarray, centroids: np.ndarray, recall: float, top: int, asked: int = 512) -> int:
    """How many lists hold `recall` of the `top` nearest among the rows of x, over `asked` of them."""
    some = x[:asked]
    scores = some @ x.T
    scores[np.arange(len(some)), np.arange(len(some))] = -np.inf
    k = min(top, len(x) - 1)
    if k < 1:
        return len(centroids)
    near = np.argpartition(-scores, k - 1, axis=1)[:, :k]
    place = np.empty((len(some), len(centroids)), np.int64)
    np.put_along_axis(place, np.argsort(-(some @ centroids.T), axis=1, kind="stable"), np.arange(len(centroids))[None, :], axis=1)
    lists = (x @ centroids.T - 0.5 * (centroids**2).sum(axis=1)).argmax(axis=1)
    ranks = np.take_along_axis(place, lists[near], axis=1)
    return int(np.quantile(ranks, recall, method="higher")) + 1


def fit(vectors: DataFrame, lists: int | None, recall: float, parts: int, sample_rows: int, top: int, rounds: int = 8, seed: int = 7) -> tuple[Index | None, int]:
    """Fit centroids and codebooks on a bounded sample of (vec_id, v); gives the index and the dimension."""
    n = vectors.count()
    rows = vectors.select("vec_id", "v").orderBy(F.xxhash64("v"), "vec_id").limit(sample_rows).toArrow()
    got = rows.column("v").to_pylist()
    if not got:
        return None, 0
    dims = np.bincount([len(v) for v in got])
    dim = int(dims.argmax())
    x = np.array([v for v in got if len(v) == dim], float)
    lists = lists or max(1, min(4096, int(np.sqrt(n) / 4)))
    centroids = k_means(x, lists, rounds, seed)
    index = Index(centroids, np.zeros((0, 0, 0)), probes_for(x, centroids, recall, top) if recall < 1 else None, x)
    d = -(-dim // parts)
    rest = np.zeros((len(x), parts * d))
    rest[:, :dim] = x - centroids[index.assign(x)]
    index.codebooks = np.stack([_padded(k_means(rest[:, p * d : (p + 1) * d], 256, rounds, seed + 1 + p)) for p in range(parts)])
    return index, dim


def _padded(book: np.ndarray) -> np.ndarray:
    return book if len(book) == 256 else np.concatenate([book, np.repeat(book[:1], 256 - len(book), axis=0)])


def shelve(sizes: dict[int, int], block_rows: int) -> tuple[dict[int, int], dict[int, int]]:
    """For each list its first block and its number of blocks: short lists share one, long ones are cut."""
    first, parts, block, room = {}, {}, 0, block_rows
    for c, n in sorted(sizes.items()):
        parts[c] = -(-n // block_rows)
        if parts[c] > 1 or n > room:
            block, room = block + (room < block_rows), block_rows
        first[c] = block
        if parts[c] > 1:
            block += parts[c]
        else:
            room -= n
    return first, parts


@dataclass
class Block:
    """Entries of a block: vectors, codes, lists, lengths of what the codes leave out, lengths."""

    x: np.ndarray
    codes: np.ndarray
    lists: np.ndarray
    rest: np.ndarray
    size: np.ndarray


def nearest_in_block(block: Block, index: Index, q: np.ndarray, wanted: np.ndarray, floor: np.ndarray, top: int, shortlist: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, entry, exact score): the best of a block for each row of q; wanted: queries x lists, those it visits.

    top + 1 entries (a query's own may be one), and all that tie with the last of them, none under the query's floor.
    """
    x, exact = block.x, index.probes is None
    tables = index.tables(q)
    near = np.where(wanted, q @ index.centroids.T, -np.inf)[:, block.lists]
    for p in range(block.codes.shape[1]):
        near += tables[:, p].take(block.codes[:, p], axis=1)
    take = min(shortlist, len(x))
    short = np.argpartition(-near, take - 1, axis=1)[:, :take]
    score = exact_scores(q[:, None, :], x[short])
    seen = np.isfinite(np.take_along_axis(near, short, axis=1))
    score[~seen] = -np.inf
    least = np.maximum(floor, -np.partition(-score, top, axis=1)[:, top]) if take > top + 1 else floor
    row, at = np.nonzero((score >= least[:, None]) & (score > -np.inf))
    which, found = short[row, at], score[row, at]
    if exact and take < len(x):
        long = lengths(q)
        np.put_along_axis(near, short, -np.inf, axis=1)
        near += long[:, None] * (block.rest + SLACK * block.size)
        open_ = (near >= least[:, None]) & (near > -np.inf)
        more = np.flatnonzero(open_.any(axis=0))
        about = q @ x[more].T
        row2, at2 = np.nonzero(open_[:, more] & (about >= least[:, None] - SLACK * long[:, None] * block.size[more]))
        found2 = np.concatenate([np.zeros(0), *(exact_scores(q[row2[k : k + 65_536]], x[more[at2[k : k + 65_536]]]) for k in range(0, len(row2), 65_536))])
        row, which, found = np.concatenate([row, row2]), np.concatenate([which, more[at2]]), np.concatenate([found, found2])
    order = np.lexsort((-found, row))
    row, which, found = row[order], which[order], found[order]
    begin = np.searchsorted(row, np.arange(len(q) + 1))
    last = np.array([found[a + top] if b - a > top else -np.inf for a, b in zip(begin[:-1], begin[1:], strict=True)])
    kept = found >= np.maximum(last, floor)[row]
    return row[kept], which[kept], found[kept]


def search(df: DataFrame, queries: DataFrame, top: int = 20, lists: int | None = None, recall: float = 1.0, parts: int = 16, shortlist: int = 96, sample_rows: int = SAMPLE_ROWS, id_col: str = "vec_id", vector_col: str = "embedding", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): the nearest found of each row of `queries` among all rows of df.

    A query's own id is no candidate.
    """
    spark = df.sparkSession
    empty = spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    rows = valid_vectors(df, id_col, vector_col)
    # the few smallest ids of each distinct vector; counted off before the shuffle, which the aggregate shares
    smallest = Window.partitionBy("v").orderBy("vec_id")
    kept = rows.withColumn("r", F.dense_rank().over(smallest)).filter(F.col("r") <= top + 1)
    entries = materialise(kept.groupBy("v").agg(F.array_sort(F.collect_set("vec_id")).alias("ids")), "vectors")
    index, dim = fit(entries.select(F.element_at("ids", 1).alias("vec_id"), "v"), lists, recall, parts, sample_rows, top)
    if index is None:
        return empty
    entries = entries.filter(F.size("v") == dim)
    asked = valid_vectors(queries, id_col, vector_col).filter(F.size("v") == dim).distinct()
    element = entries.schema["v"].dataType.simpleString()

    def matrix(column) -> np.ndarray:
        return np.asarray(column.flatten()).reshape(-1, dim)

    def assigned(batches):
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column(0)).astype(float)
                where = index.assign(x)
                yield pa.RecordBatch.from_arrays([pa.array(where.astype(np.int32)), pa.array(lengths(x - index.centroids[where]))], ["list", "far"])

    found = entries.select("v").mapInArrow(assigned, "list int, far double").groupBy("list").agg(F.count("*").alias("n"), F.max("far").alias("far")).collect()  # a row for each list
    sizes = {r["list"]: r["n"] for r in found}
    radius = np.full(len(index.centroids), -np.inf)
    for r in found:
        radius[r["list"]] = r["far"]
    reach = radius + SLACK * (lengths(index.centroids) + np.maximum(radius, 0))
    first_block, parts_of = shelve(sizes, block_rows)
    sent = "block int, query_id bigint, ids array<bigint>, v " + element + ", lists array<int>, code binary, floor double"

    names = ["block", "query_id", "ids", "v", "lists", "code", "floor"]

    def put(batches):
        """Entries to their blocks, with their list and code."""
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(batch.column(0)).astype(float)
            where = index.assign(x)
            for k in np.flatnonzero(lengths(x - index.centroids[where]) > radius[where]):  # as near to another list, by rounding
                gap = lengths(x[k] - index.centroids)
                where[k] = np.where(gap <= radius, gap, np.inf).argmin()
            codes = index.encode(x, where)
            blocks = [first_block[c] + (k % parts_of[c]) for c, k in zip(where.tolist(), batch.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int32()), pa.nulls(len(x), pa.int64()), batch.column(1), batch.column(0), pa.array(where[:, None].tolist(), pa.list_(pa.int32())), pa.array([c.tobytes() for c in codes], pa.binary()), pa.nulls(len(x), pa.float64())], names)

    def probe(batches):
        """For each query a row for each block that holds lists which it visits."""
        for batch in batches:
            for k in range(0, batch.num_rows, 1024):
                part = batch.slice(k, 1024)
                q = matrix(part.column(1)).astype(float)
                scores = q @ index.centroids.T
                if index.probes is None:
                    floor = index.floors(q, top)
                    best = [np.flatnonzero(b).tolist() for b in scores + lengths(q)[:, None] * reach >= floor[:, None]]
                else:
                    floor = np.full(len(q), -np.inf)
                    best = np.argsort(-scores, axis=1, kind="stable")[:, : index.probes].tolist()
                at, to, visits = [], [], []
                for row, lists_ in enumerate(best):
                    wanted: dict[int, list[int]] = {}
                    for c in lists_:
                        for b in range(parts_of.get(c, 0)):
                            wanted.setdefault(first_block[c] + b, []).append(c)
                    at += [row] * len(wanted)
                    to += wanted.keys()
                    visits += wanted.values()
                pick = pa.array(at, pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), part.column(0).take(pick), pa.nulls(len(at), pa.list_(pa.int64())), part.column(1).take(pick), pa.array(visits, pa.list_(pa.int32())), pa.nulls(len(at), pa.binary()), pa.array(floor).take(pick)], names)

    placed = entries.select("v", "ids", F.pmod(F.xxhash64("v"), F.lit(1 << 30)).alias("k")).mapInArrow(put, sent)
    visiting = asked.select("vec_id", "v").repartition(width(spark)).mapInArrow(probe, sent)
    met = placed.union(visiting).repartition(max(width(spark), len(set(first_block.values()))), "block").sortWithinPartitions("block", F.col("query_id").asc_nulls_first())

    def visit(batches):
        """A block's entries come first and are held; its queries stream past."""
        block, held, ready = None, [], None

        def load(parts_):
            t = pa.Table.from_batches(parts_)
            ids = t.column("ids").to_pylist()
            n = np.array([len(i) for i in ids])
            x = np.concatenate([matrix(c) for c in t.column("v").chunks]).astype(float)
            codes = np.frombuffer(b"".join(t.column("code").to_pylist()), np.uint8).reshape(t.num_rows, -1)
            own = np.array([c[0] for c in t.column("lists").to_pylist()])
            return Block(x, codes, own, index.left_out(x, own, codes), lengths(x)), np.array([v for i in ids for v in i], np.int64), np.cumsum(n) - n, n

        for batch in batches:
            blocks = batch.column(0).to_numpy()
            edges = np.flatnonzero(np.concatenate([[True], blocks[1:] != blocks[:-1]])).tolist() if len(blocks) else []
            for a, b in zip(edges, [*edges[1:], len(blocks)], strict=True):
                part = batch.slice(a, b - a)
                if blocks[a] != block:
                    block, held, ready = blocks[a], [], None
                asks = part.column("query_id").is_valid()
                if some := part.num_rows - asks.true_count:
                    held.append(part.slice(0, some))
                part = part.slice(some)
                if not part.num_rows or not held:
                    continue
                ready = ready or load(held)
                entries_, flat, begin, n_ids = ready
                for k in range(0, part.num_rows, QUERY_ROWS):
                    group = part.slice(k, QUERY_ROWS)
                    visits = np.zeros((group.num_rows, len(index.centroids)), bool)
                    for row, lists_ in enumerate(group.column("lists").to_pylist()):
                        visits[row, lists_] = True
                    rows_, which, score = nearest_in_block(entries_, index, matrix(group.column("v")).astype(float), visits, group.column("floor").to_numpy(), top, shortlist)
                    many = n_ids[which]
                    ids = flat[np.repeat(begin[which] - (np.cumsum(many) - many), many) + np.arange(many.sum())]
                    q_ids = np.repeat(group.column("query_id").to_numpy()[rows_], many)
                    other = ids != q_ids
                    yield pa.RecordBatch.from_arrays([pa.array(c[other]) for c in (q_ids, ids, np.repeat(score, many))], ["query_id", "vec_id", "score"])

    best = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))
    return met.mapInArrow(visit, FOUND).withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")
