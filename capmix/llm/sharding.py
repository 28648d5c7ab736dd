"""Sharding [native]: a keyed Feistel permutation with cycle walking over global row numbers.

Every row gets a global row number g in 0..N-1 (ascending id), the permutation maps it to p, and
shard = p mod S, slot = p div S. So the shuffle is reproducible from (key, N) alone, shard sizes
differ by one row at most, slots have no gaps, and the place of a row can be computed without data
(`place_of`) as can the row at a place (`row_at`).

The permutation works on pairs (l, r) of Z_a x Z_b with a = ceil(sqrt N), b = ceil(N / a). The
domain exceeds N by less than a, so a walk back into range is rare and short: the chance that a
row needs k extra steps is below N**(-k/2). Up to 64 steps are provided, which is certain to
suffice for N <= 4096 and fails with probability below 1e-100 beyond; a row that would still be
outside raises an error instead of getting a wrong place.

Row numbers need no global sort: quantile bounds of the id cut it into ranges, each range is
numbered by its own window, and range offsets (one number for each range) are added. Rows with equal id, checksum and size
are counted off before the shuffle and numbered together; a range with too many others (one id, or no id, in
much of the table) is cut further by the checksum.

Defined cases: null ids come first; rows with equal ids are ordered by checksum and size (within a range that was cut by
the checksum, that comes before the id) and identical rows are interchangeable; null text counts as no bytes; an empty
table gives no rows; extra columns are ignored. Only SQL functions are used; nothing runs in Python on executors.
"""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import materialise, width

ROUNDS = 4
STEPS = 64
#: About so many different rows are numbered by one task at most; so many identical ones are written out by one.
RANGE_ROWS, SAME_ROWS = 5_000_000, 1_000_000


def domain(n: int) -> tuple[int, int]:
    """Sides (a, b) of the smallest nearly square grid that holds n numbers."""
    a = max(1, math.isqrt(max(0, n - 1)) + 1) if n > 1 else 1
    return a, max(1, -(-n // a))


def _draw(value: Column, round_no: int, key: str, modulus: int) -> Column:
    digest = F.md5(F.concat(F.lit(f"{key}:{round_no}:"), value.cast("string")))
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("bigint") % F.lit(modulus)


def _once(x: Column, n: int, key: str) -> Column:
    """One pass of the Feistel network, as an expression over a bigint column."""
    a, b = domain(n)
    side = F.lit(b).cast("bigint")
    state = F.struct(((x - x % side) / side).cast("bigint").alias("l"), (x % side).alias("r"))
    def left(k: int):
        return lambda s: F.struct(((s["l"] + _draw(s["r"], k, key, a)) % F.lit(a)).alias("l"), s["r"].alias("r"))

    def right(k: int):
        return lambda s: F.struct(s["l"].alias("l"), ((s["r"] + _draw(s["l"], k, key, b)) % F.lit(b)).alias("r"))

    for k in range(ROUNDS):
        # transform() over one element binds each round's state once, so it isn't expanded twice
        state = F.transform(F.array(state), left(k) if k % 2 == 0 else right(k))[0]
    return F.transform(F.array(state), lambda s: s["l"] * F.lit(b) + s["r"])[0]


def permute(x: Column, n: int, key: str) -> Column:
    """The permuted place of row number x among n rows; walks until it is in range."""
    limit = F.lit(n).cast("bigint")
    walked = F.reduce(F.sequence(F.lit(1), F.lit(STEPS)), _once(x, n, key), lambda p, _: F.when(p < limit, p).otherwise(_once(p, n, key)))
    return F.transform(F.array(walked), lambda p: F.when(p < limit, p).otherwise(F.raise_error(F.lit("cycle walk ended outside the range")).cast("bigint")))[0]


def _draw_py(value: int, round_no: int, key: str, modulus: int) -> int:
    return int(hashlib.md5(f"{key}:{round_no}:{value}".encode()).hexdigest()[:15], 16) % modulus


def place_of(row: int, n: int, key: str, shards: int) -> tuple[int, int]:
    """(shard, slot) of a row number, without any data."""
    a, b = domain(n)
    p = row
    while True:
        l, r = divmod(p, b)
        for k in range(ROUNDS):
            if k % 2 == 0:
                l = (l + _draw_py(r, k, key, a)) % a
            else:
                r = (r + _draw_py(l, k, key, b)) % b
        p = l * b + r
        if p < n:
            return p % shards, p // shards


def row_at(shard: int, slot: int, n: int, key: str, shards: int) -> int:
    """The row number that lies at (shard, slot): the inverse of place_of."""
    a, b = domain(n)
    p = slot * shards + shard
    while True:
        l, r = divmod(p, b)
        for k in reversed(range(ROUNDS)):
            if k % 2 == 0:
                l = (l - _draw_py(r, k, key, a)) % a
            else:
                r = (r - _draw_py(l, k, key, b)) % b
        p = l * b + r
        if p < n:
            return p


def _longs(values: list[int]) -> Column:
    return F.lit(values).cast(T.ArrayType(T.LongType()))


def number_rows(df: DataFrame, order: list[str], name: str = "row_number", times: str | None = None, spread: str | None = None, range_rows: int = RANGE_ROWS) -> tuple[DataFrame, int]:
    """Add gapless global row numbers from 0 in ascending `order` (nulls first), and count the rows.

    The first column of `order` must be integral; its quantiles cut the rows into ranges. `times`: a row stands for so many and
    gets the number of its first. `spread`: an integral column of 32 even bits that cuts ranges of too many rows.
    """
    spark = df.sparkSession
    first = order[0]
    ranges = width(spark, df.select(first).count(), range_rows)
    shares = [k / ranges for k in range(1, ranges)]
    bounds = df.select(F.percentile_approx(first, shares, max(10_000, 20 * ranges))).first()[0] if shares else None
    bounds = sorted(set(bounds or []))
    place = F.lit(0)
    if bounds:
        # search in two steps over literal bounds: whole strides below the value, then within one stride
        value, stride = F.col(first).cast("bigint"), math.isqrt(len(bounds)) + 1
        below = lambda found: F.size(F.filter(found, lambda e: e < value))
        heads = bounds[stride - 1 :: stride]
        whole = below(_longs(heads)) * stride if heads else F.lit(0)
        place = F.when(value.isNull(), F.lit(0)).otherwise(whole + below(F.slice(_longs(bounds), whole + 1, stride)))
    weight = F.col(times) if times else F.lit(1).cast("bigint")
    ranged = df.withColumn("_range", place.cast("int"))
    found = {r["_range"]: r for r in ranged.groupBy("_range").agg(F.count("*").alias("n"), F.sum(weight).alias("total")).collect()}  # one row for each range
    if not found:
        return ranged.withColumn(name, F.lit(0).cast("bigint")).drop("_range"), 0
    parts = [-(-found[k]["n"] // range_rows) if spread and k in found and found[k]["n"] > 2 * range_rows else 1 for k in range(max(found) + 1)]
    totals = {(k, 0): r["total"] for k, r in found.items()}
    ranged = ranged.withColumn("_part", F.lit(0).cast("bigint"))
    if max(parts) > 1:
        ranged = ranged.withColumn("_part", F.shiftright(F.col(spread) * F.get(_longs(parts), F.col("_range")), 32))
        totals = {(r["_range"], r["_part"]): r["total"] for r in ranged.groupBy("_range", "_part").agg(F.sum(weight).alias("total")).collect()}  # one row for each part
    starts, offsets, total = [], [], 0
    for k, n in enumerate(parts):
        starts.append(len(offsets))
        for p in range(n):
            offsets.append(total)
            total += totals.get((k, p), 0)
    base = F.get(_longs(offsets), (F.get(_longs(starts), F.col("_range")) + F.col("_part")).cast("int"))
    window = Window.partitionBy("_range", "_part").orderBy(*[F.col(c).asc_nulls_first() for c in order])
    local = F.sum(weight).over(window.rowsBetween(Window.unboundedPreceding, 0)) - weight if times else F.row_number().over(window) - 1
    return ranged.withColumn(name, base + local).drop("_range", "_part"), total


def shard(df: DataFrame, shards: int, key: str = "capmix", id_col: str = "doc_id", text_col: str = "text", range_rows: int = RANGE_ROWS, same_rows: int = SAME_ROWS) -> DataFrame:
    """Deal df's rows to `shards` shards: (id, size, text_crc32, row_number, shard, slot).

    Texts don't move: only the id, the size and the checksum are shuffled. size is the text's UTF-8
    length plus 8.
    """
    narrow = df.select(
        F.col(id_col).cast("bigint").alias("_id"),
        (F.coalesce(F.octet_length(text_col), F.lit(0)) + 8).cast("bigint").alias("_size"),
        F.crc32(F.coalesce(F.col(text_col), F.lit("")).cast("binary")).cast("bigint").alias("_crc"),
    )
    # kept as a narrow table: it is read for bounds, sizes and numbers, and texts are read once
    same = materialise(narrow.groupBy("_id", "_crc", "_size").agg(F.count("*").alias("_times")), "rows")
    numbered, n = number_rows(same, ["_id", "_crc", "_size"], "_first", "_times", "_crc", range_rows)
    most = same.agg(F.max("_times")).first()[0] or 0

    def rows(some: DataFrame, step: int) -> DataFrame:
        return some.withColumn("_g", F.explode(F.sequence(F.col("_first"), F.least(F.col("_first") + step, F.col("_end")) - 1)))

    ends = numbered.withColumn("_end", F.col("_first") + F.col("_times"))
    every = rows(ends.filter(F.col("_times") <= same_rows), same_rows)
    if most > same_rows:
        # many identical rows are written out by several tasks
        cut = ends.filter(F.col("_times") > same_rows).withColumn("_first", F.explode(F.sequence("_first", F.col("_end") - 1, F.lit(same_rows).cast("bigint"))))
        every = every.union(rows(cut.repartition(width(df.sparkSession), "_first"), same_rows))
    placed = every.withColumn("_p", permute(F.col("_g"), max(n, 1), key))
    return placed.select(F.col("_id").alias(id_col), F.col("_size").alias("size"), F.col("_crc").alias("text_crc32"), F.col("_g").alias("row_number"), (F.col("_p") % shards).cast("int").alias("shard"), F.floor(F.col("_p") / shards).cast("bigint").alias("slot"))
