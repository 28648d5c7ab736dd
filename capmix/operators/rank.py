"""Percent cuts without a global sort.

The exact cut takes two narrow scans: a histogram of the score finds the bin that holds the k-th
row, and only that bin's rows are ordered. An oversized bin is split again, by score and, if its scores
are all equal, by id. Many percents share one histogram.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

BINS = 1 << 16
#: A bin of at most so many rows is ordered by one task.
BIN_ROWS = 1_000_000


@dataclass(frozen=True)
class Cut:
    """The last row within the best k: its score and id. With no row, nothing is covered."""

    x: float
    k: int
    sim: float | None
    id: int | None

    def covers_rank(self, sim: Column, pair_id: Column) -> Column:
        """Is a row among the best k? Ties at the cut are split by id."""
        if self.sim is None:
            return F.lit(False)
        sim = F.when(~F.isnan(sim), sim)
        return F.coalesce((sim > self.sim) | ((sim == self.sim) & (pair_id <= self.id)), F.lit(False))

    def covers_value(self, sim: Column) -> Column:
        """Does a score reach the cut's value? The id plays no part; without a cut nothing does."""
        return F.lit(False) if self.sim is None else F.coalesce(F.when(~F.isnan(sim), sim) >= self.sim, F.lit(False))


def rows_wanted(x: float, n: int) -> int:
    """k = ceil(x n / 100), free of binary rounding for percents with few decimals."""
    if not 0 <= x <= 100:
        raise ValueError("a percent lies between 0 and 100")
    return math.ceil(round(x * n, 9) / 100 - 1e-12)


def _bin(sim: Column, low: float, high: float) -> Column:
    return F.greatest(F.lit(0), F.least(F.lit(BINS - 1), F.floor((sim - low) * (BINS / (high - low))))).cast("bigint")


def cuts(sheet: DataFrame, col: str, xs: list[float], id_col: str = "pair_id", low: float = -1.0, high: float = 1.0, bin_rows: int = BIN_ROWS, as_rows: bool = False) -> dict[float, Cut]:
    """The cuts of all percents, from one histogram and one scan of the boundary bins; `as_rows`: xs are numbers of rows."""
    score = F.when(~F.isnan(col), F.col(col))
    rows = sheet.select(F.col(id_col).alias("id"), score.alias("s"))
    counts = rows.groupBy(F.when(F.col("s").isNotNull(), _bin(F.col("s"), low, high)).alias("bin")).count().collect()  # at most BINS + 1 rows
    n = sum(r["count"] for r in counts)
    there = sorted(((r["bin"], r["count"]) for r in counts if r["bin"] is not None), reverse=True)
    total = sum(c for _, c in there)
    out, need = {}, {}
    for x in xs:
        k = min(x if as_rows else rows_wanted(x, n), total)
        if k == 0:
            out[x] = Cut(x, 0, None, None)
            continue
        above = 0
        for b, c in there:
            if above + c >= k:
                need[x] = (b, k - above, k, c)
                break
            above += c
    small = {x: v for x, v in need.items() if v[3] <= bin_rows}
    if small:
        edge = rows.withColumn("bin", _bin(F.col("s"), low, high)).filter(F.col("bin").isin(*{v[0] for v in small.values()}))
        ranked = edge.withColumn("r", F.row_number().over(Window.partitionBy("bin").orderBy(F.desc("s"), F.asc("id"))))
        wanted = F.lit(False)
        for b, r, *_ in set(small.values()):
            wanted = wanted | ((F.col("bin") == b) & (F.col("r") == r))
        found = {(r["bin"], r["r"]): r for r in ranked.filter(wanted).select("bin", "r", "s", "id").collect()}
        for x, (b, r, k, _) in small.items():
            out[x] = Cut(x, k, found[b, r]["s"], found[b, r]["id"])
    for x, (b, r, k, _) in need.items():
        if x not in out:
            inside = rows.filter(_bin(F.col("s"), low, high) == b)
            sim, rest = _kth(inside, "s", r, descending=True)
            number, _ = _kth(inside.filter(F.col("s") == sim), "id", rest, descending=False)
            out[x] = Cut(x, k, sim, number)
    return out


def nested_cuts(sheet: DataFrame, col: str, xs: list[float], level: str, levels: int, id_col: str = "pair_id", low: float = -1.0, high: float = 1.0, bin_rows: int = BIN_ROWS) -> dict[tuple[int, float], Cut]:
    """The cuts of all percents over nested subsets: subset t holds the rows whose `level` is at most t.

    One histogram by level serves all subsets, one scan orders their boundary bins.
    """
    score = F.when(~F.isnan(col), F.col(col))
    rows = sheet.select(F.col(id_col).alias("id"), score.alias("s"), F.col(level).alias("level"))
    counts = rows.groupBy("level", F.when(F.col("s").isNotNull(), _bin(F.col("s"), low, high)).alias("bin")).count().collect()  # levels * (BINS + 1) rows at most
    out: dict[tuple[int, float], Cut] = {}
    wanted = []
    for t in range(levels):
        there: dict[int, int] = {}
        n = 0
        for r in counts:
            if r["level"] <= t:
                n += r["count"]
                if r["bin"] is not None:
                    there[r["bin"]] = there.get(r["bin"], 0) + r["count"]
        total, order = sum(there.values()), sorted(there, reverse=True)
        for x in xs:
            k, above = min(rows_wanted(x, n), total), 0
            if k == 0:
                out[t, x] = Cut(x, 0, None, None)
                continue
            for b in order:
                if above + there[b] >= k:
                    if there[b] <= bin_rows:
                        wanted.append((t, x, b, k - above, k))
                    else:
                        out[t, x] = cuts(sheet.filter(F.col(level) <= t), col, [x], id_col, low, high, bin_rows)[x]
                    break
                above += there[b]
    if wanted:
        asks = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(t).alias("t"), F.lit(b).cast("bigint").alias("b"), F.lit(r).alias("r")) for i, (t, _, b, r, _) in enumerate(wanted)])
        edge = rows.withColumn("bin", _bin(F.col("s"), low, high)).filter(F.col("bin").isin(*{w[2] for w in wanted}))
        own = edge.withColumn("ask", F.explode(F.filter(asks, lambda a: (a["b"] == F.col("bin")) & (F.col("level") <= a["t"]))))
        ranked = own.withColumn("place", F.row_number().over(Window.partitionBy("ask.i").orderBy(F.desc("s"), F.asc("id"))))
        for r in ranked.filter(F.col("place") == F.col("ask.r")).select("ask.i", "s", "id").collect():  # one row an ask
            t, x, _, _, k = wanted[r["i"]]
            out[t, x] = Cut(x, k, r["s"], r["id"])
    return out


def _kth(df: DataFrame, col: str, r: int, descending: bool):
    """The r-th value of a column and r's place among the rows equal to it, by repeated histograms."""
    while True:
        low, high = df.agg(F.min(col), F.max(col)).first()
        if low == high:
            return low, r
        step = (high - low) / 1024
        part = F.least(F.lit(1023), F.floor((F.col(col) - F.lit(low)) / F.lit(step))).cast("int")
        counts = sorted(((p, c) for p, c in df.groupBy(part.alias("p")).count().collect()), reverse=descending)
        if len(counts) == 1 or step == 0:
            values = sorted(((v, c) for v, c in df.groupBy(col).count().collect()), reverse=descending)
        else:
            values = None
        for p, c in values or counts:
            if r <= c:
                break
            r -= c
        if values:
            return p, r
        df = df.filter(part == p)


def top_percent(sheet: DataFrame, col: str, x: float, id_col: str = "pair_id", ties: str = "exact", **options) -> DataFrame:
    """The best x percent of the rows by `col`; ties='include' keeps every row at the cut's score."""
    cut = cuts(sheet, col, [x], id_col, **options)[x]
    return sheet.filter(cut.covers_value(F.col(col)) if ties == "include" else cut.covers_rank(F.col(col), F.col(id_col)))


def top_percent_window(sheet: DataFrame, col: str, x: float, id_col: str = "pair_id") -> DataFrame:
    """The same by a global window: one task sorts everything. The reference for tests only."""
    k = rows_wanted(x, sheet.count())
    ranked = sheet.withColumn("_r", F.row_number().over(Window.orderBy(F.desc_nulls_last(col), F.asc(id_col))))
    return ranked.filter((F.col("_r") <= k) & F.col(col).isNotNull()).drop("_r")


def approx_cut(sheet: DataFrame, col: str, x: float, accuracy: int = 10_000) -> float | None:
    """The cut's score by a mergeable quantile sketch: one scan, rank error about n / accuracy."""
    return sheet.agg(F.percentile_approx(col, 1 - x / 100, accuracy)).first()[0]


def kll_cut(sheet: DataFrame, col: str, x: float) -> float | None:
    """The cut's score by a KLL sketch."""
    sketch = sheet.agg(F.kll_sketch_agg_double(col).alias("k"))
    return sketch.select(F.kll_sketch_get_quantile_double("k", F.lit(1 - x / 100))).first()[0]


def top_k(sheet: DataFrame, col: str, k: int, id_col: str = "pair_id") -> DataFrame:
    """A small top k: every task keeps k rows."""
    return sheet.orderBy(F.desc_nulls_last(col), F.asc(id_col)).limit(k)
