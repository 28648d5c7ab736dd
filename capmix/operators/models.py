"""Many training sets at once: alignment maps from mask-weighted Gram sums, and their evaluation.

A training set is a bit of the two masks of `recipes.with_masks`. One scan gives every set's budget cut, one its Gram
sums; only set x d x 2d numbers reach the driver, where the ridge maps are solved. All maps are then evaluated
in one pass over each evaluation set: ranks are counts of better candidates, so candidates are taken in blocks of
bounded size and counts are added up, whatever the size of the evaluation set.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.fixtures import salted

#: Candidates broadcast at a time; bins of the budget's and the AUC's histograms; what counts as a tie.
BLOCK_ROWS, BUDGET_BINS, AUC_BINS, TIE = 20_000, 1 << 12, 4096, 1e-12


@dataclass(frozen=True)
class Budget:
    """How often a row of a set is seen: `base` times, once more if (number, id) comes no later than the cut."""

    base: int
    number: int = -1
    pair_id: int = -1

    def copies(self, number: np.ndarray, pair_id: np.ndarray) -> np.ndarray:
        return self.base + ((number < self.number) | ((number == self.number) & (pair_id <= self.pair_id)))


def budgets(masks: DataFrame, samples: list[int], salt: str = "budget") -> list[Budget]:
    """For each set the rule by which samples[k] samples are seen in all: from one histogram and one scan of its cuts' bins."""
    member = F.col("raw_mask").bitwiseOR(F.col("gen_mask"))
    rows = masks.select("pair_id", member.alias("m"), salted("pair_id", salt).alias("u")).filter("m <> 0")
    rows = rows.withColumn("bin", F.shiftright("u", 32 - (BUDGET_BINS - 1).bit_length()))
    bit = lambda k: F.col("m").bitwiseAND(F.lit(1 << k).cast("bigint")) != 0
    counts = rows.groupBy("bin").agg(*[F.count_if(bit(k)).alias(f"n{k}") for k in range(len(samples))]).collect()  # BUDGET_BINS rows
    counts.sort(key=lambda r: r["bin"])
    out, asks = [Budget(0)] * len(samples), []
    for k, n in enumerate(samples):
        m = sum(r[f"n{k}"] for r in counts)
        if not m:
            continue
        base, rest = divmod(n, m)
        out[k] = Budget(base)
        below = 0
        for r in counts:
            if rest and below < rest <= below + r[f"n{k}"]:
                asks.append((k, r["bin"], rest - below))
            below += r[f"n{k}"]
    if asks:
        wanted = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(b).cast("bigint").alias("bin"), F.lit(r).alias("r"), F.lit(1 << k).cast("bigint").alias("bit")) for k, b, r in asks])
        edge = rows.filter(F.col("bin").isin(*{a[1] for a in asks})).withColumn("ask", F.explode(F.filter(wanted, lambda a: (a["bin"] == F.col("bin")) & (F.col("m").bitwiseAND(a["bit"]) != 0))))
        placed = edge.withColumn("place", F.row_number().over(Window.partitionBy("ask.k").orderBy("u", "pair_id")))
        for r in placed.filter(F.col("place") == F.col("ask.r")).select("ask.k", "u", "pair_id").collect():  # one row a set
            out[r["k"]] = Budget(out[r["k"]].base, r["u"], r["pair_id"])
    return out


def _summed(parts: DataFrame, sets: int) -> list[np.ndarray]:
    """Sums of (set, gram) over all tasks, added in one order."""

    def add(batches):
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                g = np.frombuffer(raw)
                total[k] = total[k] + g if k in total else g
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([g.tobytes() for g in total.values()], pa.binary())], ["set", "gram"])

    spark = parts.sparkSession
    n = min(sets, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = parts.repartition(n, "set").sortWithinPartitions("set", "gram").mapInArrow(add, "set int, gram binary").collect()  # one row a set
    found = {r["set"]: np.frombuffer(r["gram"]) for r in rows}
    d = max((int(np.sqrt(len(g) / 2)) for g in found.values()), default=0)
    return [found[k].reshape(d, 2 * d) if k in found else np.zeros((d, 2 * d)) for k in range(sets)]


def gram_sums(pool: DataFrame, rules: list[Budget], salt: str = "budget") -> list[np.ndarray]:
    """For each set the sums of w t t' beside w t i', d x 2d, over the captions that it uses, w the copies of its budget.

    pool: pair_id, image_vec, raw_vec, gen_vec, raw_mask, gen_mask. One Arrow pass for all sets.
    """

    def work(batches):
        sums: list[np.ndarray | None] = [None] * len(rules)
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, u, raw, gen = (batch.column(c).to_numpy() for c in range(4))
            image, *texts = (np.asarray(batch.column(c).flatten()).reshape(batch.num_rows, -1) for c in (4, 5, 6))
            for k, rule in enumerate(rules):
                for mask, t in ((raw, texts[0]), (gen, texts[1])):
                    own = np.flatnonzero(mask >> k & 1)
                    if len(own):
                        w = rule.copies(u[own], ids[own])[:, None].astype(float)
                        part = (w * t[own]).T @ np.concatenate([t[own], image[own]], axis=1)
                        sums[k] = part if sums[k] is None else sums[k] + part
        there = [k for k, g in enumerate(sums) if g is not None]
        yield pa.RecordBatch.from_arrays([pa.array(there, pa.int32()), pa.array([sums[k].tobytes() for k in there], pa.binary())], ["set", "gram"])

    vec = lambda c: F.col(c).cast("array<double>").alias(c)
    rows = pool.filter("raw_mask <> 0 OR gen_mask <> 0").select("pair_id", salted("pair_id", salt).alias("u"), "raw_mask", "gen_mask", vec("image_vec"), vec("raw_vec"), vec("gen_vec")).dropna()
    return _summed(rows.mapInArrow(work, "set int, gram binary"), len(rules))


def grouped_gram_sums(rows: DataFrame, groups: list[str]) -> list[np.ndarray]:
    """The same over (origin, text_vec, image_vec): a set for each name of `groups`, every row once."""
    number = {g: k for k, g in enumerate(groups)}

    def work(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            of = np.array([number[g] for g in batch.column(0).to_pylist()])
            t, i = (np.asarray(batch.column(c).flatten()).reshape(batch.num_rows, -1) for c in (1, 2))
            for k in np.unique(of).tolist():
                part = t[of == k].T @ np.concatenate([t[of == k], i[of == k]], axis=1)
                sums[k] = sums[k] + part if k in sums else part
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([g.tobytes() for g in sums.values()], pa.binary())], ["set", "gram"])

    known = rows.select("origin", F.col("text_vec").cast("array<double>"), F.col("image_vec").cast("array<double>")).dropna().filter(F.col("origin").isin(*groups))
    return _summed(known.mapInArrow(work, "set int, gram binary"), len(groups))


def solve(grams: list[np.ndarray], ridge: float = 1.0) -> list[np.ndarray]:
    """The ridge map from text to image vectors of each set; a set without rows maps everything to zero."""
    return [np.linalg.solve(g[:, : len(g)] + ridge * np.eye(len(g)), g[:, len(g) :]) for g in grams]


def train_sets(pool: DataFrame, samples: list[int], ridge: float = 1.0) -> list[np.ndarray]:
    """The maps of all sets of a masked pool with vectors, each seen samples[k] times in all."""
    return solve(gram_sums(pool, budgets(pool, samples)), ridge)


def _unit(x: np.ndarray) -> np.ndarray:
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, size, out=np.zeros_like(x), where=size > 0)


def _better(s: np.ndarray, own: np.ndarray, ids: np.ndarray, others: np.ndarray) -> np.ndarray:
    """How many candidates beat each row's own one; ties go to the lower id. `others` is in order.

    Two counts for each row; only rows with another candidate near their own one are compared one by one.
    """
    out = np.count_nonzero(s > (own + TIE)[:, None], axis=1)
    near = np.count_nonzero(s >= (own - 2 * TIE)[:, None], axis=1) - out
    itself = np.searchsorted(others, ids, "right") - np.searchsorted(others, ids, "left")
    at = np.flatnonzero((near != itself) | (itself > 1))
    if len(at):
        s, own, ids = s[at], own[at], ids[at]
        beats = (s > own[:, None] + TIE) | ((np.abs(s - own[:, None]) <= TIE) & (others[None, :] < ids[:, None]))
        out[at] = (beats & (others[None, :] != ids[:, None])).sum(axis=1)
    return out


def retrieval_ranks(items: DataFrame, maps: dict[str, np.ndarray], block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(model, direction, item_id, rank): the place of each item's own image (t2i) and text (i2t) among all items.

    items: (item_id, image_vec, text_vec). Candidates are broadcast in blocks of about block_rows; counts are added up.
    """
    rows = items.select(F.col("item_id").cast("bigint"), F.col("image_vec").cast("array<double>").alias("i"), F.col("text_vec").cast("array<double>").alias("t")).dropna()
    blocks, out = rows.count() // block_rows + 1, None
    spark = items.sparkSession
    for b in range(blocks):
        part = rows.filter(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == b).orderBy("item_id").toArrow()  # about block_rows
        if not part.num_rows:
            continue
        flat = lambda c: np.asarray(part.column(c).combine_chunks().flatten()).reshape(part.num_rows, -1)  # noqa: E731, B023
        sent = spark.sparkContext.broadcast((part.column(0).to_numpy(), flat(1), flat(2)))

        def count(batches, sent=sent):
            ids, images, texts = sent.value
            images, mapped = _unit(images), {}
            for whole in batches:
                for k in range(0, whole.num_rows, 256):  # a block of 256 x block_rows scores at a time
                    batch = whole.slice(k, 256)
                    own_ids = batch.column(0).to_numpy()
                    i, t = (np.asarray(batch.column(c).flatten()).reshape(batch.num_rows, -1) for c in (1, 2))
                    i = _unit(i)
                    for name, w in maps.items():
                        y = _unit(t @ w)
                        if name not in mapped:
                            mapped[name] = _unit(texts @ w)
                        own = (y * i).sum(axis=1)
                        for direction, a, b in (("t2i", y, images), ("i2t", i, mapped[name])):
                            n, s = batch.num_rows, a @ b.T
                            yield pa.RecordBatch.from_arrays([pa.array([name] * n), pa.array([direction] * n), batch.column(0), pa.array(_better(s, own, own_ids, ids).astype(np.int64))], ["model", "direction", "item_id", "better"])

        one = rows.mapInArrow(count, "model string, direction string, item_id bigint, better bigint")
        out = one if out is None else out.union(one)
    if out is None:
        return spark.createDataFrame([], "model string, direction string, item_id bigint, rank bigint")
    return out.groupBy("model", "direction", "item_id").agg((F.sum("better") + 1).alias("rank"))


def retrieval_scores(ranks: DataFrame) -> DataFrame:
    """(model, score): the mean of both directions' recall at 1."""
    by = ranks.groupBy("model", "direction").agg(F.avg(F.when(F.col("rank") <= 1, 1.0).otherwise(0.0)).alias("recall"))
    return by.groupBy("model").agg(F.avg("recall").alias("score"))


def class_ranks(images: DataFrame, classes: DataFrame, maps: dict[str, np.ndarray], most: int = 50_000) -> DataFrame:
    """(model, image_id, rank) of the true class of each image among the mapped class texts; ties to the lower class.

    images: (image_id, vec, class); classes: (class, proto), at most `most`, one mean caption vector each.
    """
    protos = classes.orderBy("class").limit(most + 1).collect()
    if len(protos) > most:
        raise ValueError(f"more than {most} classes")
    names = np.array([p["class"] for p in protos], np.int64)
    texts = {m: _unit(np.array([p["proto"] for p in protos], float) @ w) for m, w in maps.items()} if protos else {}

    def work(batches):
        for whole in batches:
            for k in range(0, whole.num_rows, 1024):
                batch = whole.slice(k, 1024)
                x = _unit(np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1))
                truth = batch.column(2).to_numpy()
                at = np.minimum(np.searchsorted(names, truth), len(names) - 1)
                known = names[at] == truth
                for model, t in texts.items():
                    s = x @ t.T
                    better = _better(s, s[np.arange(len(x)), at], truth, names)
                    rank = pa.array(better + 1, mask=~known)
                    yield pa.RecordBatch.from_arrays([pa.array([model] * len(x)), batch.column(0), rank], ["model", "image_id", "rank"])

    rows = images.select(F.col("image_id").cast("bigint"), F.col("vec").cast("array<double>"), F.col("class").cast("bigint")).dropna()
    return rows.mapInArrow(work, "model string, image_id bigint, rank bigint")


def class_accuracy(ranks: DataFrame, tops: tuple[int, ...] = (1,)) -> DataFrame:
    """(model, k, accuracy); an image whose class has no text counts as wrong."""
    wide = ranks.groupBy("model").agg(*[F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias(f"k{k}") for k in tops])
    return wide.select("model", F.expr(f"stack({len(tops)}, {', '.join(f'{k}, k{k}' for k in tops)}) AS (k, accuracy)"))


def label_auc(pairs: DataFrame, maps: dict[str, np.ndarray]) -> DataFrame:
    """(model, grp, auc): how well the mapped text's cosine with its image ranks label 1 over label 0, by group.

    pairs: (grp, label, image_vec, text_vec). From histograms of the cosine, so that rows within 1/2048 count as ties.
    """

    def work(batches):
        counts: dict[tuple, int] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            groups, labels = np.array(batch.column(0).to_pylist(), object), batch.column(1).to_numpy()
            i, t = (np.asarray(batch.column(c).flatten()).reshape(batch.num_rows, -1) for c in (2, 3))
            i = _unit(i)
            for model, w in maps.items():
                bins = np.clip(((_unit(t @ w) * i).sum(axis=1) + 1) * (AUC_BINS / 2), 0, AUC_BINS - 1).astype(int)
                for g in set(groups.tolist()):
                    for y in (0, 1):
                        at, n = np.unique(bins[(groups == g) & (labels == y)], return_counts=True)
                        for b, c in zip(at.tolist(), n.tolist(), strict=True):
                            counts[model, g, b, y] = counts.get((model, g, b, y), 0) + c
        keys = list(zip(*counts, strict=True)) if counts else [[]] * 4
        yield pa.RecordBatch.from_arrays([pa.array(keys[0], pa.string()), pa.array(keys[1], pa.string()), pa.array(keys[2], pa.int32()), pa.array(keys[3], pa.int32()), pa.array(list(counts.values()), pa.int64())], ["model", "grp", "bin", "label", "n"])

    rows = pairs.select(F.col("grp").cast("string"), F.col("label").cast("int"), F.col("image_vec").cast("array<double>"), F.col("text_vec").cast("array<double>")).dropna()
    bins = rows.mapInArrow(work, "model string, grp string, bin int, label int, n bigint").groupBy("model", "grp", "bin").agg(F.sum(F.when(F.col("label") == 1, F.col("n")).otherwise(0)).alias("pos"), F.sum(F.when(F.col("label") == 0, F.col("n")).otherwise(0)).alias("neg"))
    below = Window.partitionBy("model", "grp").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    won = F.col("pos") * (F.coalesce(F.sum("neg").over(below), F.lit(0)) + F.col("neg") / 2)
    total = bins.withColumn("won", won).groupBy("model", "grp").agg(F.sum("won").alias("won"), F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    return total.select("model", "grp", (F.col("won") / F.nullif(F.col("pos") * F.col("neg"), F.lit(0))).alias("auc"))
