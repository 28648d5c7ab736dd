"""The image gate: keep images whose cluster is the nearest one of some reference image."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..storage import few

#: Centres held and broadcast at a time; more are taken in several passes.
FLAT_CENTRES = 50_000


def seeded_centres(images: DataFrame, k: int, iterations: int = 0) -> DataFrame:
    """(cid int, centre): the k images of smallest id, then `iterations` Lloyd steps; an empty cluster stays."""
    first = images.orderBy("image_id").limit(k)
    centres = first.select((F.row_number().over(Window.orderBy("image_id")) - 1).cast("int").alias("cid"), F.col("vec").alias("centre"))  # k rows
    for _ in range(iterations):
        near = assign(images, centres).join(images.select("image_id", "vec"), "image_id")
        parts = near.select("cid", F.posexplode("vec").alias("dim", "v")).groupBy("cid", "dim").agg(F.avg("v").alias("v"))
        moved = parts.groupBy("cid").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "v"))), lambda s: s["v"]).alias("moved"))
        centres = centres.join(moved, "cid", "left").select("cid", F.coalesce("moved", "centre").alias("centre"))
    return centres


def kmeans_centres(images: DataFrame, k: int, sample_rows: int = 1_000_000, iterations: int = 10, seed: int = 1) -> DataFrame:
    """(cid, centre) by k-means on a sample of at most about sample_rows rows, drawn by the hash of the id."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    n = images.count()
    share = min(1.0, sample_rows / max(n, 1))
    drawn = images.filter(F.pmod(F.xxhash64("image_id"), F.lit(1 << 20)) < int(share * (1 << 20)) + 1)
    model = KMeans(k=k, maxIter=iterations, seed=seed, featuresCol="f").fit(drawn.select(array_to_vector("vec").alias("f")))
    rows = [(i, [float(v) for v in c]) for i, c in enumerate(model.clusterCenters())]
    return images.sparkSession.createDataFrame(rows, "cid int, centre array<double>")


def _matrix(centres: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    rows = centres.orderBy("cid").collect()  # at most about FLAT_CENTRES rows
    return np.array([r["cid"] for r in rows], np.int32), np.array([r["centre"] for r in rows], float)


def assign(images: DataFrame, centres: DataFrame, metric: str = "dot", nearest: int = 1, flat: int = FLAT_CENTRES) -> DataFrame:
    """(image_id, cid) of the nearest centre(s) by inner product or squared distance; ties to the lower cid.

    An Arrow pass of block products against the broadcast centres; of more than `flat` centres one pass for each
    part of them, and the best of all passes.
    """
    parts = centres.count() // flat + 1
    if parts == 1:
        return _assign_part(images, centres, metric, nearest).select("image_id", "cid")
    found = None
    for k in range(parts):
        one = _assign_part(images, centres.filter(F.pmod(F.xxhash64("cid"), F.lit(parts)) == k), metric, nearest)
        found = one if found is None else found.union(one)
    best = Window.partitionBy("image_id").orderBy(F.desc("score"), "cid")
    return found.withColumn("r", F.row_number().over(best)).filter(F.col("r") <= nearest).select("image_id", "cid")


def _assign_part(images: DataFrame, centres: DataFrame, metric: str, nearest: int) -> DataFrame:
    cids, matrix = _matrix(centres)
    if not len(cids):
        return images.select("image_id", F.lit(None).cast("int").alias("cid"), F.lit(None).cast("double").alias("score")).limit(0)
    offset = np.zeros(len(cids)) if metric == "dot" else 0.5 * (matrix**2).sum(axis=1)
    m = min(nearest, len(cids))

    def work(batches):
        for batch in batches:
            ids, column = batch.column(0), batch.column(1)
            there = column.is_valid()
            ids, column = ids.filter(there), column.filter(there)
            if not len(ids):
                continue
            x = np.asarray(column.flatten()).reshape(len(ids), -1)
            rows = max(1, min(4096, (1 << 22) // len(cids)))
            for k in range(0, len(x), rows):
                score = x[k : k + rows] @ matrix.T - offset
                best = score.argmax(axis=1)[:, None] if m == 1 else np.argsort(-score, axis=1, kind="stable")[:, :m]
                at = pa.array(np.repeat(np.arange(len(best)), m))
                yield pa.RecordBatch.from_arrays([ids.slice(k, rows).take(at), pa.array(cids[best.ravel()]), pa.array(np.take_along_axis(score, best, axis=1).ravel())], ["image_id", "cid", "score"])

    return images.select("image_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(work, "image_id bigint, cid int, score double")


def assign_expression(images: DataFrame, centres: DataFrame) -> DataFrame:
    """The same in plain DataFrame terms: a join with the few centres and the best of each image."""
    from ..functions.vectors import dot

    if not few(centres, FLAT_CENTRES):
        raise ValueError(f"more than {FLAT_CENTRES} centres; use assign")
    scored = images.select("image_id", "vec").join(F.broadcast(centres), how="cross").select("image_id", "cid", dot("vec", "centre").alias("s"))
    return scored.groupBy("image_id").agg(F.max_by("cid", F.struct("s", -F.col("cid"))).alias("cid"))


def assign_two_level(images: DataFrame, centres: DataFrame, groups: int | None = None, probes: int = 2) -> DataFrame:
    """Approximate assignment for many centres: the best groups of centres first, then their members."""
    cids, matrix = _matrix(centres)
    groups = groups or max(1, int(np.sqrt(len(cids))))
    heads = matrix[:: max(1, len(cids) // groups)][:groups]
    member = (matrix @ heads.T).argmax(axis=1)
    lists = [np.flatnonzero(member == g) for g in range(len(heads))]

    def work(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1)
            near = np.argsort(-(x @ heads.T), axis=1, kind="stable")[:, :probes]
            best, at = np.full(len(x), -np.inf), np.zeros(len(x), np.int64)
            for g, own in enumerate(lists):
                rows = np.flatnonzero((near == g).any(axis=1))
                if len(rows) and len(own):
                    s = x[rows] @ matrix[own].T
                    k = s.argmax(axis=1)
                    better = s[np.arange(len(rows)), k] > best[rows]
                    best[rows[better]], at[rows[better]] = s[np.arange(len(rows)), k][better], own[k][better]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cids[at])], ["image_id", "cid"])

    return images.select("image_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(work, "image_id bigint, cid int")


def reference_hits(references: DataFrame, centres: DataFrame, nearest: int = 1) -> DataFrame:
    """(cid, n_hits) of the clusters that are nearest to some reference image."""
    return assign(references, centres, nearest=nearest).groupBy("cid").agg(F.count("*").alias("n_hits"))


def keep(assigned: DataFrame, hits: DataFrame, drop: bool = False) -> DataFrame:
    """Images of hit clusters, or with `drop` all others."""
    return assigned.join(hits, "cid", "left_anti" if drop else "left_semi").select("image_id", "cid")


def gated_sheet(sheet: DataFrame, assigned: DataFrame, hits: DataFrame) -> DataFrame:
    """The score sheet with cid and the gate's flag."""
    flagged = assigned.join(hits.select("cid", F.lit(True).alias("_hit")), "cid", "left").select("image_id", "cid", F.coalesce("_hit", F.lit(False)).alias("gated"))
    return sheet.join(flagged, "image_id", "left").withColumn("gated", F.coalesce("gated", F.lit(False)))


def report(assigned: DataFrame, hits: DataFrame) -> DataFrame:
    """(cid, n_images, n_hits, kept): cluster sizes and hits."""
    sizes = assigned.groupBy("cid").agg(F.count("*").alias("n_images"))
    return sizes.join(hits, "cid", "left").select("cid", "n_images", F.coalesce("n_hits", F.lit(0)).cast("bigint").alias("n_hits"), F.col("n_hits").isNotNull().alias("kept"))
