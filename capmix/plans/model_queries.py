"""Queries that train and evaluate models: every recipe, threshold, scale and captioner of the experiments.

A model is a ridge map from caption to image vectors, trained on a set seen as often as its pool has rows. All sets of a
query are bits of one mask: one scan trains them, one pass over each evaluation set measures them. Vectors are the
planted pool's, so the figures show how the methods compare there and reproduce no published accuracy.
"""

from __future__ import annotations


from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import evaluate, gate, models, recipes
from ..operators.recipes import Arm, Recipe
from ..sources import fixtures as fx
from ..sources.tables import load
from ..storage import materialise
from . import pool_queries as pq

NOISY = 3.85
SWEEP = pq.XS


def curve_recipes(xs: list[float] = SWEEP) -> list[Recipe]:
    """The four curves of the threshold sweep: raw alone, with some or all of the rest generated, generated alone."""
    out = []
    for x in xs:
        rest = Arm(eligible="remaining")
        out += [Recipe(f"raw:{x:g}", Arm(x)), Recipe(f"raw_plus_some:{x:g}", Arm(x), Arm(eligible="remaining", min_sim="inherit")), Recipe(f"raw_plus_all:{x:g}", Arm(x), rest), Recipe(f"gen:{x:g}", None, Arm(x))]
    return out


def trained(spark, d, plans: list[tuple[str, recipes.Plan]], sheet: DataFrame, **captioner) -> tuple[dict, DataFrame]:
    """The maps of all (scale, plan) by name, and (model, scale, recipe, n_rows, mean_sim): sizes of the sets."""
    sizes = {r["level"]: r["count"] for r in sheet.groupBy("level").count().collect()}  # a row for each scale
    at = {name: k for k, (name, _) in enumerate(pq.SCALES)}
    samples = [sum(n for level, n in sizes.items() if level <= at[scale]) for scale, _ in plans]
    # kept as a table: it is read for the budget, the sizes and the training
    masked = materialise(recipes.arrow_masks(sheet, [p for _, p in plans]), "masks")
    names = [(scale, p.recipe.name) for scale, p in plans]
    vecs = fx.planted_pool(spark, d, **captioner).select("pair_id", "image_vec", "raw_vec", "gen_vec")
    masks = masked.select("pair_id", "raw_mask", "gen_mask")
    maps = models.solve(models.gram_sums(vecs.join(masks, "pair_id"), models.budgets(masks, samples)))
    rows = recipes.mask_sheet(masked, names).select(F.concat_ws("/", "scale", "recipe").alias("model"), "scale", "recipe", "n_rows", "mean_sim")
    return {"/".join(n): w for n, w in zip(names, maps, strict=True)}, rows


def evaluation(spark, d):
    """(images with their cluster as class, class texts, two retrieval sets)."""
    centres = pq._centres(spark, d)
    n = fx.image_count(spark, d)
    items = fx.evaluation_set(spark, d)
    truth = gate.assign(items.select(F.col("item_id").alias("image_id"), F.col("image_vec").alias("vec")), centres)
    images = items.select(F.col("item_id").alias("image_id"), F.col("image_vec").alias("vec")).join(truth, "image_id").withColumnRenamed("cid", "class")
    pool = fx.captioned(spark, d, n // 5, None, fx.EVAL_WEIGHT)
    placed = pool.join(gate.assign(fx.pool_images(spark, d), centres).withColumnRenamed("image_id", "item_id"), "item_id")
    return images, evaluate.class_prototypes(placed, "cid", "text_vec"), items, fx.evaluation_set(spark, d, NOISY)


def measured(spark, d, maps: dict) -> DataFrame:
    """(model, classification, retrieval, retrieval_noisy, retrieval_mean) of all maps."""
    images, protos, first, second = evaluation(spark, d)
    accuracy = models.class_accuracy(models.class_ranks(images, protos, maps)).select("model", F.col("accuracy").alias("classification"))
    a = models.retrieval_scores(models.retrieval_ranks(first, maps)).withColumnRenamed("score", "retrieval")
    b = models.retrieval_scores(models.retrieval_ranks(second, maps)).withColumnRenamed("score", "retrieval_noisy")
    return accuracy.join(a, "model").join(b, "model").withColumn("retrieval_mean", (F.col("retrieval") + F.col("retrieval_noisy")) / 2)


def _whole(spark, d, names: list[Recipe]) -> tuple[dict, DataFrame]:
    s = pq.gated(spark, d).withColumn("level", F.lit(len(pq.SCALES) - 1))
    return trained(spark, d, [("large", p) for p in recipes.plan(s, names)], s)


def _out(df: DataFrame, *names: str) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.select(*names).dtypes])


def recipe_results(spark, d):
    """Every recipe at full scale: size, noise, classification and retrieval."""
    maps, rows = _whole(spark, d, [pq.REGISTRY[n] for n in pq.REGISTRY])
    return _out(rows.join(measured(spark, d, maps), "model"), "recipe", "n_rows", "mean_sim", "classification", "retrieval", "retrieval_noisy", "retrieval_mean")


def scale_results(spark, d):
    """Recipes at every scale: the gate fixed, cuts found anew at each scale for the same percents."""
    s = pq.leveled(pq.gated(spark, d))
    plans = recipes.plan_scales(s, [pq.REGISTRY[r] for r in pq.SCALE_RECIPES], [n for n, _ in pq.SCALES])
    maps, rows = trained(spark, d, plans, s)
    return _out(rows.join(measured(spark, d, maps), "model"), "scale", "recipe", "n_rows", "classification", "retrieval")


def _sweep_at(spark, d, s: DataFrame, scale: int) -> DataFrame:
    inside = s.filter(F.col("level") <= scale)
    maps, rows = trained(spark, d, [(pq.SCALES[scale][0], p) for p in recipes.plan(inside, curve_recipes())], inside)
    named = rows.join(measured(spark, d, maps), "model")
    return named.select(F.split("recipe", ":")[0].alias("curve"), F.split("recipe", ":")[1].cast("double").alias("x"), "n_rows", "classification", "retrieval")


def sweep_results(spark, d):
    """The threshold sweep with its outcomes: (curve, x, n_rows, classification, retrieval)."""
    return _out(_sweep_at(spark, d, pq.leveled(pq.gated(spark, d)), len(pq.SCALES) - 1), "curve", "x", "n_rows", "classification", "retrieval")


def tune_results(spark, d):
    """Percents tuned on classification at the medium scale and kept at all others: (scale, curve, x, n_rows, …)."""
    s = pq.leveled(pq.gated(spark, d))
    best = evaluate.best_percent(_sweep_at(spark, d, s, 1), "classification").collect()  # a row for each curve
    chosen = {r["curve"]: r["x"] for r in best}
    names = {f"{c}:{x:g}" for c, x in chosen.items()}
    wanted = [r for r in curve_recipes(sorted(set(chosen.values()))) if r.name in names]
    maps, rows = trained(spark, d, recipes.plan_scales(s, wanted, [n for n, _ in pq.SCALES]), s)
    named = rows.join(measured(spark, d, maps), "model").withColumns({"curve": F.split("recipe", ":")[0], "x": F.split("recipe", ":")[1].cast("double")})
    return _out(named, "scale", "curve", "x", "n_rows", "classification", "retrieval")


TABLE = ["raw_all", "raw_top30_gate", "raw_top30", "mix30_filtered", "gen_top75_gate", "gen_top50", "mix30", "gen_all"]


def retr_by_recipe(spark, d):
    """Retrieval by recipe on two sets, their mean, and its ratio to the best filtered raw set's."""
    maps, rows = _whole(spark, d, [pq.REGISTRY[n] for n in TABLE])
    found = rows.select("model", "recipe").join(measured(spark, d, maps), "model")
    gain = evaluate.gain_over(found.select("recipe", F.col("retrieval_mean").alias("score")), "raw_top30", value="score").select("recipe", "ratio")
    return _out(found.join(gain, "recipe"), "recipe", "retrieval", "retrieval_noisy", "retrieval_mean", "ratio")


def retr_swap(spark, d):
    """The same images with other captions, the whole pool with either captioner, and the mix, on two retrieval sets."""
    maps, rows = _whole(spark, d, [pq.REGISTRY[n] for n in ("raw_top30", "swap30", "gen_all", "mix30", "mix30_filtered")])
    tuned = pq.tuned_sheet(spark, d).withColumn("level", F.lit(len(pq.SCALES) - 1))
    more, other = trained(spark, d, [("large", p) for p in recipes.plan(tuned, [Recipe("gen_all_ft", None, Arm())])], tuned, **pq.TUNED)
    rows = rows.union(other)
    return _out(rows.select("model", "recipe", "n_rows").join(measured(spark, d, maps | more), "model"), "recipe", "n_rows", "retrieval", "retrieval_noisy", "retrieval_mean")


SUITE = ["raw_top30", "gen_top30", "mix30_filtered"]


def _suite(spark, d) -> DataFrame:
    maps, rows = _whole(spark, d, [pq.REGISTRY[n] for n in SUITE])
    images, protos, first, second = evaluation(spark, d)
    named = rows.select("model", "recipe")
    found = []

    def task(df: DataFrame, kind: str, metric: str) -> None:
        found.append(df.select("model", "task", F.lit(kind).alias("kind"), F.lit(metric).alias("metric"), F.col("value").cast("double").alias("value")))

    hit = F.avg(F.when(F.col("rank") <= 1, 1.0).otherwise(0.0)).alias("value")
    labels = load(spark, d, "embeddings").select(F.col("vec_id").alias("item_id"), "label")
    for name, items in (("clear", first), ("noisy", second)):
        ranks = models.retrieval_ranks(items, maps)
        task(ranks.groupBy("model", F.concat(F.lit(f"{name}:"), "direction").alias("task")).agg(hit), "retrieval", "recall_1")
        task(ranks.join(labels, "item_id").groupBy("model", F.concat(F.lit(f"{name}:class:"), "label").alias("task")).agg(hit), "retrieval", "recall_1")
    clusters = models.class_accuracy(models.class_ranks(images, protos, maps), (1, 5))
    task(clusters.select("model", F.concat(F.lit("cluster:top"), "k").alias("task"), F.col("accuracy").alias("value")), "classification", "accuracy")
    n = fx.image_count(spark, d)
    pool = fx.captioned(spark, d, n // 5, None, fx.EVAL_WEIGHT)
    own = first.select(F.col("item_id").alias("image_id"), F.col("image_vec").alias("vec")).join(labels.select(F.col("item_id").alias("image_id"), F.col("label").alias("class")), "image_id")
    by_label = models.class_accuracy(models.class_ranks(own, evaluate.class_prototypes(pool, "label", "text_vec"), maps))
    task(by_label.select("model", F.lit("label:top1").alias("task"), F.col("accuracy").alias("value")), "classification", "accuracy")
    marked = fx.planted_pool(spark, d).select("lang", "quality", "toxic", "image_vec", F.col("raw_vec").alias("text_vec"))
    each = F.explode(F.array(F.struct(F.lit("quality").alias("grp"), F.col("quality").alias("label")), F.struct(F.concat(F.lit("quality:"), "lang").alias("grp"), F.col("quality").alias("label")), F.struct(F.lit("clean").alias("grp"), (1 - F.col("toxic")).alias("label"))))
    auc = models.label_auc(marked.select(each.alias("g"), "image_vec", "text_vec").select("g.grp", "g.label", "image_vec", "text_vec"), maps)
    task(auc.filter("auc IS NOT NULL").select("model", F.col("grp").alias("task"), F.col("auc").alias("value")), "prediction", "auc")
    every = found[0]
    for one in found[1:]:
        every = every.union(one)
    return every.join(named, "model").select("recipe", "task", "kind", "metric", "value")


def suite(spark, d):
    """(recipe, task, kind, metric, value): retrieval by set, direction and class, classification, prediction of labels."""
    return _out(_suite(spark, d), "recipe", "task", "kind", "metric", "value")


def suite_results(spark, d):
    """(recipe, n_tasks, mean_value): the suite's average."""
    return _out(_suite(spark, d).groupBy("recipe").agg(F.count("*").alias("n_tasks"), F.avg("value").alias("mean_value")), "recipe", "n_tasks", "mean_value")


def suite_delta(spark, d):
    """Wins, ties, losses and mean gain over the filtered raw set: of generated text, and of generated rows added to it."""
    every = _suite(spark, d).cache()
    of = lambda r: every.filter(F.col("recipe") == r).select("task", "value")
    out = None
    for other in ("gen_top30", "mix30_filtered"):
        one = evaluate.task_delta(of(other), of("raw_top30")).select(F.lit(f"{other} over raw_top30").alias("comparison"), "*")
        out = one if out is None else out.union(one)
    return _out(out, "comparison", "n_tasks", "n_better", "n_equal", "n_worse", "mean_gain")


def sel_gen_all_tuned(spark, d):
    """The whole pool with the specialised captioner's text, as a Selection."""
    return pq._r6(recipes.select(pq.tuned_sheet(spark, d), Recipe("gen_all_ft", None, Arm())).select("pair_id", "image_id", "origin", "sim"), "sim")


def queries():
    names = "recipe_results scale_results sweep_results tune_results retr_by_recipe retr_swap suite suite_results suite_delta sel_gen_all_tuned"
    return {n: globals()[n] for n in names.split()}


def oracle_sql():
    from . import ctes as q

    tuned = q.SHEET.replace("(11 * d.doc_id + 29) % n AS g", f"({fx.TUNED_STEP} * d.doc_id + {fx.TUNED_SHIFT}) % n AS g").replace(f"{fx.GEN_WEIGHT}::DOUBLE", f"{fx.TUNED_WEIGHT}::DOUBLE")
    return {"sel_gen_all_tuned": f"WITH {tuned.strip()} SELECT pair_id, image_id, 'gen' AS origin, round(gen_sim, 6) AS sim FROM s"}
