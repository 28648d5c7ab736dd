"""Queries over the planted pool: recipes, cuts, gate, alignment, evaluation, tuning and scale."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as vx
from ..operators import alignment, diversity, evaluate, gate, rank, recipes
from ..operators import reference_metrics as rm
from ..sources import fixtures as fx
from ..sources.tables import load
from ..storage import materialise
from . import ctes as q

XS = [10.0, 20.0, 30.0, 50.0, 75.0, 90.0]
SCALES = (("small", 0.01), ("medium", 0.1), ("mid", 1 / 3), ("large", 1.0))
REGISTRY = recipes.registry()
NAMES = [r for r in REGISTRY if r not in ("raw_min", "gen_min")]


def sheet(spark: SparkSession, d: str) -> DataFrame:
    """The score sheet of the planted pool, with labels, lang and source.

    It is narrow and read several times (histogram, boundary bins, recipe), so it is kept; a lost part is computed again.
    """
    pool = fx.planted_pool(spark, d)
    return pool.select("pair_id", "image_id", vx.cosine("image_vec", "raw_vec").alias("raw_sim"), vx.cosine("image_vec", "gen_vec").alias("gen_sim"), "quality", "toxic", "lang", "source").cache()


#: The specialised captioner's planted captions.
TUNED = {"gen_weight": fx.TUNED_WEIGHT, "gen_step": fx.TUNED_STEP, "gen_shift": fx.TUNED_SHIFT}


def tuned_sheet(spark: SparkSession, d: str) -> DataFrame:
    """The score sheet with the specialised captioner's text; recipes on it don't use the gate."""
    return alignment.score_sheet(fx.planted_pool(spark, d, **TUNED)).withColumn("gated", F.lit(True)).cache()


def gated(spark: SparkSession, d: str) -> DataFrame:
    images = fx.pool_images(spark, d)
    centres = gate.seeded_centres(images, fx.centre_count(fx.image_count(spark, d)))
    return gate.gated_sheet(sheet(spark, d), gate.assign(images, centres), gate.reference_hits(fx.reference_images(spark, d), centres)).cache()


def _centres(spark: SparkSession, d: str, iterations: int = 0) -> DataFrame:
    return gate.seeded_centres(fx.pool_images(spark, d), fx.centre_count(fx.image_count(spark, d)), iterations)


def _r6(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in names})


def _select(name: str, spark: SparkSession, d: str) -> DataFrame:
    r = REGISTRY[name]
    uses_gate = any(a and a.gate for a in (r.raw, r.gen))
    got = recipes.select(gated(spark, d) if uses_gate else sheet(spark, d), r)
    return _r6(got.select("pair_id", "image_id", "origin", "sim"), "sim")


def sim_rows(spark, d):
    return _r6(sheet(spark, d).select("pair_id", "raw_sim", "gen_sim"), "raw_sim", "gen_sim")


def sim_rows_arrow(spark, d):
    return _r6(alignment.score_sheet(fx.planted_pool(spark, d), "arrow").select("pair_id", "raw_sim", "gen_sim"), "raw_sim", "gen_sim")


def cut_points(spark, d):
    s = sheet(spark, d)
    found = rank.cuts(s, "raw_sim", XS)
    return spark.createDataFrame([(c.x, c.k, round(c.sim, 6), c.id) for c in found.values()], "x double, k bigint, cut_sim double, cut_id bigint")


def sweep_cuts(spark, d):
    s = sheet(spark, d)
    rows = [(col, float(x), c.k, round(c.sim, 6), c.id) for col in ("raw_sim", "gen_sim") for x, c in rank.cuts(s, col, [float(x) for x in range(5, 101, 5)]).items()]
    return spark.createDataFrame(rows, "score string, x double, k bigint, cut_sim double, cut_id bigint")


def topk_pairs(spark, d):
    return _r6(rank.top_k(sheet(spark, d), "raw_sim", 25).select("pair_id", "raw_sim"), "raw_sim")


def discarded_sample(spark, d):
    s = sheet(spark, d)
    cut = rank.cuts(s, "raw_sim", [30.0])[30.0]
    rest = s.filter(~cut.covers_rank(F.col("raw_sim"), F.col("pair_id"))).withColumn("place", fx.salted("pair_id", "discarded"))
    few = rest.orderBy("place", "pair_id").limit(20)
    docs = load(spark, d, "documents").select(F.col("doc_id").alias("pair_id"), F.md5(F.col("text").cast("binary")).alias("text_md5"))
    return _r6(docs.join(F.broadcast(few), "pair_id").select("pair_id", "raw_sim", "text_md5"), "raw_sim")


def recipe_sheet(spark, d):
    return _r6(recipes.recipe_sheet(gated(spark, d), [REGISTRY[n] for n in NAMES]), "mean_sim", "rel_size")


def recipe_pivot(spark, d):
    long = recipe_sheet(spark, d).select("recipe", F.expr("stack(3, 'n_rows', n_rows, 'n_raw', n_raw, 'n_gen', n_gen) AS (metric, value)"))
    return long.groupBy("recipe").pivot("metric", ["n_gen", "n_raw", "n_rows"]).agg(F.first("value"))


def sel_best_of(spark, d):
    return _r6(recipes.best_of(sheet(spark, d)), "sim")


def sel_multi(spark, d):
    return _r6(recipes.multi_source(alignment.long_scores(sheet(spark, d))), "sim")


def gate_assign(spark, d):
    return gate.assign(fx.pool_images(spark, d), _centres(spark, d)).withColumn("cid", F.col("cid").cast("bigint"))


def gate_assign_expression(spark, d):
    return gate.assign_expression(fx.pool_images(spark, d), _centres(spark, d)).withColumn("cid", F.col("cid").cast("bigint"))


def gate_centres_iter1(spark, d):
    return _centres(spark, d, 1).select(F.col("cid").cast("bigint").alias("cid"), F.posexplode("centre").alias("dim", "value")).select("cid", F.col("dim").cast("bigint").alias("dim"), F.round("value", 6).alias("value"))


def gate_hits(spark, d):
    return gate.reference_hits(fx.reference_images(spark, d), _centres(spark, d)).select(F.col("cid").cast("bigint").alias("cid"), "n_hits")


def _gate_keep(drop, spark, d):
    c = _centres(spark, d)
    return gate.keep(gate.assign(fx.pool_images(spark, d), c), gate.reference_hits(fx.reference_images(spark, d), c), drop).withColumn("cid", F.col("cid").cast("bigint"))


def gate_report(spark, d):
    c = _centres(spark, d)
    return gate.report(gate.assign(fx.pool_images(spark, d), c), gate.reference_hits(fx.reference_images(spark, d), c)).withColumn("cid", F.col("cid").cast("bigint"))


def gate_nearest2(spark, d):
    """The gate's other reading: every reference image keeps its two nearest clusters."""
    return gate.reference_hits(fx.reference_images(spark, d), _centres(spark, d), nearest=2).select(F.col("cid").cast("bigint").alias("cid"), "n_hits")


def gate_two_level(spark, d):
    """How far the two-level assignment agrees with the flat one: (n_images, n_equal, share)."""
    images, centres = fx.pool_images(spark, d), _centres(spark, d)
    flat, near = gate.assign(images, centres), gate.assign_two_level(images, centres).select("image_id", F.col("cid").alias("other"))
    both = flat.join(near, "image_id").agg(F.count("*").alias("n_images"), F.count_if(F.col("cid") == F.col("other")).alias("n_equal"))
    return _r6(both.withColumn("share", F.col("n_equal") / F.col("n_images")), "share")


def kmeans_gate(spark, d):
    images = fx.pool_images(spark, d)
    return gate.assign(images, gate.kmeans_centres(images, 16), metric="euclid").groupBy("cid").count()


def noise_mean(spark, d):
    return _r6(alignment.mean_similarity(alignment.long_scores(sheet(spark, d))), "mean_sim")


def sim_hist(spark, d):
    return alignment.histogram(alignment.long_scores(sheet(spark, d)))


def sim_hist_sample(spark, d):
    """The same over a one-percent sample."""
    from ..operators.prep import subpool

    return alignment.histogram(alignment.long_scores(subpool(sheet(spark, d), 0.01, "one_percent")))


def sim_quantiles(spark, d):
    return _r6(alignment.quantiles(alignment.long_scores(sheet(spark, d))), "value")


def ref_free(spark, d):
    return _r6(alignment.reference_free(alignment.long_scores(sheet(spark, d))), "ref_free")


def sim_paired(spark, d):
    return _r6(alignment.paired(sheet(spark, d)), "mean_diff", "sd_diff")


def sweep_curves(spark, d):
    return _r6(evaluate.sweep_curves(sheet(spark, d), XS), "mean_sim")


def tune_grid(spark, d):
    return evaluate.tune(evaluate.sweep_curves(sheet(spark, d), XS))


def tune_transfer(spark, d):
    """Percents tuned on the medium subpool, reused at every scale: (scale, curve, x, n_rows, mean_sim).

    The percent is what is carried over; each scale finds its own cut for it.
    """
    s = sheet(spark, d).withColumn("_u", fx.salted("pair_id", "scale"))
    parts = {name: s.filter(F.col("_u") < int(share * (1 << 32))) if share < 1 else s for name, share in SCALES}
    tuned = {r["curve"]: r["x"] for r in evaluate.tune(evaluate.sweep_curves(parts["medium"], XS)).collect()}  # one row a curve
    keep = F.create_map(*[F.lit(v) for kv in tuned.items() for v in kv])
    out = None
    for name, part in parts.items():
        one = evaluate.sweep_curves(part, sorted(set(tuned.values()))).filter(F.col("x") == F.element_at(keep, F.col("curve"))).select(F.lit(name).alias("scale"), "curve", "x", "n_rows", "mean_sim")
        out = one if out is None else out.unionByName(one)
    return _r6(out, "mean_sim")


def leveled(s: DataFrame) -> DataFrame:
    """The sheet with the smallest of the nested scales that each row belongs to, from one salted number."""
    level = F.lit(len(SCALES) - 1)
    for k in reversed(range(len(SCALES) - 1)):
        level = F.when(fx.salted("pair_id", "scale") < int(SCALES[k][1] * (1 << 32)), F.lit(k)).otherwise(level)
    return s.withColumn("level", level)


SCALE_RECIPES = ["raw_all", "gen_all", "raw_top30", "gen_top50", "raw_top30_gate", "gen_top75_gate", "mix30_filtered", "mix30_filtered_gate"]


def scale_grid(spark, d):
    """Sizes and mean similarities of recipes over nested subpools, from one scan of masks."""
    s = leveled(gated(spark, d))
    plans = recipes.plan_scales(s, [REGISTRY[r] for r in SCALE_RECIPES], [n for n, _ in SCALES])
    masks = materialise(recipes.arrow_masks(s, [p for _, p in plans]), "masks")
    found = recipes.mask_sheet(masks, [(n, p.recipe.name) for n, p in plans])
    return _r6(found.select("scale", "recipe", "n_rows", "mean_sim"), "mean_sim")


def noise_by_scale(spark, d):
    s = sheet(spark, d).withColumn("_u", fx.salted("pair_id", "scale"))
    scales = F.explode(F.filter(F.array(*[F.when(F.col("_u") < int(share * (1 << 32)) if share < 1 else F.lit(True), F.lit(name)) for name, share in SCALES]), lambda x: x.isNotNull()))
    long = s.withColumn("scale", scales).select("scale", F.expr("stack(2, 'raw', raw_sim, 'gen', gen_sim) AS (origin, sim)"))
    return _r6(long.groupBy("scale", "origin").agg(F.count("*").alias("n_rows"), F.avg("sim").alias("mean_sim")), "mean_sim")


def budget_draws(spark, d):
    s = sheet(spark, d)
    chosen = recipes.select(s, REGISTRY["mix30_filtered"])
    return evaluate.budget_copies(chosen, s.count())


def gram(spark, d):
    pool = fx.planted_pool(spark, d).select(F.col("raw_vec").alias("text_vec"), "image_vec")
    return evaluate.gram_entries(pool).select("kind", F.col("row_dim").cast("bigint").alias("row_dim"), F.col("col_dim").cast("bigint").alias("col_dim"), F.round("value", 4).alias("value"))


def retr_rk(spark, d):
    got = evaluate.retrieval(fx.evaluation_set(spark, d))
    return _r6(got.select("direction", F.col("k").cast("bigint").alias("k"), F.col("recall").cast("double").alias("recall")), "recall")


def retr_r1(spark, d):
    return _r6(evaluate.retrieval_score(fx.evaluation_set(spark, d)), "score")


def retr_mean(spark, d):
    """Mean over two evaluation sets: the usual one and one of noisier captions."""
    two = evaluate.retrieval_score(fx.evaluation_set(spark, d)).union(evaluate.retrieval_score(fx.evaluation_set(spark, d, 3.85)))
    return _r6(two.agg(F.avg("score").alias("score")), "score")


def zs_label(spark, d):
    imgs = fx.images(spark, d)
    n = fx.image_count(spark, d)
    train, test = imgs.filter(F.col("image_id") >= n // 5), imgs.filter((F.col("image_id") >= n // 10) & (F.col("image_id") < n // 5))
    protos = evaluate.class_prototypes(train, "label", "vec")
    return _r6(evaluate.zero_shot(test.select("image_id", "vec", F.col("label").alias("class")), protos).select(F.col("k").cast("bigint").alias("k"), F.col("accuracy").cast("double").alias("accuracy")), "accuracy")


def zs_cluster(spark, d):
    centres = _centres(spark, d)
    items = fx.evaluation_set(spark, d)
    truth = gate.assign(items.select(F.col("item_id").alias("image_id"), F.col("image_vec").alias("vec")), centres)
    rows = items.select(F.col("item_id").alias("image_id"), F.col("text_vec").alias("vec")).join(truth, "image_id").select("image_id", "vec", F.col("cid").alias("class"))
    return _r6(evaluate.zero_shot(rows, centres.select(F.col("cid").alias("class"), F.col("centre").alias("proto"))).select(F.col("k").cast("bigint").alias("k"), F.col("accuracy").cast("double").alias("accuracy")), "accuracy")


def _suite(spark, d, x=30.0, by="raw"):
    """(task, value): closed-form tasks over a selection's rows, by language and source."""
    s = sheet(spark, d)
    col = f"{by}_sim"
    kept = rank.top_percent(s, col, x)
    langs = kept.groupBy(F.concat(F.lit("mean_sim:"), "lang").alias("task")).agg(F.avg(col).alias("value"))
    quality = kept.select(F.lit("quality_rate").alias("task"), F.col("quality").cast("double").alias("v")).groupBy("task").agg(F.avg("v").alias("value"))
    clean = kept.select(F.lit("clean_rate").alias("task"), (1 - F.col("toxic")).cast("double").alias("v")).groupBy("task").agg(F.avg("v").alias("value"))
    return langs.union(quality).union(clean)


def suite_avg(spark, d):
    return _r6(_suite(spark, d).agg(F.count("*").alias("n_tasks"), F.avg("value").alias("mean_value")), "mean_value")


def task_delta(spark, d):
    return _r6(evaluate.task_delta(_suite(spark, d, by="gen"), _suite(spark, d, by="raw")), "mean_gain")


def gain_vs_base(spark, d):
    """Each recipe's mean similarity on the planted pool against that of raw_top30."""
    found = recipes.recipe_sheet(gated(spark, d), [REGISTRY[n] for n in NAMES]).select("recipe", "mean_sim")
    return _r6(evaluate.gain_over(found, "raw_top30", value="mean_sim"), "mean_sim", "ratio", "points")


#: What is compared over the sources of the pool: mean scores, and the shares that labels give.
AGREED, OUTCOMES = ("raw_sim", "gen_sim", "gain"), ("quality", "toxic")


def metric_agreement(spark, d):
    """(metric, outcome, pearson, spearman): do a source's mean scores go with its labelled quality and toxicity?"""
    s = sheet(spark, d).withColumn("gain", F.col("gen_sim") - F.col("raw_sim"))
    by = s.filter("source IS NOT NULL").groupBy("source").agg(*[F.avg(c).alias(c) for c in (*AGREED, *OUTCOMES)])
    return _r6(rm.metric_agreement(by.dropna(), AGREED, OUTCOMES), "pearson", "spearman")


def enrich_quality(spark, d):
    s = sheet(spark, d)
    out = None
    for name in ("raw_all", "raw_top30", "gen_top30", "mix30_filtered"):
        one = evaluate.enrichment(s, recipes.select(s, REGISTRY[name])).select(F.lit(name).alias("recipe"), "*")
        out = one if out is None else out.union(one)
    return _r6(out, "precision", "recall", "toxic_share")


def cluster_entropy(spark, d):
    s = gated(spark, d)
    return _r6(diversity.cluster_entropy(recipes.select(s, REGISTRY["raw_top30"]).select("cid")), "entropy")


def retention_group(spark, d):
    s = sheet(spark, d)
    kept = recipes.select(s, REGISTRY["raw_top30"]).select("pair_id")
    out = diversity.retention(s, kept, "lang").withColumn("kind", F.lit("lang")).union(diversity.retention(s, kept, "source").withColumn("kind", F.lit("source")))
    return _r6(out, "rate", "disparity")


def approx_cut(spark, d):
    s = sheet(spark, d)
    return spark.createDataFrame([(x, rank.approx_cut(s, "raw_sim", x), rank.kll_cut(s, "raw_sim", x)) for x in (10.0, 30.0, 50.0)], "x double, percentile_cut double, kll_cut double")


def queries():
    out = {f"sel_{n}": partial(_select, n) for n in REGISTRY}
    names = (
        "sim_rows sim_rows_arrow cut_points sweep_cuts topk_pairs discarded_sample recipe_sheet recipe_pivot sel_best_of sel_multi gate_assign gate_assign_expression gate_centres_iter1 gate_hits gate_report gate_nearest2 gate_two_level "
        "kmeans_gate noise_mean sim_hist sim_hist_sample sim_quantiles ref_free sim_paired sweep_curves tune_grid tune_transfer scale_grid noise_by_scale budget_draws gram retr_rk retr_r1 retr_mean zs_label zs_cluster suite_avg "
        "task_delta gain_vs_base metric_agreement enrich_quality cluster_entropy retention_group approx_cut"
    )
    out |= {n: globals()[n] for n in names.split()}
    out |= {"gate_keep": partial(_gate_keep, False), "gate_drop": partial(_gate_keep, True)}
    return out


def _gain_sql() -> str:
    rows = " UNION ALL ".join(f"SELECT '{n}' AS recipe, * FROM ({q.RECIPES[n]})" for n in NAMES)
    return q.everything(f" x AS ({rows}), m AS (SELECT recipe, avg(sim) AS m FROM x GROUP BY recipe), b AS (SELECT m AS b FROM m WHERE recipe = 'raw_top30')") + " SELECT recipe, round(m, 6) AS mean_sim, round(m / b, 6) AS ratio, round(m - b, 6) AS points FROM m CROSS JOIN b"


def _agreement_sql() -> str:
    pairs = [(m, o) for m in AGREED for o in OUTCOMES]
    by = "by_source AS (SELECT source, avg(raw_sim) AS raw_sim, avg(gen_sim) AS gen_sim, avg(gen_sim - raw_sim) AS gain, avg(quality) AS quality, avg(toxic) AS toxic FROM s WHERE source IS NOT NULL GROUP BY source), full_ AS (SELECT * FROM by_source WHERE raw_sim IS NOT NULL AND gen_sim IS NOT NULL AND gain IS NOT NULL AND quality IS NOT NULL AND toxic IS NOT NULL)"
    return f"WITH {q.SHEET.strip()}, {by} " + " UNION ALL ".join(f"SELECT '{m}' AS metric, '{o}' AS outcome, round(corr({m}, {o}), 6) AS pearson, round(corr(rm, ro), 6) AS spearman FROM (SELECT {m}, {o}, rank() OVER (ORDER BY {m})::DOUBLE AS rm, rank() OVER (ORDER BY {o})::DOUBLE AS ro FROM full_)" for m, o in pairs)


def _union_sheets() -> str:
    rows = " UNION ALL ".join(f"SELECT '{n}' AS recipe, * FROM ({q.RECIPES[n]})" for n in NAMES)
    return q.everything(f" x AS ({rows})") + " SELECT recipe, count(*) AS n_rows, count(*) FILTER (origin = 'raw') AS n_raw, count(*) FILTER (origin = 'gen') AS n_gen, round(avg(sim), 6) AS mean_sim, round(count(*) / (SELECT count(*) FROM s), 6) AS rel_size FROM x GROUP BY recipe"


def _transfer() -> str:
    body = _sweep(XS).split(", c AS (", 1)[1]
    full = q.SHEET.strip().replace("\ns AS (", "\nfull_s AS (")
    parts = [f"SELECT '{name}' AS scale, * FROM (WITH s AS (SELECT * FROM full_s WHERE {q.salted('pair_id', 'scale')} < {int(share * (1 << 32))}), c AS ({body.replace('round(avg(sim), 6)', 'avg(sim)')})" for name, share in SCALES]
    return f"WITH {full}, every AS ({' UNION ALL '.join(parts)}), best AS (SELECT curve, x FROM every WHERE scale = 'medium' AND mean_sim IS NOT NULL QUALIFY row_number() OVER (PARTITION BY curve ORDER BY round(mean_sim * sqrt(n_rows), 9) DESC, x) = 1) SELECT scale, curve, x, n_rows, round(mean_sim, 6) AS mean_sim FROM every JOIN best USING (curve, x)"


def _sweep(xs) -> str:
    parts = []
    for x in xs:
        t, g = q.top("raw_sim", x), q.top("gen_sim", x)
        cut = f"(SELECT min(raw_sim) FROM s WHERE pair_id IN {t})"
        for curve, sim in (("raw", f"CASE WHEN pair_id IN {t} THEN raw_sim END"), ("raw_plus_some", f"CASE WHEN pair_id IN {t} THEN raw_sim WHEN gen_sim >= {cut} THEN gen_sim END"), ("raw_plus_all", f"CASE WHEN pair_id IN {t} THEN raw_sim ELSE gen_sim END"), ("gen", f"CASE WHEN pair_id IN {g} THEN gen_sim END")):
            parts.append(f"SELECT {x}::DOUBLE AS x, '{curve}' AS curve, {sim} AS sim FROM s")
    return f"WITH {q.SHEET.strip()}, c AS ({' UNION ALL '.join(parts)}) SELECT x, curve, count(sim) AS n_rows, round(avg(sim), 6) AS mean_sim FROM c GROUP BY x, curve"


def _cuts(col: str, xs, label: str = "") -> str:
    return " UNION ALL ".join(f"SELECT {label}{x}::DOUBLE AS x, rn AS k, round({col}, 6) AS cut_sim, pair_id AS cut_id FROM (SELECT {col}, pair_id, row_number() OVER (ORDER BY {col} DESC, pair_id) AS rn FROM s) WHERE rn = (SELECT ceil({x} * count(*) / 100.0) FROM s)" for x in xs)


def _scale_grid() -> str:
    parts = []
    for name, share in SCALES:
        pre = f"WITH s AS (SELECT * FROM full_s WHERE {q.salted('pair_id', 'scale')} < {int(share * (1 << 32))}), {q.TOP30.strip()} "
        rows = " UNION ALL ".join(f"SELECT '{r}' AS recipe, * FROM ({q.RECIPES[r]})" for r in SCALE_RECIPES)
        parts.append(f"SELECT * FROM ({pre} SELECT '{name}' AS scale, recipe, count(*) AS n_rows, round(avg(sim), 6) AS mean_sim FROM ({rows}) GROUP BY recipe)")
    sheet_sql = q.SHEET.strip().replace("\ns AS (", "\nfull_s AS (")
    return f"WITH {sheet_sql}, {q.GATE.strip()} {' UNION ALL '.join(parts)}"


_LONG = "long AS (SELECT pair_id, 'raw' AS origin, raw_sim AS sim FROM s UNION ALL SELECT pair_id, 'gen', gen_sim FROM s)"
_HIST = "SELECT origin, least(floor((sim + 1.0) / 0.05), 39)::BIGINT AS bin, count(*) AS n_rows FROM long WHERE sim IS NOT NULL {0} GROUP BY ALL"


def _suite_sql(name: str, col: str) -> str:
    top = q.top(col, 30)
    return f"{name} AS (SELECT 'mean_sim:' || lang AS task, avg({col}) AS value FROM s WHERE pair_id IN {top} GROUP BY lang UNION ALL SELECT 'quality_rate', avg(quality::DOUBLE) FROM s WHERE pair_id IN {top} UNION ALL SELECT 'clean_rate', avg((1 - toxic)::DOUBLE) FROM s WHERE pair_id IN {top})"


def oracle_sql():
    S = f"WITH {q.SHEET.strip()}"
    G = f"WITH {q.VECTORS.strip()}, {q.GATE.strip()}"
    E = f"WITH {q.EVALUATION.strip()}"
    out = {f"sel_{n}": f"SELECT pair_id, image_id, origin, round(sim, 6) AS sim FROM ({q.recipe(n)})" for n in REGISTRY}
    sims = f"{S} SELECT pair_id, round(raw_sim, 6) AS raw_sim, round(gen_sim, 6) AS gen_sim FROM s"
    out |= {
        "sim_rows": sims,
        "sim_rows_arrow": sims,
        "cut_points": f"{S} {_cuts('raw_sim', XS)}",
        "sweep_cuts": S + " " + " UNION ALL ".join(_cuts(c, [float(x) for x in range(5, 101, 5)], f"'{c}' AS score, ") for c in ("raw_sim", "gen_sim")),
        "topk_pairs": f"{S} SELECT pair_id, round(raw_sim, 6) AS raw_sim FROM s ORDER BY s.raw_sim DESC, pair_id LIMIT 25",
        "discarded_sample": f"WITH {q.SHEET.strip()}, {q.TOP30.strip()}, few AS (SELECT * FROM rest ORDER BY {q.salted('pair_id', 'discarded')}, pair_id LIMIT 20) SELECT pair_id, round(raw_sim, 6) AS raw_sim, md5(text) AS text_md5 FROM few JOIN documents ON doc_id = pair_id",
        "recipe_sheet": _union_sheets(),
        "recipe_pivot": f"SELECT recipe, n_gen, n_raw, n_rows FROM ({_union_sheets()})",
        "sel_best_of": f"{S} SELECT pair_id, image_id, CASE WHEN gen_sim > raw_sim THEN 'gen' ELSE 'raw' END AS origin, round(greatest(raw_sim, gen_sim), 6) AS sim FROM s",
        "sel_multi": f"{S} SELECT pair_id, CASE WHEN gen_sim >= raw_sim THEN 'gen' ELSE 'raw' END AS origin, round(greatest(raw_sim, gen_sim), 6) AS sim FROM s",
        "gate_assign": f"{G} SELECT image_id, cid FROM assigned",
        "gate_assign_expression": f"{G} SELECT image_id, cid FROM assigned",
        "gate_centres_iter1": f"{G}, near AS (SELECT a.cid, p.v FROM assigned a JOIN pool_images p USING (image_id)), el AS (SELECT cid, unnest(range(64)) AS dim, unnest(v) AS x FROM near) SELECT cid, dim, round(avg(x), 6) AS value FROM el GROUP BY cid, dim UNION ALL SELECT cid, unnest(range(64)), round(unnest(v), 6) FROM centres WHERE cid NOT IN (SELECT cid FROM near)",
        "gate_hits": f"{G} SELECT cid, n_hits FROM hits",
        "gate_keep": f"{G} SELECT image_id, cid FROM kept",
        "gate_drop": f"{G} SELECT image_id, cid FROM assigned WHERE cid NOT IN (SELECT cid FROM hits)",
        "gate_report": f"{G} SELECT a.cid, count(*) AS n_images, coalesce(any_value(n_hits), 0) AS n_hits, any_value(n_hits) IS NOT NULL AS kept FROM assigned a LEFT JOIN hits ON hits.cid = a.cid GROUP BY a.cid",
        "gate_nearest2": f"{G} SELECT cid, count(*) AS n_hits FROM (SELECT e.vec_id, c.cid, row_number() OVER (PARTITION BY e.vec_id ORDER BY list_inner_product(e.v, c.v) DESC, c.cid) AS rn FROM e CROSS JOIN centres c CROSS JOIN n WHERE e.vec_id < n // 10 AND label < 5) WHERE rn <= 2 GROUP BY cid",
        "noise_mean": f"{S}, {_LONG} SELECT origin, round(avg(sim), 6) AS mean_sim, count(sim) AS n_rows FROM long GROUP BY origin",
        "sim_hist": f"{S}, {_LONG} {_HIST.format('')}",
        "sim_hist_sample": f"{S}, {_LONG} " + _HIST.format(f"AND {q.salted('pair_id', 'one_percent')} < {int(0.01 * (1 << 32))}"),
        "sim_quantiles": f"{S}, {_LONG} " + " UNION ALL ".join(f"SELECT origin, {p}::DOUBLE AS share, round(quantile_cont(sim, {p}), 6) AS value FROM long GROUP BY origin" for p in (0.1, 0.25, 0.5, 0.75, 0.9)),
        "ref_free": f"{S}, {_LONG} SELECT origin, round(avg(2.5 * greatest(sim, 0)), 6) AS ref_free FROM long GROUP BY origin",
        "sim_paired": f"{S} SELECT count(*) AS n_rows, count(*) FILTER (gen_sim > raw_sim) AS n_better, round(avg(gen_sim - raw_sim), 6) AS mean_diff, round(stddev_samp(gen_sim - raw_sim), 6) AS sd_diff FROM s",
        "sweep_curves": _sweep(XS),
        "tune_grid": f"SELECT curve, x FROM (SELECT curve, x, row_number() OVER (PARTITION BY curve ORDER BY round(mean_sim * sqrt(n_rows), 9) DESC, x) AS rn FROM ({_sweep(XS).replace('round(avg(sim), 6)', 'avg(sim)')})) WHERE rn = 1",
        "tune_transfer": _transfer(),
        "scale_grid": _scale_grid(),
        "noise_by_scale": f"{S}, {_LONG} " + " UNION ALL ".join(f"SELECT '{n}' AS scale, origin, count(*) AS n_rows, round(avg(sim), 6) AS mean_sim FROM long WHERE {q.salted('pair_id', 'scale')} < {int(share * (1 << 32))} GROUP BY origin" for n, share in SCALES),
        "budget_draws": f"{q.everything()}, sel AS ({q.RECIPES['mix30_filtered']}), m AS (SELECT count(*) AS m, (SELECT count(*) FROM s) AS total FROM sel) SELECT pair_id, (total // m + CASE WHEN row_number() OVER (ORDER BY {q.salted('pair_id', 'budget')}, pair_id) <= total % m THEN 1 ELSE 0 END)::BIGINT AS copies FROM sel, m QUALIFY copies > 0",
        "gram": f"WITH {q.VECTORS.strip()}, p AS (SELECT i.v AS iv, {q.mixed('i.v', 'rv.v', 'w')} AS tv FROM pairs JOIN e i ON i.vec_id = image_id JOIN e rv ON rv.vec_id = pairs.r), el AS (SELECT iv, tv, unnest(range(64)) AS row_dim FROM p), el2 AS (SELECT iv, tv, row_dim, unnest(range(64)) AS col_dim FROM el) SELECT 'tt' AS kind, row_dim, col_dim, round(sum(tv[row_dim + 1] * tv[col_dim + 1]), 4) AS value FROM el2 GROUP BY ALL UNION ALL SELECT 'ti', row_dim, col_dim, round(sum(tv[row_dim + 1] * iv[col_dim + 1]), 4) FROM el2 GROUP BY ALL",
        "retr_rk": E + " " + " UNION ALL ".join(f"SELECT '{t}' AS direction, {k}::BIGINT AS k, round(avg(CASE WHEN rn <= {k} THEN 1.0 ELSE 0.0 END), 6)::DOUBLE AS recall FROM {t}" for t in ("t2i", "i2t") for k in (1, 5, 10)),
        "retr_r1": f"{E} SELECT round(((SELECT avg((rn = 1)::INT) FROM t2i) + (SELECT avg((rn = 1)::INT) FROM i2t)) / 2, 6) AS score",
        "zs_label": f"WITH {q.VECTORS.strip()}, protos AS (SELECT label, list(x ORDER BY dim) AS p FROM (SELECT label, dim, avg(x) AS x FROM (SELECT label, unnest(range(64)) AS dim, unnest(v) AS x FROM e, n WHERE vec_id >= n // 5) GROUP BY label, dim) GROUP BY label), r AS (SELECT e.label, p.label AS guess, row_number() OVER (PARTITION BY vec_id ORDER BY list_inner_product(v, p) DESC, p.label) AS rn FROM e CROSS JOIN protos p CROSS JOIN n WHERE vec_id >= n // 10 AND vec_id < n // 5) " + " UNION ALL ".join(f"SELECT {k}::BIGINT AS k, round(count(*) FILTER (rn <= {k}) / (SELECT count(DISTINCT vec_id) FROM e, n WHERE vec_id >= n // 10 AND vec_id < n // 5), 6) AS accuracy FROM r WHERE label = guess" for k in (1, 5)),
        "zs_cluster": f"WITH {q.EVALUATION.strip()}, {q.GATE.strip()}, r AS (SELECT nearest.cid AS truth, c.cid AS guess, row_number() OVER (PARTITION BY item_id ORDER BY list_inner_product(tv, c.v) DESC, c.cid) AS rn FROM items JOIN nearest ON nearest.vec_id = item_id CROSS JOIN centres c) " + " UNION ALL ".join(f"SELECT {k}::BIGINT AS k, round(count(*) FILTER (rn <= {k}) / (SELECT count(*) FROM items), 6) AS accuracy FROM r WHERE truth = guess" for k in (1, 5)),
        "suite_avg": f"{S}, {_suite_sql('a', 'raw_sim')} SELECT count(*) AS n_tasks, round(avg(value), 6) AS mean_value FROM a",
        "task_delta": f"{S}, {_suite_sql('a', 'gen_sim')}, {_suite_sql('b', 'raw_sim')} SELECT count(*) AS n_tasks, count(*) FILTER (a.value > b.value) AS n_better, count(*) FILTER (a.value = b.value) AS n_equal, count(*) FILTER (a.value < b.value) AS n_worse, round(avg(a.value - b.value), 6) AS mean_gain FROM a JOIN b USING (task)",
        "gain_vs_base": _gain_sql(),
        "metric_agreement": _agreement_sql(),
        "enrich_quality": f"{q.everything()} " + " UNION ALL ".join(f"SELECT '{r}' AS recipe, count(*) FILTER (k) AS n_rows, round(count(*) FILTER (k AND quality = 1) / count(*) FILTER (k AND quality IS NOT NULL), 6) AS precision, round(count(*) FILTER (k AND quality = 1) / count(*) FILTER (quality = 1), 6) AS recall, round(count(*) FILTER (k AND toxic = 1) / count(*) FILTER (k AND toxic IS NOT NULL), 6) AS toxic_share FROM (SELECT quality, toxic, pair_id IN (SELECT pair_id FROM ({q.RECIPES[r]})) AS k FROM s)" for r in ("raw_all", "raw_top30", "gen_top30", "mix30_filtered")),
        "cluster_entropy": f"{q.everything()}, c AS (SELECT cid, count(*) AS n FROM t30 JOIN assigned USING (image_id) GROUP BY cid) SELECT count(*) AS n_clusters, round(-sum(n / total * ln(n / total)), 6) AS entropy FROM c, (SELECT sum(n) AS total FROM c)",
        "retention_group": f"WITH {q.SHEET.strip()}, {q.TOP30.strip()}, r AS (" + " UNION ALL ".join(f"SELECT '{g}' AS kind, {g} AS grp, count(*) AS n_rows, count(*) FILTER (pair_id IN (SELECT pair_id FROM t30)) AS n_kept FROM s GROUP BY {g}" for g in ("lang", "source")) + ") SELECT kind, grp, n_rows, n_kept, round(n_kept / n_rows, 6) AS rate, round((n_kept / n_rows) / max(n_kept / n_rows) OVER (PARTITION BY kind), 6) AS disparity FROM r",
    }
    noisy = q.EVALUATION.strip().replace("2.5::DOUBLE", "3.85::DOUBLE")
    score = "SELECT ((SELECT avg((rn = 1)::INT) FROM t2i) + (SELECT avg((rn = 1)::INT) FROM i2t)) / 2 AS s"
    out["retr_mean"] = f"SELECT round(avg(s), 6) AS score FROM (SELECT * FROM (WITH {q.EVALUATION.strip()} {score}) UNION ALL SELECT * FROM (WITH {noisy} {score}))"
    return out
