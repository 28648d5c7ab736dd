"""Many models at once against NumPy, brute force and the single-set forms; corner cases of cuts and recipes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from capmix.operators import evaluate, gate, models, rank, recipes
from capmix.operators.recipes import Arm, Recipe
from capmix.plans import caption_queries as cq
from capmix.plans import catalogue
from capmix.plans import model_queries as mq
from capmix.plans import pool_queries as pq
from capmix.sources import fixtures as fx
from tests.conftest import SMOKE


@pytest.fixture(scope="module")
def sheet(spark):
    return pq.leveled(pq.gated(spark, SMOKE)).cache()


NAMES = ["raw_all", "raw_top30", "mix30_filtered", "gen_top75_gate", "swap30", "gen_min", "rest_filtered"]


def bits(df):
    return {(r["pair_id"], r["raw_mask"], r["gen_mask"]) for r in df.collect() if r["raw_mask"] or r["gen_mask"]}


def test_arrow_masks_equal_expressions(sheet):
    scored = sheet.withColumn("raw_sim", F.when(F.col("pair_id") % 11 == 0, F.lit(float("nan"))).when(F.col("pair_id") % 13 != 0, F.col("raw_sim")))
    plans = recipes.plan(scored, [pq.REGISTRY[n] for n in NAMES])
    assert bits(recipes.arrow_masks(scored, plans)) == bits(recipes.with_masks(scored, plans).select("pair_id", "raw_mask", "gen_mask"))


def test_scales_equal_single_scales(sheet):
    names = [n for n, _ in pq.SCALES]
    plans = recipes.plan_scales(sheet, [pq.REGISTRY[n] for n in NAMES], names)
    rows = recipes.arrow_masks(sheet, [p for _, p in plans]).collect()
    for k, (scale, p) in enumerate(plans):
        inside = sheet.filter(F.col("level") <= names.index(scale))
        want = {(r["pair_id"], r["origin"]) for r in recipes.select(inside, p.recipe).collect()}
        assert {(r["pair_id"], o) for r in rows for o in ("raw", "gen") if r[f"{o}_mask"] >> k & 1} == want


def test_nested_cuts_equal_cuts(sheet):
    xs = [0.0, 1.0, 30.0, 77.0, 100.0]
    for bin_rows in (10**6, 1):
        got = rank.nested_cuts(sheet, "raw_sim", xs, "level", 4, bin_rows=bin_rows)
        for t in range(4):
            assert {x: got[t, x] for x in xs} == rank.cuts(sheet.filter(F.col("level") <= t), "raw_sim", xs)


@pytest.mark.parametrize("samples", [[10, 200], [201, 65]])
def test_budgets_equal_single_budgets(sheet, samples):
    some = [pq.REGISTRY["raw_top30"], pq.REGISTRY["mix30_filtered"]]
    masks = recipes.arrow_masks(sheet, recipes.plan(sheet, some))
    rules = models.budgets(masks, samples)
    for k, (r, n) in enumerate(zip(some, samples, strict=True)):
        want = {x["pair_id"]: x["copies"] for x in evaluate.budget_copies(recipes.select(sheet, r), n).collect()}
        own = masks.filter(F.col("raw_mask").bitwiseOR(F.col("gen_mask")).bitwiseAND(1 << k) != 0).select("pair_id", fx.salted("pair_id", "budget").alias("u")).toPandas()
        got = rules[k].copies(own.u.to_numpy(), own.pair_id.to_numpy())
        assert {i: c for i, c in zip(own.pair_id, got, strict=True) if c} == want and sum(want.values()) == n


def test_budget_of_many_rows_is_exact(spark):
    m, n = 1_000_003, 1_700_011  # the percent form of this share was one row off
    got = evaluate.budget_copies(spark.range(m).withColumnRenamed("id", "pair_id"), n).agg(F.sum("copies")).first()[0]
    assert got == n


def plain_ranks(own, others):
    return [1 + sum(1 for j, s in enumerate(row) if j != k and (s > row[k] + 1e-12 or (abs(s - row[k]) <= 1e-12 and j < k))) for k, row in enumerate(own @ others.T)]


def test_training_and_retrieval_against_numpy(spark, sheet):
    """retr_by_recipe's figures from a plain NumPy trainer and evaluator."""
    pool = fx.planted_pool(spark, SMOKE).select("pair_id", "image_vec", "raw_vec", "gen_vec").toPandas().set_index("pair_id")
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    sets = [fx.evaluation_set(spark, SMOKE, w).orderBy("item_id").toPandas() for w in (fx.EVAL_WEIGHT, mq.NOISY)]
    got = {r["recipe"]: r for r in mq.retr_by_recipe(spark, SMOKE).collect()}
    assert set(got) == set(mq.TABLE)
    for name in ("raw_top30", "mix30_filtered", "gen_top75_gate"):
        chosen = recipes.select(sheet, pq.REGISTRY[name])
        rows = chosen.join(evaluate.budget_copies(chosen, sheet.count()), "pair_id").collect()
        t = np.array([pool.loc[r["pair_id"], f"{r['origin']}_vec"] for r in rows])
        i = np.array([pool.loc[r["pair_id"], "image_vec"] for r in rows])
        w = np.array([r["copies"] for r in rows])[:, None]
        m = np.linalg.solve((w * t).T @ t + np.eye(t.shape[1]), (w * t).T @ i)
        for column, items in zip(("retrieval", "retrieval_noisy"), sets, strict=True):
            y, x = unit(np.stack(items.text_vec) @ m), unit(np.stack(items.image_vec))
            recall = np.mean([np.mean(np.array(plain_ranks(y, x)) == 1), np.mean(np.array(plain_ranks(x, y)) == 1)])
            assert got[name][column] == pytest.approx(recall, abs=2e-6)


def test_blocks_of_candidates_add_up(spark):
    items = fx.evaluation_set(spark, SMOKE)
    items = items.union(items.selectExpr("item_id + 1000", "image_vec", "text_vec"))  # every similarity ties
    maps = {"same": np.eye(64), "none": np.zeros((64, 64))}
    ranked = lambda n: {tuple(r) for r in models.retrieval_ranks(items, maps, n).collect()}
    whole = ranked(20_000)
    assert whole == ranked(17) and len(whole) == 2 * 2 * items.count()
    plain = evaluate.retrieval_score(fx.evaluation_set(spark, SMOKE)).first()[0]
    assert models.retrieval_scores(models.retrieval_ranks(fx.evaluation_set(spark, SMOKE), {"same": np.eye(64)})).first()["score"] == pytest.approx(plain)
    none = sorted(r[3] for r in whole if r[0] == "none" and r[1] == "t2i")
    assert none == list(range(1, items.count() + 1))  # all tie: ranks are the order of the ids
    assert models.retrieval_ranks(items.limit(0), maps).count() == 0


def test_class_ranks(spark):
    images = spark.createDataFrame([(1, [1.0, 0.0], 5), (2, [0.0, 1.0], 5), (3, [1.0, 1.0], 9)], "image_id bigint, vec array<double>, class bigint")
    classes = spark.createDataFrame([(5, [1.0, 0.1]), (6, [0.1, 1.0])], "class bigint, proto array<double>")
    ranks = models.class_ranks(images, classes, {"m": np.eye(2)})
    assert {r["image_id"]: r["rank"] for r in ranks.collect()} == {1: 1, 2: 2, 3: None}
    assert {r["k"]: round(r["accuracy"], 6) for r in models.class_accuracy(ranks, (1, 2)).collect()} == {1: round(1 / 3, 6), 2: round(2 / 3, 6)}


def test_auc_against_brute_force(spark):
    rng = np.random.default_rng(3)
    data = [("g", int(rng.random() < 0.4), rng.normal(size=4).tolist(), rng.normal(size=4).tolist()) for _ in range(120)]
    got = models.label_auc(spark.createDataFrame(data, "grp string, label int, image_vec array<double>, text_vec array<double>"), {"m": np.eye(4)}).first()["auc"]
    cos = [np.dot(i, t) / np.linalg.norm(i) / np.linalg.norm(t) for _, _, i, t in data]
    pos, neg = ([c for c, d in zip(cos, data, strict=True) if d[1] == y] for y in (1, 0))
    assert got == pytest.approx(np.mean([(p > n) + 0.5 * (p == n) for p in pos for n in neg]), abs=0.003)


def test_nan_scores_pass_no_recipe(spark):
    nan = float("nan")
    rows = spark.createDataFrame([(1, 1, nan, 0.5), (2, 2, 0.4, nan), (3, 3, None, None), (4, 4, nan, nan)], "pair_id bigint, image_id bigint, raw_sim double, gen_sim double")
    rows = rows.withColumn("gated", F.lit(True))
    ids = lambda name: {(r["pair_id"], r["origin"]) for r in recipes.select(rows, pq.REGISTRY[name]).collect()}
    assert ids("raw_min") == ids("raw_all") == {(2, "raw")} and ids("gen_min") == ids("gen_all") == {(1, "gen")}
    best = {r["pair_id"]: (r["origin"], r["sim"]) for r in recipes.best_of(rows).collect()}
    assert best[1] == ("gen", 0.5) and best[2] == ("raw", 0.4) and best[4][1] is None


def test_multi_source_ties_go_to_the_first_name(spark):
    data = [(1, "captioner_b", 0.5), (1, "captioner_a", 0.5), (2, "z", 0.1), (2, "a", float("nan")), (3, "b", None), (3, "a", None)]
    for order in (data, data[::-1]):
        got = recipes.multi_source(spark.createDataFrame(order, "pair_id bigint, origin string, sim double")).collect()
        assert {r["pair_id"]: (r["origin"], r["sim"]) for r in got} == {1: ("captioner_a", 0.5), 2: ("z", 0.1), 3: ("a", None)}


def test_more_centres_than_one_pass_holds(spark):
    images = fx.pool_images(spark, SMOKE)
    centres = gate.seeded_centres(images, 40)
    one = {tuple(r) for r in gate.assign(images, centres).collect()}
    assert {tuple(r) for r in gate.assign(images, centres, flat=7).collect()} == one
    two = {tuple(r) for r in gate.assign(images, centres, nearest=2).collect()}
    assert {tuple(r) for r in gate.assign(images, centres, nearest=2, flat=7).collect()} == two and len(two) == 2 * images.count()


def test_kmeans_gate_lowers_the_distance(spark):
    """Every image is with its nearest centre, and the centres are closer than the seeded ones."""
    images = fx.pool_images(spark, SMOKE)
    x = np.array([r["vec"] for r in images.orderBy("image_id").collect()])

    def cost(centres):
        c = np.array([r["centre"] for r in centres.orderBy("cid").collect()])
        return ((x[:, None] - c[None]) ** 2).sum(axis=2).min(axis=1).sum()

    fitted = gate.kmeans_centres(images, 16)
    assert cost(fitted) < cost(gate.seeded_centres(images, 16))
    c = np.array([r["centre"] for r in fitted.orderBy("cid").collect()])
    got = {r["image_id"]: r["cid"] for r in gate.assign(images, fitted, metric="euclid").collect()}
    want = ((x[:, None] - c[None]) ** 2).sum(axis=2).argmin(axis=1)
    assert [got[i] for i in sorted(got)] == want.tolist()
    assert pq.kmeans_gate(spark, SMOKE).agg(F.sum("count")).first()[0] == images.count()


def test_two_level_reports_its_agreement(spark):
    r = pq.gate_two_level(spark, SMOKE).first()
    assert r["n_images"] == fx.pool_images(spark, SMOKE).count() and 0.5 < r["share"] <= 1


def test_suite_and_its_deltas(spark):
    rows = mq.suite(spark, SMOKE).toPandas()
    assert set(rows.recipe) == set(mq.SUITE) and rows.value.between(0, 1).all()
    n = rows.groupby("recipe").size()
    assert n.nunique() == 1 and n.iloc[0] >= 20 and set(rows.kind) == {"retrieval", "classification", "prediction"}
    wide = rows.pivot(index="task", columns="recipe", values="value")
    for r in mq.suite_delta(spark, SMOKE).collect():
        a, b = r["comparison"].split(" over ")
        assert (r["n_tasks"], r["n_better"], r["n_worse"]) == (len(wide), (wide[a] > wide[b]).sum(), (wide[a] < wide[b]).sum())
        assert r["mean_gain"] == pytest.approx((wide[a] - wide[b]).mean(), abs=1e-5)


def test_sweep_and_tuned_percents(spark):
    rows = mq.sweep_results(spark, SMOKE).toPandas()
    sizes = {(r["curve"], r["x"]): r["n_rows"] for r in evaluate.sweep_curves(pq.sheet(spark, SMOKE), mq.SWEEP).collect()}
    assert {(r.curve, r.x): r.n_rows for r in rows.itertuples()} == sizes
    tuned = mq.tune_results(spark, SMOKE).toPandas()
    assert (tuned.groupby("curve").x.nunique() == 1).all() and set(tuned.scale) == {n for n, _ in pq.SCALES}


def test_captioner_experiments(spark):
    """Every configuration is trained and measured; one run of all temperatures equals runs of each."""
    from capmix.operators import captioners
    from capmix.sources.tables import load

    table = captioners.bigrams(load(spark, SMOKE, "documents"))
    pairs = spark.range(30).withColumnRenamed("id", "pair_id")
    both = {(r["pair_id"], r["temperature"]): r["text"] for r in captioners.NgramSampler(table).generate(pairs, temperatures=(0.5, 1.5)).collect()}
    for t in (0.5, 1.5):
        one = captioners.NgramSampler(table, captioners.GenConfig(temperature=t)).generate(pairs).collect()
        assert {(r["pair_id"], t): r["text"] for r in one} == {k: v for k, v in both.items() if k[1] == t}
    sweep = cq.temp_sweep(spark, SMOKE).toPandas().sort_values("temperature")
    assert sweep.n_rows.tolist() == [200] * 4 and sweep.n_unique.is_monotonic_increasing and sweep.mean_sim.between(0, 1).all()
    got = cq.captioner_results(spark, SMOKE).toPandas()
    assert set(got.captioner) == set(cq.CONFIGS) and got.classification.between(0, 1).all() and got.retrieval.between(0, 1).all()


def test_selected_rows_of_the_specialised_captioner(spark):
    got = mq.sel_gen_all_tuned(spark, SMOKE)
    assert got.columns == ["pair_id", "image_id", "origin", "sim"] and got.count() == 200
    made = cq.gen_all_ft(spark, SMOKE).collect()
    assert len(made) == 200 and all(5 <= len(r["text"].split()) <= 40 for r in made)


def test_swap_and_recipes_have_all_rows(spark):
    swap = {r["recipe"]: r for r in mq.retr_swap(spark, SMOKE).collect()}
    assert set(swap) == {"raw_top30", "swap30", "gen_all", "gen_all_ft", "mix30", "mix30_filtered"} and swap["raw_top30"]["n_rows"] == swap["swap30"]["n_rows"]
    assert mq.recipe_results(spark, SMOKE).count() == len(pq.REGISTRY)
    assert mq.scale_results(spark, SMOKE).count() == len(pq.SCALES) * len(pq.SCALE_RECIPES)


def test_unregistered_names_are_gone():
    assert "cap_bigrams_whole" not in catalogue.queries() and {"scale_results", "sweep_results", "suite_delta"} <= set(catalogue.queries())


def test_nothing_is_checkpointed_locally():
    import pathlib

    root = pathlib.Path(rank.__file__).parents[2]
    assert not [p for p in (root / "capmix").rglob("*.py") if "localCheckpoint" in p.read_text()]
    assert [p.name for p in (root / "capmix").rglob("*.py") if "mkdtemp" in p.read_text()] == ["storage.py"]


def test_recipe_of_no_rows_trains_to_zero(spark, sheet):
    plans = recipes.plan(sheet, [Recipe("none", Arm(0)), pq.REGISTRY["raw_all"]])
    masks = recipes.arrow_masks(sheet, plans)
    pool = fx.planted_pool(spark, SMOKE).select("pair_id", "image_vec", "raw_vec", "gen_vec").join(masks.select("pair_id", "raw_mask", "gen_mask"), "pair_id")
    none, some = models.train_sets(pool, [200, 200])
    assert not none.any() and some.shape == (64, 64) and np.abs(some).max() > 0


def test_retrieval_counts_as_folded_cosines_do(spark):
    """Ties, copies, zero, null and tiny vectors; several blocks of candidates."""
    from pyspark.sql import Window

    from capmix.functions import vectors as vx

    rng = np.random.default_rng(4)
    vecs = rng.integers(-2, 3, size=(150, 2, 4)).astype(float).tolist()
    data = [(k, i, t) for k, (i, t) in enumerate(vecs)]
    data += [(200 + k, vecs[0][0], vecs[0][1]) for k in range(30)] + [(300, [0.0] * 4, vecs[1][1]), (301, None, vecs[2][1]), (302, vecs[3][0], [1e-3, None, 0.0, 0.0]), (303, [1e-9] * 4, [3e-9] * 4)]
    items = spark.createDataFrame(data, "item_id bigint, image_vec array<double>, text_vec array<double>")
    sims = items.selectExpr("item_id AS a", "text_vec").crossJoin(items.selectExpr("item_id AS b", "image_vec")).select("a", "b", vx.cosine("text_vec", "image_vec").alias("s"))
    want = set()
    for direction, own, other in (("t2i", "a", "b"), ("i2t", "b", "a")):
        ranked = sims.withColumn("r", F.row_number().over(Window.partitionBy(own).orderBy(F.desc("s"), other))).filter("a = b")
        want |= {(direction, r["a"], r["r"]) for r in ranked.collect()}
    assert {(r["direction"], r["item_id"], r["r"]) for r in evaluate.own_ranks(items, block_rows=50).collect()} == want
