"""Set identities of the recipes, golden counts, gate and budget on the planted pool."""

import pytest

from capmix.operators import evaluate, gate, recipes
from capmix.plans import pool_queries as pq
from tests.conftest import ORACLE, SMOKE


@pytest.fixture(scope="module")
def sheet(spark):
    return pq.gated(spark, SMOKE).cache()


def chosen(sheet, name):
    return {(r["pair_id"], r["origin"]) for r in recipes.select(sheet, pq.REGISTRY[name]).collect()}


def test_identities(sheet):
    raw, mix, some, both = (chosen(sheet, n) for n in ("raw_top30", "mix30", "mix30_filtered", "mix30_filtered_gate"))
    everyone = {r["pair_id"] for r in sheet.select("pair_id").collect()}
    assert {p for p, _ in mix} == everyone and len(mix) == len(everyone)
    assert raw == {x for x in some if x[1] == "raw"} == {x for x in mix if x[1] == "raw"}
    assert some <= mix and {p for p, _ in both} <= {p for p, _ in some}
    assert chosen(sheet, "raw_top30_gate") == raw & chosen(sheet, "raw_gate")
    assert {p for p, _ in chosen(sheet, "swap30")} == {p for p, _ in raw}
    assert chosen(sheet, "rest_filtered") == {x for x in some if x[1] == "gen"}


def test_golden_counts(sheet):
    got = {n: len(chosen(sheet, n)) for n in ("raw_top30", "mix30_filtered", "gen_top50", "raw_gate", "raw_top30_gate", "gen_top75_gate", "mix30_filtered_gate")}
    assert got == {"raw_top30": 60, "mix30_filtered": 119, "gen_top50": 100, "raw_gate": 152, "raw_top30_gate": 44, "gen_top75_gate": 115, "mix30_filtered_gate": 86}


def test_inherited_cut_bounds_the_mix(sheet):
    cut = pq.rank.cuts(sheet, "raw_sim", [30.0])[30.0]
    assert recipes.select(sheet, pq.REGISTRY["mix30_filtered"]).agg({"sim": "min"}).first()[0] >= cut.sim


def test_x_zero_gives_no_generated_rows(spark, sheet):
    r = recipes.Recipe("none", recipes.Arm(0), recipes.Arm(eligible="remaining", min_sim="inherit"))
    assert recipes.select(sheet, r).count() == 0


def test_fused_masks_equal_single_recipes(sheet):
    names = ["raw_top30", "mix30_filtered", "gen_top75_gate", "swap30"]
    rows = recipes.select_many(sheet, [pq.REGISTRY[n] for n in names]).select("pair_id", "raw_mask", "gen_mask").collect()
    for k, n in enumerate(names):
        got = {(r["pair_id"], o) for r in rows for o, m in (("raw", r["raw_mask"]), ("gen", r["gen_mask"])) if m >> k & 1}
        assert got == chosen(sheet, n)


def test_gate_extremes(spark):
    from capmix.sources import fixtures as fx

    images = fx.pool_images(spark, SMOKE)
    centres = gate.seeded_centres(images, 8)
    assigned = gate.assign(images, centres)
    none = gate.reference_hits(images.limit(0), centres)
    assert gate.keep(assigned, none).count() == 0
    every = gate.reference_hits(centres.selectExpr("cast(cid as bigint) image_id", "centre as vec"), centres)
    assert gate.keep(assigned, every).count() == images.count()
    kept, dropped = (gate.keep(assigned, gate.reference_hits(fx.reference_images(spark, SMOKE), centres), drop).count() for drop in (False, True))
    assert kept + dropped == images.count()


def test_two_level_assignment_agrees_mostly(spark):
    from capmix.sources import fixtures as fx

    images = fx.pool_images(spark, ORACLE)
    centres = gate.seeded_centres(images, 40)
    a, b = gate.assign(images, centres), gate.assign_two_level(images, centres, probes=4).withColumnRenamed("cid", "c2")
    n = a.join(b, "image_id").filter("cid = c2").count()
    assert n / images.count() > 0.7


@pytest.mark.parametrize(("m", "n", "want"), [(3, 10, [3, 3, 4]), (5, 5, [1] * 5), (7, 3, [1, 1, 1]), (0, 4, [])])
def test_budget(spark, m, n, want):
    got = evaluate.budget_copies(spark.range(m).selectExpr("id as pair_id"), n)
    assert sorted(r["copies"] for r in got.collect()) == want


def test_budget_draws_total(spark):
    draws = evaluate.budget_draws(spark.range(3).selectExpr("id as pair_id"), 10)
    assert draws.count() == 10 and draws.select("pair_id").distinct().count() == 3


def test_sweep_is_monotone(sheet):
    rows = [r for r in evaluate.sweep_curves(sheet, [10.0, 30.0, 60.0]).collect() if r["curve"] == "raw"]
    rows.sort(key=lambda r: r["x"])
    assert [r["n_rows"] for r in rows] == sorted(r["n_rows"] for r in rows)
    assert [r["mean_sim"] for r in rows] == sorted((r["mean_sim"] for r in rows), reverse=True)


def test_partitioning_does_not_matter(sheet):
    a = chosen(sheet, "mix30_filtered")
    assert chosen(sheet.repartition(13, "image_id"), "mix30_filtered") == a
