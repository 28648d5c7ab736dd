"""Selection recipes: which rows, with which caption, form the training set.

A recipe is data (`Recipe` of `Arm`s). The planner asks for the cuts it needs, all from one
histogram, turns the arms into one CASE over the score sheet, and never joins or unions the sheet with
itself. `select_many` evaluates any number of recipes in one scan, as bits of two masks.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .alignment import clean_scores
from .rank import Cut, cuts, nested_cuts


def _score(name: str) -> Column:
    """A score as recipes see it: NaN, which sorts above every number, is no score."""
    return F.when(~F.isnan(name), F.col(name))


@dataclass(frozen=True)
class Arm:
    """Rows that contribute one kind of caption.

    top_percent ranks by the arm's own score (or, with rank_by='raw', by the raw one); min_sim is an
    absolute cut, or 'inherit' for the value of the raw arm's percent cut; eligible='remaining' keeps
    rows outside the raw arm's percent set, 'not_selected' those that the raw arm didn't take.
    """

    top_percent: float | None = None
    rank_by: str = "own"
    min_sim: float | str | None = None
    gate: bool = False
    eligible: str = "all"


@dataclass(frozen=True)
class Recipe:
    name: str
    raw: Arm | None = None
    gen: Arm | None = None


def registry(x: float = 30.0) -> dict[str, Recipe]:
    """The recipes by name; x is the percent of the mixed ones."""
    rest = lambda **k: Arm(eligible="remaining", **k)
    found = [
        Recipe("raw_all", Arm()),
        Recipe("gen_all", None, Arm()),
        Recipe("raw_top30", Arm(30)),
        Recipe("gen_top30", None, Arm(30)),
        Recipe("gen_top50", None, Arm(50)),
        Recipe("raw_gate", Arm(gate=True)),
        Recipe("gen_gate", None, Arm(gate=True)),
        Recipe("raw_top30_gate", Arm(30, gate=True)),
        Recipe("gen_top75_gate", None, Arm(75, gate=True)),
        Recipe("mix30", Arm(x), rest()),
        Recipe("mix30_filtered", Arm(x), rest(min_sim="inherit")),
        Recipe("mix30_filtered_gate", Arm(x, gate=True), rest(min_sim="inherit", gate=True)),
        Recipe("rest_filtered", None, Arm(eligible="remaining", min_sim="inherit", top_percent=None)),
        Recipe("swap30", None, Arm(30, rank_by="raw")),
        Recipe("raw_min", Arm(min_sim=0.3)),
        Recipe("gen_min", None, Arm(min_sim=0.3)),
    ]
    return {r.name: r for r in found}


@dataclass(frozen=True)
class Plan:
    """A recipe with its cuts filled in: two predicates over a score sheet, within a scale if a level is given."""

    recipe: Recipe
    in_raw: Column
    in_gen: Column
    raw_cuts: dict[float, Cut]
    gen_cuts: dict[float, Cut]
    base: float = 30.0
    level: int | None = None

    def origin(self) -> Column:
        return F.when(self.in_raw, F.lit("raw")).when(self.in_gen, F.lit("gen"))


def percents(recipes: list[Recipe], base: float = 30.0) -> tuple[list[float], list[float]]:
    """The percents of raw and of generated scores that recipes need cuts for."""
    raw_xs, gen_xs = set(), set()
    for r in recipes:
        if r.raw and r.raw.top_percent is not None:
            raw_xs.add(r.raw.top_percent)
        if r.gen and r.gen.top_percent is not None:
            (raw_xs if r.gen.rank_by == "raw" else gen_xs).add(r.gen.top_percent)
        if r.gen and (r.gen.min_sim == "inherit" or r.gen.eligible == "remaining") and not (r.raw and r.raw.top_percent is not None):
            raw_xs.add(base)
    return sorted(raw_xs), sorted(gen_xs)


def plan(sheet: DataFrame, recipes: list[Recipe], base: float = 30.0) -> list[Plan]:
    """Compute all cuts that the recipes need, in two scans for each score, and bind the arms.

    `base` is the percent whose set and cut stand in where a recipe has no raw percent arm of its own.
    """
    raw_xs, gen_xs = percents(recipes, base)
    raw_cuts = cuts(sheet, "raw_sim", raw_xs) if raw_xs else {}
    gen_cuts = cuts(sheet, "gen_sim", gen_xs) if gen_xs else {}
    return [_bind(r, raw_cuts, gen_cuts, base) for r in recipes]


def plan_scales(sheet: DataFrame, recipes: list[Recipe], names: list[str], level: str = "level", base: float = 30.0) -> list[tuple[str, Plan]]:
    """(scale, plan) of every recipe on every nested subset: scale t holds the rows whose `level` is at most t.

    The cuts of all scales come from two scans for each score.
    """
    raw_xs, gen_xs = percents(recipes, base)
    raw = nested_cuts(sheet, "raw_sim", raw_xs, level, len(names)) if raw_xs else {}
    gen = nested_cuts(sheet, "gen_sim", gen_xs, level, len(names)) if gen_xs else {}
    out = []
    for t, name in enumerate(names):
        inside = F.col(level) <= t
        for r in recipes:
            p = _bind(r, {x: raw[t, x] for x in raw_xs}, {x: gen[t, x] for x in gen_xs}, base)
            out.append((name, replace(p, in_raw=p.in_raw & inside, in_gen=p.in_gen & inside, level=t)))
    return out


def _bind(r: Recipe, raw_cuts: dict[float, Cut], gen_cuts: dict[float, Cut], base: float) -> Plan:
    pair, raw, gen, gate = F.col("pair_id"), _score("raw_sim"), _score("gen_sim"), F.col("gated")
    x = r.raw.top_percent if r.raw and r.raw.top_percent is not None else base
    first = raw_cuts.get(x)
    in_raw, in_gen = F.lit(False), F.lit(False)
    if r.raw:
        in_raw = raw.isNotNull() if r.raw.min_sim is None or isinstance(r.raw.min_sim, str) else F.coalesce(raw >= r.raw.min_sim, F.lit(False))
        if r.raw.top_percent is not None:
            in_raw = in_raw & first.covers_rank(raw, pair)
        if r.raw.gate:
            in_raw = in_raw & gate
    if r.gen:
        in_gen = gen.isNotNull()
        if r.gen.top_percent is not None:
            by_raw = r.gen.rank_by == "raw"
            cut = (raw_cuts if by_raw else gen_cuts)[r.gen.top_percent]
            in_gen = in_gen & cut.covers_rank(raw if by_raw else gen, pair)
        if r.gen.min_sim == "inherit":
            in_gen = in_gen & first.covers_value(gen)
        elif r.gen.min_sim is not None:
            in_gen = in_gen & F.coalesce(gen >= r.gen.min_sim, F.lit(False))
        if r.gen.eligible == "remaining":
            in_gen = in_gen & ~first.covers_rank(raw, pair)
        elif r.gen.eligible == "not_selected":
            in_gen = in_gen & ~in_raw
        if r.gen.gate:
            in_gen = in_gen & gate
    return Plan(r, in_raw, in_gen, raw_cuts, gen_cuts, base)


def select(sheet: DataFrame, recipe: Recipe, base: float = 30.0) -> DataFrame:
    """The recipe's Selection: pair_id, image_id, origin, sim (and cid where the sheet has it)."""
    p = plan(sheet, [recipe], base)[0]
    extra = ["cid"] if "cid" in sheet.columns else []
    return sheet.withColumn("origin", p.origin()).filter("origin IS NOT NULL").select("pair_id", "image_id", "origin", F.when(F.col("origin") == "raw", F.col("raw_sim")).otherwise(F.col("gen_sim")).alias("sim"), *extra)


def with_masks(sheet: DataFrame, plans: list[Plan]) -> DataFrame:
    """The sheet with raw_mask and gen_mask: bit k is set where plan k takes that caption (63 plans at most)."""
    if len(plans) > 63:
        raise ValueError("a mask has 63 bits")
    raw, gen = F.lit(0).cast("bigint"), F.lit(0).cast("bigint")
    for k, p in enumerate(plans):
        raw = raw.bitwiseOR(F.when(p.in_raw, F.lit(1 << k)).otherwise(F.lit(0)).cast("bigint"))
        gen = gen.bitwiseOR(F.when(~p.in_raw & p.in_gen, F.lit(1 << k)).otherwise(F.lit(0)).cast("bigint"))
    return sheet.withColumns({"raw_mask": raw, "gen_mask": gen})


def _evaluate(p: Plan, pair: np.ndarray, raw: np.ndarray, gen: np.ndarray, gate: np.ndarray, level: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both predicates of a plan over a batch; missing scores are NaN, which no comparison holds for."""
    r, nobody = p.recipe, np.zeros(len(pair), bool)

    def ranked(cut: Cut, sim: np.ndarray) -> np.ndarray:
        return nobody if cut.sim is None else (sim > cut.sim) | ((sim == cut.sim) & (pair <= cut.id))

    first = p.raw_cuts.get(r.raw.top_percent if r.raw and r.raw.top_percent is not None else p.base)
    inside = np.ones(len(pair), bool) if p.level is None else level <= p.level
    in_raw = in_gen = nobody
    if r.raw:
        in_raw = inside & (~np.isnan(raw) if r.raw.min_sim is None or isinstance(r.raw.min_sim, str) else raw >= r.raw.min_sim)
        if r.raw.top_percent is not None:
            in_raw = in_raw & ranked(first, raw)
        if r.raw.gate:
            in_raw = in_raw & gate
    if r.gen:
        in_gen = inside & ~np.isnan(gen)
        if r.gen.top_percent is not None:
            by_raw = r.gen.rank_by == "raw"
            in_gen = in_gen & ranked((p.raw_cuts if by_raw else p.gen_cuts)[r.gen.top_percent], raw if by_raw else gen)
        if r.gen.min_sim == "inherit":
            in_gen = in_gen & (nobody if first.sim is None else gen >= first.sim)
        elif r.gen.min_sim is not None:
            in_gen = in_gen & (gen >= r.gen.min_sim)
        if r.gen.eligible == "remaining":
            in_gen = in_gen & ~ranked(first, raw)
        elif r.gen.eligible == "not_selected":
            in_gen = in_gen & ~in_raw
        if r.gen.gate:
            in_gen = in_gen & gate
    return in_raw, in_gen & ~in_raw


def arrow_masks(sheet: DataFrame, plans: list[Plan]) -> DataFrame:
    """(pair_id, raw_sim, gen_sim, raw_mask, gen_mask) of many plans in one Arrow pass, for more predicates than one generated
    method can hold; the same bits as `with_masks`. Rows that no plan takes are left out."""
    if len(plans) > 63:
        raise ValueError("a mask has 63 bits")
    data = [replace(p, in_raw=None, in_gen=None) for p in plans]

    def work(batches):
        for batch in batches:
            pair, level = batch.column(0).to_numpy(), batch.column(4).to_numpy()
            raw, gen = (batch.column(c).to_numpy(zero_copy_only=False).astype(float) for c in (1, 2))
            gate = batch.column(3).to_numpy(zero_copy_only=False).astype(bool)
            masks = [np.zeros(len(pair), np.int64), np.zeros(len(pair), np.int64)]
            for k, p in enumerate(data):
                for mask, member in zip(masks, _evaluate(p, pair, raw, gen, gate, level), strict=True):
                    mask |= member.astype(np.int64) << k
            some = pa.array((masks[0] | masks[1]) != 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(masks[0]), pa.array(masks[1])], ["pair_id", "raw_sim", "gen_sim", "raw_mask", "gen_mask"]).filter(some)

    level = F.col("level").cast("int") if "level" in sheet.columns else F.lit(0)
    gate = F.coalesce("gated", F.lit(False)) if "gated" in sheet.columns else F.lit(False)
    return sheet.select("pair_id", F.col("raw_sim").cast("double"), F.col("gen_sim").cast("double"), gate.alias("gated"), level.alias("level")).mapInArrow(work, "pair_id bigint, raw_sim double, gen_sim double, raw_mask bigint, gen_mask bigint")


def select_many(sheet: DataFrame, recipes: list[Recipe], base: float = 30.0) -> DataFrame:
    """The sheet with raw_mask and gen_mask: bit k is set where recipe k takes that caption."""
    return with_masks(sheet, plan(sheet, recipes, base))


def mask_sheet(masks: DataFrame, names: list[tuple], by: tuple[str, ...] = ()) -> DataFrame:
    """(scale, recipe, n_rows, n_raw, n_gen, mean_sim, rel_size) of the sets (scale, recipe) of a masked sheet, in one scan."""
    n, parts = F.count(F.lit(1)), []
    for k, (scale, recipe) in enumerate(names):
        in_raw, in_gen = F.col("raw_mask").bitwiseAND(F.lit(1 << k).cast("bigint")) != 0, F.col("gen_mask").bitwiseAND(F.lit(1 << k).cast("bigint")) != 0
        sim = F.when(in_raw, F.col("raw_sim")).when(in_gen, F.col("gen_sim"))
        parts.append(F.struct(F.lit(scale).alias("scale"), F.lit(recipe).alias("recipe"), F.count(sim).alias("n_rows"), F.count_if(in_raw).alias("n_raw"), F.count_if(in_gen).alias("n_gen"), F.avg(sim).alias("mean_sim"), (F.count(sim) / n).alias("rel_size")).alias(f"r{k}"))
    wide = masks.groupBy(*by).agg(*parts) if by else masks.agg(*parts)
    return wide.select(*by, F.explode(F.array(*[f"r{k}" for k in range(len(names))])).alias("r")).select(*by, "r.*")


def recipe_sheet(sheet: DataFrame, recipes: list[Recipe], base: float = 30.0, by: tuple[str, ...] = ()) -> DataFrame:
    """(recipe, n_rows, n_raw, n_gen, mean_sim, rel_size) of all recipes from one scan."""
    return mask_sheet(select_many(sheet, recipes, base), [(None, r.name) for r in recipes], by).drop("scale")


def best_of(sheet: DataFrame) -> DataFrame:
    """Of each pair the caption of higher alignment; ties stay raw, NaN is no score. An extension."""
    sheet = clean_scores(sheet)
    gen = F.coalesce(F.col("gen_sim") > F.col("raw_sim"), F.col("raw_sim").isNull())
    return sheet.select("pair_id", "image_id", F.when(gen, F.lit("gen")).otherwise(F.lit("raw")).alias("origin"), F.when(gen, F.col("gen_sim")).otherwise(F.col("raw_sim")).alias("sim"))


def multi_source(long: DataFrame) -> DataFrame:
    """Of any number of captioners' (pair_id, origin, sim) the best for each pair; ties to the first name in order,
    missing scores and NaN last. An extension."""
    best = F.struct(-F.coalesce(_score("sim"), F.lit(float("-inf"))), F.col("origin"))
    return long.groupBy("pair_id").agg(F.min_by("origin", best).alias("origin"), F.max(_score("sim")).alias("sim"))


def materialise(selection: DataFrame, captions: DataFrame) -> DataFrame:
    """The training set: a selection with its captions, from (pair_id, origin, text)."""
    return selection.join(captions.select("pair_id", "origin", F.col("text").alias("caption")), ["pair_id", "origin"])
