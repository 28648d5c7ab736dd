"""Worked examples of text measures and caption metrics, and edge cases of vectors and captions."""

import math

import pytest
from pyspark.sql import functions as F

from capmix import schemas
from capmix.functions import text as tx
from capmix.functions import vectors as vx
from capmix.operators import captioners, diversity, heuristics, prep
from capmix.operators import reference_metrics as rm
from capmix.sources.tables import load, write_shards
from tests.conftest import ORACLE, SMOKE


def one(spark, expr, value, kind="string"):
    return spark.createDataFrame([(value,)], f"x {kind}").select(expr.alias("y")).first()["y"]


def test_tokens_and_trigrams(spark):
    assert one(spark, tx.tokens("x"), "Été 3x, don't A_b") == ["été", "x", "don", "t", "a", "b"]
    assert one(spark, tx.tokens("x"), None) == []
    assert one(spark, tx.ngrams(tx.tokens("x"), 3), "a b") == []
    got = one(spark, tx.ngrams(tx.tokens("x"), 3), "a b a b a")
    assert sorted(set(got)) == ["a b a", "b a b"] and len(got) == 3


def test_clean_and_mask(spark):
    assert one(spark, tx.clean_caption(F.col("x")), "a &amp; b%%% &lt;c&gt;  d") == "a b c d"
    assert one(spark, tx.mask_personal(F.col("x")), "x a.b@c.de +49 170 1234567 10.1.2.3") == "x <mail> <number> <address>"


@pytest.mark.parametrize("method", ["fold", "arrow"])
def test_cosine_edges(spark, method):
    data = [([1.0, 0.0], [1.0, 1.0]), ([0.0, 0.0], [1.0, 1.0]), (None, [1.0, 1.0])]
    f = vx.cosine if method == "fold" else vx.cosine_arrow
    got = [r["c"] for r in spark.createDataFrame(data, "a array<double>, b array<double>").select(f(F.col("a"), F.col("b")).alias("c")).collect()]
    assert got[0] == pytest.approx(math.sqrt(0.5)) and got[1] is None and got[2] is None


def test_published_agreement(spark):
    got = {(r["metric"], r["outcome"]): r for r in rm.metric_agreement(rm.published_captioners(spark)).collect()}
    spearman = {k: round(v["spearman"], 6) for k, v in got.items()}
    assert [spearman[m, "classification"] for m in rm.METRICS] == [-0.9, 0.9, 0.9, 0.3]
    assert [spearman[m, "retrieval"] for m in rm.METRICS] == [0.7, -0.3, -0.3, -0.9]
    pearson = [round(got[m, "classification"]["pearson"], 6) for m in rm.METRICS]
    assert pearson == [-0.914432, 0.927513, 0.932129, 0.703936]


def test_published_retrieval_ratios(spark):
    from capmix.operators.evaluate import gain_over

    got = sorted(round(r["ratio"], 3) for r in gain_over(rm.published_retrieval(spark), "raw_top30").collect())
    assert got == [0.670, 0.924, 1.000, 1.929, 1.975, 2.036, 2.056, 2.117]


def captions(spark, data):
    return spark.createDataFrame([(k, o, w.split()) for k, o, w in data], "pair_id bigint, origin string, words array<string>")


def references(spark, data):
    return spark.createDataFrame([(k, w.split()) for k, w in data], "pair_id bigint, words array<string>")


def test_bleu_by_hand(spark):
    c = captions(spark, [(1, "same", "the cat sat on the mat"), (1, "clip", "the the the the the the")])
    r = references(spark, [(1, "the cat sat on the mat")])
    assert {x["origin"]: x["bleu"] for x in rm.bleu(c, r, ["pair_id"]).collect()} == {"same": pytest.approx(1.0), "clip": 0.0}
    got = {x["origin"]: x["bleu"] for x in rm.bleu(c, r, ["pair_id"], max_n=1).collect()}
    assert got["clip"] == pytest.approx(2 / 6)
    short = captions(spark, [(1, "s", "the cat")])
    assert rm.bleu(short, r, ["pair_id"], max_n=1).first()["bleu"] == pytest.approx(math.exp(1 - 3))


def test_consensus_and_tuples_of_equal_captions(spark):
    c = captions(spark, [(1, "same", "a red fox jumps over logs"), (1, "other", "nothing in common here at all")])
    r = references(spark, [(1, "a red fox jumps over logs")])
    corpus = spark.createDataFrame([(1, "a red fox jumps over logs".split()), (2, "some other words".split())], "item_id bigint, words array<string>")
    got = {x["origin"]: x["consensus"] for x in rm.consensus(c, r, ["pair_id"], corpus).collect()}
    assert got["same"] == pytest.approx(10.0) and got["other"] == 0.0
    assert {x["origin"]: x["f1"] for x in rm.tuple_f1(c, r, ["pair_id"]).collect()} == {"same": 1.0, "other": 0.0}


def test_rouge(spark):
    df = spark.createDataFrame([("a b c d".split(), "a c d".split()), ([], ["a"])], "a array<string>, b array<string>")
    assert [r[0] for r in df.select(rm.rouge_l("a", "b")).collect()] == [pytest.approx(6 / 7), 0.0]


def test_diversity_exact_hashed_and_sketched(spark):
    c = captions(spark, [(k, "o", f"w{k % 7} w{k % 5} w{k % 3} end") for k in range(200)])
    exact, hashed = diversity.unique_grams(c).first(), diversity.unique_grams_hashed(c).first()
    assert (exact["n_grams"], exact["n_unique"]) == (hashed["n_grams"], hashed["n_unique"]) and exact["n_grams"] == 400
    sketched = diversity.unique_grams_sketch(c).first()["n_unique"]
    assert abs(sketched - exact["n_unique"]) <= max(2, 0.03 * exact["n_unique"])


def test_curve_is_nested(spark):
    c = captions(spark, [(k, "o", f"w{k % 17} w{k % 5} w{k % 3} end") for k in range(300)])
    rows = sorted(diversity.diversity_curve(c).collect(), key=lambda r: r["level"])
    assert [r["n_unique"] for r in rows] == sorted(r["n_unique"] for r in rows)
    assert rows[-1]["n_captions"] == 300 and rows[-1]["n_unique"] == diversity.unique_grams(c).first()["n_unique"]


def test_grounding_of_empty_caption_is_null(spark):
    c = spark.createDataFrame([(1, "o", []), (2, "o", ["tree", "xx"])], "pair_id bigint, origin string, words array<string>")
    lex = spark.createDataFrame([("tree",)], "token string")
    assert {r["pair_id"]: r["ratio"] for r in diversity.grounding(c, lex).collect()} == {1: None, 2: 0.5}


def test_hashed_pool_golden(spark):
    h = captioners.hashed_pool(load(spark, SMOKE, "documents"), raw_limit=40)
    r = h.agg(F.count("*").alias("n"), F.count("gen_text").alias("g"), F.avg("raw_sim").alias("a"), F.avg("gen_sim").alias("b")).first()
    assert (r["n"], r["g"], round(r["a"], 3), round(r["b"], 3)) == (200, 189, 0.610, 0.743)
    grams = {x["origin"]: (x["n_unique"], x["n_grams"]) for x in diversity.unique_grams(diversity.long_captions(h)).collect()}
    assert grams == {"raw": (3351, 4200), "gen": (4344, 4864)}


def test_sampler_bounds_and_repeatability(spark):
    table = captioners.bigrams(load(spark, SMOKE, "documents"))
    cfg = captioners.GenConfig()
    pairs = spark.range(40).selectExpr("id as pair_id")
    a = captioners.NgramSampler(table, cfg).generate(pairs).orderBy("pair_id").collect()
    b = captioners.NgramSampler(table.repartition(5), cfg).generate(pairs.repartition(7)).orderBy("pair_id").collect()
    assert a == b
    assert all(cfg.min_len <= len(r["text"].split()) <= cfg.max_len for r in a)


def test_temperature_raises_diversity(spark):
    table = captioners.bigrams(load(spark, SMOKE, "documents")).cache()
    n = {}
    for t in (0.3, 2.0):
        sampler = captioners.NgramSampler(table, captioners.GenConfig(temperature=t))
        n[t] = len({g for k in range(150) for c in [sampler.caption(k)] for g in zip(c, c[1:], c[2:], strict=False)})
    assert n[0.3] < n[2.0]


def test_rules_compose(spark):
    df = spark.createDataFrame([(1, "a b c d e f".split(), True), (2, ["a"], True), (3, None, None)], "pair_id bigint, words array<string>, has_noun boolean")
    rule = heuristics.length() & heuristics.noun()
    assert [r["k"] for r in df.select(rule.column().alias("k")).collect()] == [True, False, False]
    rates = {r["rule"]: r["discard_rate"] for r in heuristics.discard_rates(df, [heuristics.length(), ~heuristics.noun()]).collect()}
    assert rates["length"] == pytest.approx(2 / 3)


def test_near_duplicates_find_a_copy(spark):
    text = " ".join("abcdefghijklmnopqrstuvwxyz"[k % 26] * (1 + k % 5) + chr(97 + k // 26) for k in range(120))
    docs = spark.createDataFrame([(1, text), (2, text + " tail words"), (3, "quite another text with words of its own kind")], "doc_id bigint, text string")
    got = prep.near_duplicates(docs).collect()
    assert [(r["a"], r["b"]) for r in got] == [(1, 2)] and got[0]["jaccard"] > 0.9


def test_subpools_are_nested(spark):
    ids = spark.range(2000).selectExpr("id as pair_id")
    small, large = ({r[0] for r in prep.subpool(ids, s).collect()} for s in (0.1, 0.4))
    assert small < large and 120 < len(small) < 280


def test_schema_guard(spark):
    df = spark.createDataFrame([], "pair_id bigint, image_id int")
    with pytest.raises(ValueError, match="image_id: int, not bigint"):
        schemas.require(df, schemas.POOL)


def test_shards_and_manifest(spark, tmp_path):
    sel = spark.range(100).selectExpr("id as pair_id", "'raw' as origin")
    manifest = write_shards(sel, str(tmp_path), 4, partition_by="origin")
    assert sum(r["n_rows"] for r in manifest.collect()) == 100
    assert spark.read.parquet(f"{tmp_path}/data").count() == 100


@pytest.mark.parametrize("name", ["gain_vs_base", "metric_agreement"])
def test_comparisons_are_over_given_tables(spark, name):
    from capmix.plans import catalogue

    small, large = (sorted(map(tuple, catalogue.queries()[name](spark, d).collect()), key=str) for d in (SMOKE, ORACLE))
    assert len(small) == len(large) > 1 and small != large


def test_metrics_beside_references_equal_shuffled_grams(spark):
    """Grams counted beside a caption's references give what joins of all grams gave; several references, none, and empty captions."""
    words = lambda text: text.split()
    caps = spark.createDataFrame([(1, "a", words("a red dog runs in the park")), (1, "b", words("the dog the dog the")), (2, "a", words("a cat")), (2, "b", []), (3, "a", words("no reference here"))], "pair_id bigint, origin string, words array<string>")
    refs = spark.createDataFrame([(1, words("a red dog runs")), (1, words("the dog in the big park")), (2, words("one cat on a mat"))], "pair_id bigint, words array<string>")
    corpus = spark.createDataFrame([(1, words("a red dog runs")), (2, words("the dog in the big park")), (3, words("a cat the dog"))], "item_id bigint, words array<string>")
    own, most = rm.consensus(caps, refs, ["pair_id"], corpus), rm.consensus(caps, refs, ["pair_id"], corpus, most=1)
    a, b = ({r["origin"]: r["consensus"] for r in x.collect()} for x in (own, most))
    assert set(a) == {"a", "b"} and all(abs(a[k] - b[k]) < 1e-9 for k in a)
    assert "gram" not in rm.bleu(caps, refs, ["pair_id"])._jdf.queryExecution().executedPlan().toString()
    # clipped words and pairs of words of all captions, and lengths beside the closest references', ties to the shorter
    want = {"a": math.exp(1 - 11 / 9) * math.sqrt(9 / 12 * 4 / 9), "b": math.exp(1 - 9 / 5) * math.sqrt(3 / 5 * 1 / 4)}
    got = {r["origin"]: r["bleu"] for r in rm.bleu(caps, refs, ["pair_id"], max_n=2).collect()}
    assert set(got) == set(want) and all(got[k] == pytest.approx(want[k]) for k in want)
