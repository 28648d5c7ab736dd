"""The sampler against the whole bigram table: more contexts than any cap, joined step by step."""

from capmix.operators import captioners
from tests.conftest import SMOKE


def test_every_context_is_in_the_model(spark):
    n = 20_500
    spell = lambda k: "w" + "".join(chr(97 + int(c)) for c in str(k))
    chain = [(captioners.START, spell(0), 1)] + [(spell(k), spell(k + 1), 5) for k in range(n)] + [("zz", "zzz", 1), ("zzz", "zz", 1)]
    table = spark.createDataFrame([*chain, (captioners.START, "zz", 10**9)], "w1 string, w2 string, n bigint")
    # "zz" and "zzz" are the rarest contexts; after them nothing but each other can follow.
    sampler = captioners.NgramSampler(table)
    texts = [r["text"].split() for r in sampler.generate(spark.range(5).withColumnRenamed("id", "pair_id")).collect()]
    assert all(t == ["zz", "zzz"] * 20 for t in texts) and len(texts) == 5


def test_joined_steps_equal_the_plain_form(spark):
    docs = spark.createDataFrame([(k, f"one two three four five six.\nred two blue four {'green' if k % 2 else 'grey'} six seven eight.\nend.") for k in range(20)], "doc_id bigint, text string")
    sampler = captioners.NgramSampler(captioners.bigrams(docs), captioners.GenConfig(temperature=1.5))
    got = {r["pair_id"]: r["text"] for r in sampler.generate(spark.range(60).withColumnRenamed("id", "pair_id")).collect()}
    assert got == {k: " ".join(sampler.caption(k)) for k in range(60)}


def test_captions_do_not_depend_on_the_core(spark):
    """Words of the broadcast contexts and joined ones are drawn alike; no round for each word where all are in the core."""
    docs = spark.read.parquet(f"{SMOKE}/documents.parquet").limit(40)
    pairs, table, made = spark.range(50).withColumnRenamed("id", "pair_id"), captioners.bigrams(docs).cache(), []
    for core in (0, 20, captioners.CORE):
        got = captioners.NgramSampler(table, core=core).generate(pairs, temperatures=(0.5, 1.5))
        made.append((sorted(map(tuple, got.collect())), len({f.rsplit("/", 1)[0] for f in got.inputFiles()})))
    assert made[0][0] == made[1][0] == made[2][0] and len(made[0][0]) == 100
    assert made[2][1] == 1 < made[1][1]


def test_specialised_captions_are_drawn_beside_plain_ones(spark):
    """Both captioners in the same rounds, with the specialised one's rows kept beside the plain ones, equal runs on two whole tables."""
    docs, bench = (spark.read.parquet(f"{SMOKE}/{t}.parquet").limit(40) for t in ("documents", "benchmark"))
    pairs, table, special = spark.range(30).withColumnRenamed("id", "pair_id"), captioners.bigrams(docs).cache(), captioners.bigrams(bench).cache()
    apart = {}
    for name, counts in (("sampler", table), ("sampler_ft", captioners.mixed_bigrams(table, special))):
        apart |= {(r["pair_id"], name, r["temperature"]): r["text"] for r in captioners.NgramSampler(counts, core=20).generate(pairs, name, (0.5, 1.5)).collect()}
    for core in (0, 20, captioners.CORE):
        rows = captioners.NgramSampler(captioners.bigram_parts(docs), core=core, tuned=special).generate(pairs, "sampler", (0.5, 1.5), (False, True)).collect()
        assert {(r["pair_id"], r["captioner"], r["temperature"]): r["text"] for r in rows} == apart and len(rows) == 120
    assert any(apart[k, "sampler", 1.5] != apart[k, "sampler_ft", 1.5] for k in range(30))


def test_rounds_do_not_shuffle_the_model(spark):
    """A round deals the captions alone; the model stays where its rows were made, and unlike before none is joined by sorting."""
    docs = spark.read.parquet(f"{SMOKE}/documents.parquet").limit(10)
    sampler = captioners.NgramSampler(captioners.bigram_parts(docs))
    going = spark.createDataFrame([("the",)], "word string")
    plan = going.hint("shuffle_hash").join(sampler.model.withColumnRenamed("w1", "word"), "word", "left")._jdf.queryExecution().executedPlan().toString()
    plan = plan.split("InMemoryRelation")[0]
    assert "LeftOuter, BuildLeft" in plan and plan.count("Exchange") == 1 and "Sort" not in plan


def test_bigrams_of_odd_letters(spark):
    """Counted in Arrow batches, and in several parts, as by Spark's expressions."""
    from pyspark.sql import functions as F

    from capmix.functions import text as tx

    texts = ["ΟΔΟΣ.Α ΟΔΟΣ\nΣΑΣ Σ", "x²y ½ Ⅷ naïve STRASSE", "İstanbul ǅ a_b 7z", "", None, "..\n.", "日本語 文。字", "one two.one two"]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id bigint, text string")
    for least in (1, 2):
        words = docs.select(F.explode(tx.sentences("text")).alias("s")).select(tx.tokens("s").alias("t")).filter(F.size("t") >= least)
        want: dict = {}
        for (t,) in words.collect():
            marked = [captioners.START, *t, captioners.END]
            for pair in zip(marked, marked[1:], strict=False):
                want[pair] = want.get(pair, 0) + 1
        assert {(r["w1"], r["w2"]): r["n"] for r in captioners.bigrams(docs, least).collect()} == want
