"""Queries over the hashed-text pool: richness, diversity, captioners, reference metrics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as tx
from ..functions import vectors as vx
from ..operators import alignment, captioners, diversity, evaluate, gate, models, recipes
from ..operators import reference_metrics as rm
from ..operators.encoders import HashedEncoder
from ..sources import fixtures as fx
from ..sources.tables import load, spread
from . import ctes as q
from . import pool_queries as pq

TEMPERATURES = (0.5, 0.75, 1.0, 1.5)


def pool(spark, d) -> DataFrame:
    """H, kept while a query reads it several times; a small single file is spread over the cores first."""
    return captioners.hashed_pool(spread(load(spark, d, "documents").select("doc_id", "text"), "doc_id")).cache()


def long(spark, d) -> DataFrame:
    return diversity.long_captions(pool(spark, d))


def _r6(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in names})


def lex(spark, d) -> DataFrame:
    return diversity.lexicon(load(spark, d, "benchmark"))


def cap_extract(spark, d):
    return pool(spark, d).filter("gen_text IS NOT NULL").select("pair_id", F.md5(F.array_join("gen_text", " ").cast("binary")).alias("text_md5"))


def words_hist(spark, d):
    return diversity.words_histogram(long(spark, d))


def grounding(spark, d):
    ratios = diversity.grounding(long(spark, d), lex(spark, d))
    return _r6(ratios.groupBy("origin").agg(F.count("*").alias("n_rows"), F.avg("ratio").alias("mean_ratio")), "mean_ratio")


def grounding_rows(spark, d):
    return _r6(diversity.grounding(long(spark, d), lex(spark, d)), "ratio")


def uniq_trigrams(spark, d):
    return diversity.unique_grams(long(spark, d))


def uniq_trigrams_hashed(spark, d):
    return diversity.unique_grams_hashed(long(spark, d))


def approx_trigrams(spark, d):
    return diversity.unique_grams_sketch(long(spark, d))


def uniq_nouns(spark, d):
    return diversity.unique_nouns(long(spark, d), lex(spark, d))


def div_curve(spark, d):
    return diversity.diversity_curve(long(spark, d))


def div_slope(spark, d):
    return _r6(diversity.diversity_slope(div_curve(spark, d)), "slope")


def coverage(spark, d):
    return _r6(diversity.coverage(long(spark, d), lex(spark, d)), "share")


def noun_curve(spark, d):
    """Distinct nouns of nested random subsets, raw and generated."""
    return diversity.noun_curve(long(spark, d), lex(spark, d))


NOISE_RECIPES = ["raw_all", "gen_all", "raw_top30", "gen_top30", "mix30", "mix30_filtered", "raw_top30_gate", "gen_top75_gate", "mix30_filtered_gate"]
#: The random subset in which distinct trigrams are counted: a fixed share, so its size follows the training set's.
SUBSET_SHARE, SUBSET_SALT = 0.5, "richness"


def used_captions(spark, d, names: list[str]) -> tuple[DataFrame, DataFrame]:
    """(the pool, captions with the mask of the recipes that use them): pair_id, origin, mask, sim, words.

    Recipes are two masks over one sheet, so tokens are cut and grams shuffled once for all of them. The gate is that
    of the planted pool's images.
    """
    h, registry = pool(spark, d), recipes.registry()
    centres = pq._centres(spark, d)
    assigned = gate.assign(fx.pool_images(spark, d), centres)
    kept = gate.keep(assigned, gate.reference_hits(fx.reference_images(spark, d), centres)).select("image_id", F.lit(True).alias("gated"))
    flags = fx.planted_pairs(spark, d).select("pair_id", "image_id").join(kept, "image_id", "left").select("pair_id", F.coalesce("gated", F.lit(False)).alias("gated"))
    sheet = h.join(flags, "pair_id").withColumn("image_id", F.col("pair_id"))
    masks = recipes.select_many(sheet, [registry[n] for n in names])
    each = [F.struct(F.lit(o).alias("origin"), F.col(f"{o}_mask").alias("mask"), F.col(f"{o}_sim").alias("sim"), F.col(f"{o}_text").alias("words")) for o in ("raw", "gen")]
    return h, masks.select("pair_id", F.explode(F.array(*each)).alias("c")).select("pair_id", "c.*").filter("mask <> 0")


def _by_recipe(used: DataFrame, names: list[str]) -> DataFrame:
    """A row for each recipe that uses a caption."""
    own = F.filter(F.array(*[F.struct(F.lit(1 << k).cast("bigint").alias("bit"), F.lit(n).alias("recipe")) for k, n in enumerate(names)]), lambda s: F.col("mask").bitwiseAND(s["bit"]) != 0)
    return used.withColumn("own", F.explode(own)).withColumn("recipe", F.col("own.recipe"))


def noise_div(spark, d):
    """(recipe, n_rows, rel_size, mean_sim, n_subset, n_unique): noise against diversity of the captions each recipe uses.

    Trigrams are those of a random half of the pairs, so the subset's size follows the set's.
    """
    h, used = used_captions(spark, d, NOISE_RECIPES)
    used = used.withColumn("inside", fx.salted("pair_id", SUBSET_SALT) < int(SUBSET_SHARE * (1 << 32))).cache()
    grams = diversity.masked_unique_grams(used.filter("inside").withColumn("origin", F.lit("all")), NOISE_RECIPES)
    bits = [(n, F.col("mask").bitwiseAND(F.lit(1 << k).cast("bigint")) != 0) for k, n in enumerate(NOISE_RECIPES)]
    sims = used.agg(*[F.struct(F.count(F.when(b, F.col("sim"))).alias("n_rows"), F.avg(F.when(b, F.col("sim"))).alias("mean_sim"), F.count_if(b & F.col("inside")).alias("n_subset")).alias(n) for n, b in bits])
    wide = sims.select(F.explode(F.array(*[F.struct(F.lit(n).alias("recipe"), F.col(f"{n}.n_rows").alias("n_rows"), F.col(f"{n}.mean_sim").alias("mean_sim"), F.col(f"{n}.n_subset").alias("n_subset")) for n in NOISE_RECIPES])).alias("r")).select("r.*")
    return _r6(wide.join(F.broadcast(grams), "recipe").withColumn("rel_size", F.col("n_rows") / F.lit(h.count())), "mean_sim", "rel_size")


RICH_RECIPES = ["raw_all", "gen_all", "raw_top30", "mix30", "mix30_filtered"]


def words_by_recipe(spark, d):
    """(recipe, n_words, n_rows): the distribution of caption lengths in training sets."""
    _, used = used_captions(spark, d, RICH_RECIPES)
    counts = used.groupBy("mask", F.size("words").cast("bigint").alias("n_words")).agg(F.count("*").alias("n"))
    return _by_recipe(counts, RICH_RECIPES).groupBy("recipe", "n_words").agg(F.sum("n").alias("n_rows"))


def grounding_by_recipe(spark, d):
    """(recipe, bin, n_rows): the distribution of grounding ratios in training sets, in bins of a twentieth."""
    _, used = used_captions(spark, d, RICH_RECIPES)
    used = used.cache()
    ratios = diversity.grounding(used, lex(spark, d)).join(used.select("pair_id", "origin", "mask"), ["pair_id", "origin"])
    bins = ratios.filter("ratio IS NOT NULL").groupBy("mask", F.least(F.floor(F.col("ratio") * 20), F.lit(19)).cast("bigint").alias("bin")).agg(F.count("*").alias("n"))
    return _by_recipe(bins, RICH_RECIPES).groupBy("recipe", "bin").agg(F.sum("n").alias("n_rows"))


def richness_by_recipe(spark, d):
    """(recipe, n_rows, mean_words, mean_ratio): means of the two distributions."""
    _, used = used_captions(spark, d, RICH_RECIPES)
    used = used.cache()
    ratios = diversity.grounding(used, lex(spark, d)).join(used.select("pair_id", "origin", "mask", F.size("words").alias("n_words")), ["pair_id", "origin"])
    return _r6(_by_recipe(ratios, RICH_RECIPES).groupBy("recipe").agg(F.count("*").alias("n_rows"), F.avg("n_words").alias("mean_words"), F.avg("ratio").alias("mean_ratio")), "mean_words", "mean_ratio")


def hashed_paired(spark, d):
    return _r6(alignment.paired(pool(spark, d)), "mean_diff", "sd_diff")


def cap_bigrams(spark, d):
    return captioners.bigrams(load(spark, d, "documents"))


def topk_successors(spark, d):
    """Five successors of every word, however rare."""
    got = captioners.top_successors(captioners.bigrams(load(spark, d, "documents")), 5)
    return got.select("w1", "w2", "n", F.col("rank").cast("bigint").alias("rank"))


def _references(spark, d, captions: DataFrame) -> DataFrame:
    """(pair_id, words): the passage each document's raw caption overlaps most."""
    bench = load(spark, d, "benchmark")
    matched = rm.matched_references(captions, bench)
    return matched.join(bench, "item_id").select("pair_id", tx.tokens("text").alias("words"))


def _matched(spark, d, h: DataFrame | None = None):
    h = pool(spark, d) if h is None else h
    return _references(spark, d, h.select("pair_id", F.col("raw_text").alias("words")))


def _judged(spark, d) -> tuple[DataFrame, DataFrame]:
    """(captions, references) of one pool, which is made once."""
    h = pool(spark, d)
    return diversity.long_captions(h), _matched(spark, d, h)


def matched_refs(spark, d):
    h = pool(spark, d)
    return rm.matched_references(h.select("pair_id", F.col("raw_text").alias("words")), load(spark, d, "benchmark"))


def bleu4(spark, d):
    return _r6(rm.bleu(*_judged(spark, d), ["pair_id"]), "bleu")


def bleu2(spark, d):
    return _r6(rm.bleu(*_judged(spark, d), ["pair_id"], max_n=2), "bleu")


def consensus(spark, d):
    corpus = load(spark, d, "benchmark").select("item_id", tx.tokens("text").alias("words"))
    return _r6(rm.consensus(*_judged(spark, d), ["pair_id"], corpus), "consensus")


def tuple_f1(spark, d):
    return _r6(rm.tuple_f1(*_judged(spark, d), ["pair_id"]), "f1")


def rouge(spark, d):
    captions, refs = _judged(spark, d)
    both = captions.join(refs.withColumnRenamed("words", "ref"), "pair_id")
    return both.groupBy("origin").agg(F.avg(rm.rouge_l("words", "ref")).alias("rouge_l"))


def _sampled(spark, d, temperatures: tuple[float, ...], tuned: tuple[bool, ...] = (False,)) -> DataFrame:
    """(pair_id, captioner, temperature, words) for the whole pool, all temperatures and captioners drawn in the same rounds."""
    docs = load(spark, d, "documents")
    special = captioners.bigrams(load(spark, d, "benchmark")) if any(tuned) else None
    sampler = captioners.NgramSampler(captioners.bigram_parts(spread(docs.select("doc_id", "text"), "doc_id")), tuned=special)
    made = sampler.generate(docs.select(F.col("doc_id").alias("pair_id")), "sampler", temperatures, tuned)
    sampler.model.unpersist()  # all captions are drawn and kept by now
    return made.select("pair_id", "captioner", "temperature", F.split("text", " ").alias("words"))


CONFIGS = ["extractive", "sampler_075", "sampler_075_ft", "sampler_150", "sampler_150_ft"]


def _configs(spark, d, h: DataFrame) -> DataFrame:
    """(pair_id, origin, words) of five captioner configurations."""
    every = h.filter("gen_text IS NOT NULL").select("pair_id", F.lit("extractive").alias("origin"), F.col("gen_text").alias("words"))
    name = F.concat(F.when(F.col("temperature") == 0.75, "sampler_075").otherwise("sampler_150"), F.when(F.col("captioner") == "sampler_ft", "_ft").otherwise(""))
    return every.union(_sampled(spark, d, (0.75, 1.5), (False, True)).select("pair_id", name, "words"))


def _with_vectors(captions: DataFrame, h: DataFrame) -> DataFrame:
    """Captions with their hashed vectors and the content vectors of their documents."""
    text = captions.select("pair_id", "origin", F.array_join("words", " ").alias("text")).join(h.select("pair_id", "content_vec"), "pair_id")
    vecs = HashedEncoder().encode_arrow(text, "pair_id", "text", "origin", "content_vec")
    return vecs.select(F.col("key").alias("pair_id"), "origin", F.col("vec").alias("text_vec"), F.col("content_vec").alias("image_vec"))


#: Pairs held out from training of captioner models, and evaluated.
HELD_OUT = 0.1


def captioner_results(spark, d, h: DataFrame | None = None, every: DataFrame | None = None):
    """(captioner, classification, retrieval): a model trained on each captioner's text, evaluated on held-out documents.

    Retrieval is between first lines and contents; classification takes the language whose mean first line is nearest.
    """
    h = pool(spark, d) if h is None else h
    held = fx.salted("pair_id", "held_out") < int(HELD_OUT * (1 << 32))
    rows = _with_vectors(_configs(spark, d, h) if every is None else every, h).filter(~held)
    maps = dict(zip(CONFIGS, models.solve(models.grouped_gram_sums(rows, CONFIGS)), strict=True))
    firsts = _with_vectors(h.select("pair_id", F.lit("raw").alias("origin"), F.col("raw_text").alias("words")), h)
    langs = load(spark, d, "documents").select(F.col("doc_id").alias("pair_id"), "lang").filter("lang IS NOT NULL")
    numbers = {r["lang"]: k for k, r in enumerate(langs.select("lang").distinct().orderBy("lang").limit(1000).collect())}
    named = firsts.join(langs, "pair_id").withColumn("class", F.element_at(F.create_map(*[F.lit(x) for kv in numbers.items() for x in kv]), F.col("lang")))
    protos = evaluate.class_prototypes(named.filter(~held), "class", "text_vec")
    test = named.filter(held).withColumnRenamed("pair_id", "item_id")
    accuracy = models.class_accuracy(models.class_ranks(test.select(F.col("item_id").alias("image_id"), F.col("image_vec").alias("vec"), "class"), protos, maps))
    recall = models.retrieval_scores(models.retrieval_ranks(test, maps))
    found = accuracy.select("model", F.col("accuracy").alias("classification")).join(recall, "model")
    return _r6(found.select(F.col("model").alias("captioner"), "classification", F.col("score").alias("retrieval")), "classification", "retrieval")


def captioner_table(spark, d):
    """(captioner, n_rows, mean_words, mean_sim, ref_free, n_grams, n_unique, bleu2, consensus, classification, retrieval).

    Similarity is the hashed-text cosine of a caption with its document; references are the passages that the
    raw captions overlap most.
    """
    h = pool(spark, d)
    every = _configs(spark, d, h).cache()
    sims = _with_vectors(every, h).select("origin", vx.cosine_arrow("text_vec", "image_vec").alias("sim")).cache()
    noise = sims.groupBy("origin").agg(F.avg("sim").alias("mean_sim")).join(alignment.reference_free(sims), "origin")
    sizes = every.groupBy("origin").agg(F.count("*").alias("n_rows"), F.avg(F.size("words")).alias("mean_words"))
    refs = _matched(spark, d, h).cache()
    corpus = load(spark, d, "benchmark").select("item_id", tx.tokens("text").alias("words"))
    scores = rm.bleu(every, refs, ["pair_id"], max_n=2).withColumnRenamed("bleu", "bleu2").join(rm.consensus(every, refs, ["pair_id"], corpus), "origin")
    table = sizes.join(noise, "origin").join(diversity.unique_grams(every), "origin").join(scores, "origin").withColumnRenamed("origin", "captioner")
    return table.join(captioner_results(spark, d, h, every), "captioner")


def captioner_agreement(spark, d):
    """(metric, outcome, pearson, spearman) of our own captioners' metrics with their models' outcomes."""
    return _r6(rm.metric_agreement(captioner_table(spark, d).cache(), ("consensus", "ref_free", "mean_sim", "n_unique", "bleu2")), "pearson", "spearman")


def temp_sweep(spark, d):
    """(temperature, n_rows, mean_words, mean_sim, n_grams, n_unique) of sampled captions over temperatures."""
    h = pool(spark, d)
    made = _sampled(spark, d, TEMPERATURES).select("pair_id", F.col("temperature").cast("string").alias("origin"), "words").cache()
    sims = _with_vectors(made, h).groupBy("origin").agg(F.avg(vx.cosine_arrow("text_vec", "image_vec")).alias("mean_sim"))
    sizes = made.groupBy("origin").agg(F.count("*").alias("n_rows"), F.avg(F.size("words")).alias("mean_words"))
    return _r6(sizes.join(sims, "origin").join(diversity.unique_grams(made), "origin").withColumnRenamed("origin", "temperature"), "mean_words", "mean_sim")


def gen_all_ft(spark, d):
    """Generated text for the whole pool, from the specialised captioner."""
    docs, bench = load(spark, d, "documents"), load(spark, d, "benchmark")
    tuned = captioners.mixed_bigrams(captioners.bigrams(docs), captioners.bigrams(bench))
    return captioners.NgramSampler(tuned).generate(docs.select(F.col("doc_id").alias("pair_id")), "sampler_ft")


def captioner_mix(spark, d):
    """(origin, n_rows, mean_sim): of four captioners and the raw caption the best-aligned one of each pair."""
    h = pool(spark, d)
    raw = h.select("pair_id", F.lit("raw").alias("origin"), F.col("raw_text").alias("words"))
    sims = _with_vectors(_configs(spark, d, h).filter("origin <> 'sampler_150_ft'").union(raw), h)
    best = recipes.multi_source(sims.select("pair_id", "origin", vx.cosine_arrow("text_vec", "image_vec").alias("sim")))
    return _r6(best.groupBy("origin").agg(F.count("*").alias("n_rows"), F.avg("sim").alias("mean_sim")), "mean_sim")


def conv_richness(spark, d):
    turns = load(spark, d, "conversations").select(F.col("role").alias("origin"), tx.tokens("text").alias("words"))
    sizes = turns.groupBy("origin").agg(F.count("*").alias("n_rows"), F.avg(F.size("words")).alias("mean_words"))
    return _r6(sizes.join(diversity.unique_grams(turns.withColumn("pair_id", F.lit(0))), "origin", "left").select("origin", "n_rows", "mean_words", F.coalesce("n_unique", F.lit(0)).alias("n_unique")), "mean_words")


def queries():
    names = (
        "cap_extract words_hist words_by_recipe grounding grounding_rows grounding_by_recipe richness_by_recipe uniq_trigrams uniq_trigrams_hashed approx_trigrams uniq_nouns div_curve div_slope noun_curve coverage noise_div hashed_paired "
        "cap_bigrams topk_successors matched_refs bleu4 bleu2 consensus tuple_f1 rouge captioner_table captioner_results captioner_agreement captioner_mix temp_sweep conv_richness"
    )
    return {n: globals()[n] for n in names.split()} | {"sel_gen_all_ft": gen_all_ft}


_BIGRAMS = r"""parts0 AS (SELECT unnest(string_split_regex(coalesce(text, ''), '[.\n]')) AS p FROM documents),
words0 AS (SELECT ['<s>'] || t || ['</s>'] AS t FROM (SELECT regexp_extract_all(lower(p), '\p{L}+') AS t FROM parts0) WHERE len(t) >= 1),
big AS (SELECT t[k] AS w1, t[k + 1] AS w2, count(*) AS n FROM (SELECT t, unnest(range(1, len(t))) AS k FROM words0) GROUP BY ALL)"""

_REFS = r"""bt AS (SELECT item_id, regexp_extract_all(lower(text), '\p{L}+') AS words FROM benchmark),
shared AS (SELECT a.pair_id, b.item_id, count(*) AS shared FROM (SELECT pair_id, unnest(list_distinct(raw_text)) AS token FROM h) a JOIN (SELECT item_id, unnest(list_distinct(words)) AS token FROM bt) b USING (token) GROUP BY ALL),
matched AS (SELECT pair_id, item_id FROM shared QUALIFY row_number() OVER (PARTITION BY pair_id ORDER BY shared DESC, item_id) = 1),
refs AS (SELECT pair_id, words FROM matched JOIN bt USING (item_id))"""


def _ngrams(source: str, keys: str, sizes=(1, 2, 3, 4)) -> str:
    return " UNION ALL ".join(f"SELECT {keys}, {n} AS n, gram, count(*) AS tf FROM (SELECT {keys}, array_to_string(words[k : k + {n - 1}], ' ') AS gram FROM (SELECT {keys}, words, unnest(range(1, len(words) - {n - 2})) AS k FROM {source} WHERE len(words) >= {n})) GROUP BY ALL" for n in sizes)


def oracle_sql():
    H = f"WITH {q.HASHED.strip()}"
    HG = f"{H}, {q.GRAMS3}"
    level = "CASE " + " ".join(f"WHEN u < {(1 << 32) >> (4 - k)} THEN {k}" for k in range(4)) + " ELSE 4 END"
    curve = f"{HG}, lv AS (SELECT pair_id, origin, {level} AS level FROM (SELECT pair_id, origin, {q.salted('pair_id', 'subset')} AS u FROM long)), sizes AS (SELECT origin, level, count(*) AS own FROM lv GROUP BY ALL), fresh AS (SELECT origin, level, count(*) AS fresh FROM (SELECT g.origin, gram, min(level) AS level FROM grams g JOIN lv ON lv.pair_id = g.pair_id AND lv.origin = g.origin GROUP BY ALL) GROUP BY ALL), curve AS (SELECT s.origin, s.level, sum(own) OVER w AS n_captions, sum(coalesce(fresh, 0)) OVER w AS n_unique FROM sizes s LEFT JOIN fresh f ON f.origin = s.origin AND f.level = s.level WINDOW w AS (PARTITION BY s.origin ORDER BY s.level))"
    nouns = f"{H}, lv AS (SELECT pair_id, origin, words, {level} AS level FROM (SELECT pair_id, origin, words, {q.salted('pair_id', 'subset')} AS u FROM long)), sizes AS (SELECT origin, level, count(*) AS own FROM lv GROUP BY ALL), fresh AS (SELECT origin, level, count(*) AS fresh FROM (SELECT origin, token, min(level) AS level FROM (SELECT origin, level, unnest(words) AS token FROM lv) JOIN lex USING (token) GROUP BY ALL) GROUP BY ALL) SELECT s.origin, s.level::BIGINT AS level, (sum(own) OVER w)::BIGINT AS n_captions, (sum(coalesce(fresh, 0)) OVER w)::BIGINT AS n_unique FROM sizes s LEFT JOIN fresh f ON f.origin = s.origin AND f.level = s.level WINDOW w AS (PARTITION BY s.origin ORDER BY s.level)"
    cases = {
        "raw_all": ("pair_id IS NOT NULL AND raw_sim IS NOT NULL", "FALSE"), "gen_all": ("FALSE", "gen_sim IS NOT NULL"), "raw_top30": ("r30", "FALSE"), "gen_top30": ("FALSE", "g30"),
        "mix30": ("r30", "NOT r30 AND gen_sim IS NOT NULL"), "mix30_filtered": ("r30", "NOT r30 AND gen_sim >= cut"),
        "raw_top30_gate": ("r30 AND kept", "FALSE"), "gen_top75_gate": ("FALSE", "g75 AND kept"), "mix30_filtered_gate": ("r30 AND kept", "NOT r30 AND gen_sim >= cut AND kept"),
    }
    marked = f"WITH {q.VECTORS.strip()}, {q.GATE.strip()}, {q.HASHED.strip()}, s AS (SELECT * FROM h), m0 AS (SELECT *, pair_id IN {q.top('raw_sim', 30)} AS r30, pair_id IN {q.top('gen_sim', 30)} AS g30, pair_id IN {q.top('gen_sim', 75)} AS g75, pair_id IN (SELECT pair_id FROM pairs JOIN kept USING (image_id)) AS kept, {q.salted('pair_id', SUBSET_SALT)} < {int(SUBSET_SHARE * (1 << 32))} AS inside FROM h), m AS (SELECT m0.*, (SELECT min(raw_sim) FROM m0 WHERE r30) AS cut FROM m0)"

    def used(names):
        return " UNION ALL ".join(f"SELECT '{n}' AS recipe, pair_id, 'raw' AS origin, inside, raw_sim AS sim, raw_text AS words FROM m WHERE {cases[n][0]} UNION ALL SELECT '{n}', pair_id, 'gen', inside, gen_sim, gen_text FROM m WHERE {cases[n][1]}" for n in names)

    rich = f"{marked}, used AS ({used(RICH_RECIPES)}), tk AS (SELECT recipe, pair_id, origin, unnest(words) AS token FROM used), rt AS (SELECT recipe, pair_id, origin, count(lex.token) / count(*) AS ratio FROM tk LEFT JOIN lex USING (token) GROUP BY ALL)"
    def bleu(sizes):
        return f"{H}, {_REFS}, own AS ({_ngrams('long', 'pair_id, origin', sizes)}), rg AS ({_ngrams('refs', 'pair_id', sizes)}), clip AS (SELECT origin, own.n, sum(own.tf) AS total, sum(least(own.tf, coalesce(rg.tf, 0))) AS hit FROM own LEFT JOIN rg ON rg.pair_id = own.pair_id AND rg.n = own.n AND rg.gram = own.gram GROUP BY origin, own.n), br AS (SELECT origin, sum(len(l.words)) AS c, sum(len(r.words)) AS r FROM long l JOIN refs r USING (pair_id) GROUP BY origin) SELECT origin, round(CASE WHEN min(hit) > 0 THEN any_value(CASE WHEN c >= r THEN 1.0 ELSE exp(1 - r / c) END) * exp(avg(CASE WHEN hit > 0 THEN ln(hit / total) END)) ELSE 0 END, 6) AS bleu FROM clip JOIN br USING (origin) GROUP BY origin"

    cons = f"{H}, {_REFS}, own AS ({_ngrams('long', 'pair_id, origin')}), rg AS ({_ngrams('refs', 'pair_id')}), cg AS ({_ngrams('bt', 'item_id')}), df AS (SELECT n, gram, count(*) AS df FROM cg GROUP BY ALL), tot AS (SELECT count(*)::DOUBLE AS total FROM bt), ow AS (SELECT pair_id, origin, own.n, own.gram, tf * ln(total / greatest(coalesce(df, 1), 1)) AS w FROM own LEFT JOIN df ON df.n = own.n AND df.gram = own.gram CROSS JOIN tot), rw AS (SELECT pair_id, rg.n, rg.gram, tf * ln(total / greatest(coalesce(df, 1), 1)) AS w FROM rg LEFT JOIN df ON df.n = rg.n AND df.gram = rg.gram CROSS JOIN tot), onm AS (SELECT pair_id, origin, n, sqrt(sum(w * w)) AS a FROM ow GROUP BY ALL), rnm AS (SELECT pair_id, n, sqrt(sum(w * w)) AS b FROM rw GROUP BY ALL), dt AS (SELECT ow.pair_id, origin, ow.n, sum(ow.w * rw.w) AS d FROM ow JOIN rw ON rw.pair_id = ow.pair_id AND rw.n = ow.n AND rw.gram = ow.gram GROUP BY ALL), cs AS (SELECT o.pair_id, o.origin, sum(CASE WHEN a > 0 AND b > 0 THEN coalesce(d, 0) / (a * b) ELSE 0 END) / 4 AS score FROM onm o JOIN rnm r ON r.pair_id = o.pair_id AND r.n = o.n LEFT JOIN dt ON dt.pair_id = o.pair_id AND dt.origin = o.origin AND dt.n = o.n GROUP BY ALL) SELECT l.origin, round(10 * avg(coalesce(score, 0)), 6) AS consensus FROM long l JOIN refs USING (pair_id) LEFT JOIN cs ON cs.pair_id = l.pair_id AND cs.origin = l.origin GROUP BY l.origin"
    tup = "list_distinct(list_filter(w, lambda x: length(x) >= 4) || list_transform(range(1, greatest(len(w), 1)), lambda k: w[k] || ' ' || w[k + 1]))"
    f1 = f"{H}, {_REFS}, a AS (SELECT pair_id, origin, {tup} AS t FROM (SELECT pair_id, origin, words AS w FROM long)), b AS (SELECT pair_id, {tup} AS t FROM (SELECT pair_id, words AS w FROM refs)) SELECT origin, round(avg(CASE WHEN len(a.t) + len(b.t) > 0 THEN 2 * len(list_intersect(a.t, b.t)) / (len(a.t) + len(b.t)) ELSE 0 END), 6) AS f1 FROM a JOIN b USING (pair_id) GROUP BY origin"
    uniq = f"{HG} SELECT origin, count(*) AS n_grams, count(DISTINCT gram) AS n_unique FROM grams GROUP BY origin"
    return {
        "cap_extract": f"{H} SELECT pair_id, md5(array_to_string(gen_text, ' ')) AS text_md5 FROM h WHERE gen_text IS NOT NULL",
        "words_hist": f"{H} SELECT origin, len(words)::BIGINT AS n_words, count(*) AS n_rows FROM long GROUP BY ALL",
        "grounding": f"{H}, u AS (SELECT pair_id, origin, unnest(words) AS token FROM long), c AS (SELECT pair_id, origin, count(*) AS n, count(lex.token) AS v FROM u LEFT JOIN lex USING (token) GROUP BY ALL) SELECT l.origin, count(*) AS n_rows, round(avg(v / n), 6) AS mean_ratio FROM long l LEFT JOIN c ON c.pair_id = l.pair_id AND c.origin = l.origin GROUP BY l.origin",
        "grounding_rows": f"{H}, u AS (SELECT pair_id, origin, unnest(words) AS token FROM long), c AS (SELECT pair_id, origin, count(*) AS n, count(lex.token) AS v FROM u LEFT JOIN lex USING (token) GROUP BY ALL) SELECT l.pair_id, l.origin, round(v / n, 6) AS ratio FROM long l LEFT JOIN c ON c.pair_id = l.pair_id AND c.origin = l.origin",
        "uniq_trigrams": uniq,
        "uniq_trigrams_hashed": uniq,
        "uniq_nouns": f"{H} SELECT origin, count(DISTINCT token) AS n_nouns FROM (SELECT origin, unnest(words) AS token FROM long) JOIN lex USING (token) GROUP BY origin",
        "div_curve": f"{curve} SELECT origin, level::BIGINT AS level, n_captions::BIGINT AS n_captions, n_unique::BIGINT AS n_unique FROM curve",
        "div_slope": f"{curve} SELECT origin, round(regr_slope(ln(n_unique), ln(n_captions)), 6) AS slope FROM curve WHERE n_unique > 0 GROUP BY origin",
        "coverage": f"{H} SELECT origin, count(DISTINCT token) AS n_terms, round(count(DISTINCT token) / (SELECT count(*) FROM lex), 6) AS share FROM (SELECT origin, unnest(words) AS token FROM long) JOIN lex USING (token) GROUP BY origin",
        "noise_div": f"{marked}, used AS ({used(NOISE_RECIPES)}), g AS (SELECT recipe, count(DISTINCT words[k] || ' ' || words[k + 1] || ' ' || words[k + 2]) AS n_unique FROM (SELECT recipe, words, unnest(range(1, len(words) - 1)) AS k FROM used WHERE inside AND len(words) >= 3) GROUP BY recipe) SELECT recipe, count(sim) AS n_rows, round(count(sim) / (SELECT count(*) FROM h), 6) AS rel_size, round(avg(sim), 6) AS mean_sim, count(*) FILTER (inside) AS n_subset, any_value(n_unique) AS n_unique FROM used JOIN g USING (recipe) GROUP BY recipe",
        "words_by_recipe": f"{marked}, used AS ({used(RICH_RECIPES)}) SELECT recipe, len(words)::BIGINT AS n_words, count(*) AS n_rows FROM used GROUP BY ALL",
        "grounding_by_recipe": f"{rich} SELECT recipe, least(floor(ratio * 20), 19)::BIGINT AS bin, count(*) AS n_rows FROM rt GROUP BY ALL",
        "richness_by_recipe": f"{rich} SELECT u.recipe, count(*) AS n_rows, round(avg(len(words)), 6) AS mean_words, round(avg(ratio), 6) AS mean_ratio FROM used u LEFT JOIN rt ON rt.recipe = u.recipe AND rt.pair_id = u.pair_id AND rt.origin = u.origin GROUP BY u.recipe",
        "noun_curve": nouns,
        "hashed_paired": f"{H} SELECT count(gen_sim - raw_sim) AS n_rows, count(*) FILTER (gen_sim - raw_sim > 0) AS n_better, round(avg(gen_sim - raw_sim), 6) AS mean_diff, round(stddev_samp(gen_sim - raw_sim), 6) AS sd_diff FROM h",
        "cap_bigrams": f"WITH {_BIGRAMS} SELECT w1, w2, n FROM big",
        "topk_successors": f"WITH {_BIGRAMS} SELECT w1, w2, n, rank FROM (SELECT *, row_number() OVER (PARTITION BY w1 ORDER BY n DESC, w2) AS rank FROM big) WHERE rank <= 5",
        "matched_refs": f"{H}, {_REFS} SELECT pair_id, item_id FROM matched",
        "bleu4": bleu((1, 2, 3, 4)),
        "bleu2": bleu((1, 2)),
        "consensus": cons,
        "tuple_f1": f1,
        "conv_richness": r"WITH t AS (SELECT role AS origin, regexp_extract_all(lower(coalesce(text, '')), '\p{L}+') AS words FROM conversations), g AS (SELECT origin, count(DISTINCT words[k] || ' ' || words[k + 1] || ' ' || words[k + 2]) AS n_unique FROM (SELECT origin, words, unnest(range(1, len(words) - 1)) AS k FROM t WHERE len(words) >= 3) GROUP BY origin) SELECT t.origin, count(*) AS n_rows, round(avg(len(words)), 6) AS mean_words, coalesce(any_value(n_unique), 0) AS n_unique FROM t LEFT JOIN g ON g.origin = t.origin GROUP BY t.origin",
    }
