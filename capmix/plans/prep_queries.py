"""Queries of pool preparation, heuristic baselines and the web-page pool."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as tx
from ..operators import captioners, diversity, gate, heuristics, prep
from ..sources import fixtures as fx
from ..sources.tables import load, spread
from . import ctes as q


def _docs(spark, d):
    return load(spark, d, "documents")


def prep_safe(spark, d):
    return prep.drop_unsafe(_docs(spark, d), load(spark, d, "labels")).select("doc_id")


def prep_dedup(spark, d):
    return prep.dedup_exact(_docs(spark, d)).select("doc_id")


def prep_decontam(spark, d):
    return prep.decontaminate(spread(_docs(spark, d).select("doc_id", "text"), "doc_id"), load(spark, d, "benchmark")).select("doc_id")


def prep_decontam_vec(spark, d):
    n = fx.image_count(spark, d)
    evaluation = fx.images(spark, d).filter((F.col("image_id") >= n // 10) & (F.col("image_id") < n // 5))
    return prep.near_evaluation_images(fx.pool_images(spark, d), evaluation, 0.4).withColumn("best", F.round("best", 6))


def prep_subpool(spark, d):
    ids = _docs(spark, d).select(F.col("doc_id").alias("pair_id"))
    return prep.subpool(ids, 0.1).withColumn("share", F.lit(0.1)).union(prep.subpool(ids, 0.5).withColumn("share", F.lit(0.5)))


def prep_sample(spark, d):
    return prep.sample_exact(_docs(spark, d).select(F.col("doc_id").alias("pair_id")), 100)


def prep_mask(spark, d):
    return _docs(spark, d).select("doc_id", F.md5(tx.mask_personal(F.coalesce("text", F.lit(""))).cast("binary")).alias("text_md5"))


def prep_titles(spark, d):
    title = F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1)
    return load(spark, d, "pages").select("page_id", tx.clean_caption(title).alias("title"))


def near_dups(spark, d):
    return prep.near_duplicates(_docs(spark, d))


def near_dup_members(spark, d):
    return prep.near_duplicate_members(_docs(spark, d))


def _raw(spark, d):
    return captioners.hashed_pool(_docs(spark, d)).select("pair_id", F.col("raw_text").alias("words"))


def _kept(df, rule):
    return df.select("pair_id", rule.column().alias("kept"))


def heur_length(spark, d):
    return _kept(_raw(spark, d), heuristics.length())


def _with_noun(spark, d):
    """raw captions with the flag whether a token is in the noun lexicon."""
    raw, lex = _raw(spark, d), diversity.lexicon(load(spark, d, "benchmark"))
    hit = raw.select("pair_id", F.explode("words").alias("token")).join(lex, "token", "left_semi").select("pair_id").distinct().withColumn("has_noun", F.lit(True))
    return raw.join(hit, "pair_id", "left").withColumn("has_noun", F.coalesce("has_noun", F.lit(False)))


def heur_noun(spark, d):
    return _kept(_with_noun(spark, d), heuristics.noun())


def heur_complexity(spark, d):
    return _kept(_raw(spark, d), heuristics.complexity())


def heur_aspect(spark, d):
    return _kept(heuristics.with_sizes(_docs(spark, d).select(F.col("doc_id").alias("pair_id"))), heuristics.aspect())


def heur_min_size(spark, d):
    return _kept(heuristics.with_sizes(_docs(spark, d).select(F.col("doc_id").alias("pair_id"))), heuristics.min_size())


def heur_source(spark, d):
    return heuristics.reliable_sources(_docs(spark, d), load(spark, d, "labels")).select(F.col("doc_id").alias("pair_id"), "source", F.round("rate", 6).alias("rate"))


def heur_objects(spark, d):
    images = fx.pool_images(spark, d)
    centres = gate.seeded_centres(images, fx.centre_count(fx.image_count(spark, d)))
    pairs = fx.planted_pairs(spark, d).select("pair_id", "image_id")
    return heuristics.mentions_objects(_raw(spark, d).join(pairs, "pair_id"), gate.assign(images, centres))


def heur_discard(spark, d):
    rows = heuristics.with_sizes(_with_noun(spark, d))
    rules = [heuristics.length(), heuristics.noun(), heuristics.complexity(), heuristics.aspect(), heuristics.min_size()]
    every = rules[0] & rules[1] & rules[2] & rules[3] & rules[4]
    named = [*rules, heuristics.Rule("all_of_them", every.test)]
    return heuristics.discard_rates(rows, named).withColumn("discard_rate", F.round("discard_rate", 6))


def pages_pool(spark, d):
    p = fx.page_pool(spark, d)
    return p.select("pair_id", "raw_text", F.md5(F.col("content").cast("binary")).alias("content_md5"), "source", "lang")


def pages_sel(spark, d):
    """Pages whose title says what the page is about: at least half of its distinct tokens occur in the content."""
    p = fx.page_pool(spark, d).select("pair_id", F.array_distinct(tx.tokens("raw_text")).alias("t"), F.array_distinct(tx.tokens("content")).alias("c"))
    share = F.size(F.array_intersect("t", "c")) / F.size("t")
    return p.filter(F.size("t") > 0).select("pair_id", F.round(share, 6).alias("share")).filter("share >= 0.5")


def queries():
    names = "prep_safe prep_dedup prep_decontam prep_decontam_vec prep_subpool prep_sample prep_mask prep_titles near_dups near_dup_members heur_length heur_noun heur_complexity heur_aspect heur_min_size heur_source heur_objects heur_discard pages_pool pages_sel"
    return {n: globals()[n] for n in names.split()}


def _replace(expr: str, pairs) -> str:
    for a, b in pairs:
        expr = "replace({0}, '{1}', '{2}')".format(expr, a, b.replace("'", "''"))
    return expr


def oracle_sql():
    H = f"WITH {q.HASHED.strip()}"
    t13 = r"regexp_extract_all(lower(text), '\p{L}+')"
    masked = "coalesce(text, '')"
    for pattern, mask in tx.PERSONAL:
        masked = f"regexp_replace({masked}, '{pattern}', '{mask}', 'g')"
    title = r"regexp_extract(html, '(?is)<title>(.*?)</title>', 1)"
    sizes = f"SELECT doc_id AS pair_id, 64 + {q.salted('doc_id', 'width')} % 961 AS w, 64 + {q.salted('doc_id', 'height')} % 961 AS hh FROM documents"
    parts = f"t AS (SELECT doc_id, {t13} AS t FROM documents WHERE doc_id IS NOT NULL), p AS (SELECT doc_id, t, unnest(range(1, greatest(len(t) - 4, 1) + 1)) AS k FROM t WHERE len(t) > 0)"
    classes = f"{parts}, s AS (SELECT doc_id, list(DISTINCT array_to_string(t[k : k + 4], ' ')) AS s FROM p GROUP BY doc_id), m AS (SELECT doc_id, s, min(doc_id) OVER (PARTITION BY md5(array_to_string(list_sort(s), '|'))) AS rep FROM s)"
    met = "g AS (SELECT rep, len(s) AS n, unnest(s) AS g FROM m WHERE doc_id = rep), met AS (SELECT x.rep AS a, y.rep AS b, count(*) / (x.n + y.n - count(*)) AS jaccard FROM g x JOIN g y ON x.g = y.g AND x.rep < y.rep GROUP BY x.rep, y.rep, x.n, y.n)"
    complexity = "CASE WHEN len(words) > 0 THEN len(list_distinct(words)) / len(words) + list_sum(list_transform(words, lambda x: length(x))) / len(words) + len(list_filter(words, lambda x: length(x) >= 7)) / 10.0 END"
    flags = f"flags AS (SELECT h.pair_id, raw_text AS words, len(raw_text) BETWEEN 5 AND 40 AND length(array_to_string(raw_text, ' ')) <= 400 AS length, h.pair_id IN (SELECT pair_id FROM (SELECT pair_id, unnest(raw_text) AS token FROM h) JOIN lex USING (token)) AS noun, coalesce({complexity.replace('words', 'raw_text')} >= 5.5, FALSE) AS complexity, greatest(w, hh) / least(w, hh) <= 3 AS aspect, least(w, hh) >= 200 AS min_size FROM h JOIN ({sizes}) z ON z.pair_id = h.pair_id)"
    rules = ["length", "noun", "complexity", "aspect", "min_size"]
    html = "html"
    for tag in ("script", "style", "nav"):
        html = f"regexp_replace({html}, '(?is)<{tag}[^>]*>.*?</{tag}>', ' ', 'g')"
    content = f"trim(regexp_replace(array_to_string(regexp_extract_all({html}, '(?is)<p[^>]*>(.*?)</p>', 1), ' '), '<[^>]*>', '', 'g'))"
    pages = f"pages0 AS (SELECT page_id AS pair_id, {_replace(title, tx.ENTITIES)} AS raw_text, {content} AS content, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS source, regexp_extract(url, '^[a-z]+://[^/]+/([^/]+)', 1) AS lang FROM pages)"
    return {
        "prep_safe": "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1)",
        "prep_dedup": "SELECT min(doc_id) AS doc_id FROM documents GROUP BY coalesce(text, '')",
        "prep_decontam": f"WITH g AS (SELECT doc_id, array_to_string(t[k : k + 12], ' ') AS gram FROM (SELECT doc_id, t, unnest(range(1, len(t) - 11)) AS k FROM (SELECT doc_id, {t13} AS t FROM documents) WHERE len(t) >= 13)), b AS (SELECT DISTINCT array_to_string(t[k : k + 12], ' ') AS gram FROM (SELECT t, unnest(range(1, len(t) - 11)) AS k FROM (SELECT {t13} AS t FROM benchmark) WHERE len(t) >= 13)) SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM g JOIN b USING (gram))",
        "prep_decontam_vec": f"WITH {q.VECTORS.strip()}, c AS (SELECT p.vec_id AS image_id, list_cosine_similarity(p.v, x.v) AS best, row_number() OVER (PARTITION BY p.vec_id ORDER BY list_inner_product(p.v, x.v) DESC, x.vec_id) AS rn FROM e p CROSS JOIN e x CROSS JOIN n WHERE p.vec_id >= n // 5 AND x.vec_id >= n // 10 AND x.vec_id < n // 5) SELECT image_id, round(best, 6) AS best FROM c WHERE rn = 1 AND best >= 0.4",
        "prep_subpool": " UNION ALL ".join(f"SELECT doc_id AS pair_id, {s}::DOUBLE AS share FROM documents WHERE {q.salted('doc_id', 'pool')} < {int(s * (1 << 32))}" for s in (0.1, 0.5)),
        "prep_sample": f"SELECT doc_id AS pair_id FROM documents ORDER BY {q.salted('doc_id', 'sample')}, doc_id LIMIT 100",
        "prep_mask": f"SELECT doc_id, md5({masked}) AS text_md5 FROM documents",
        "prep_titles": f"SELECT page_id, trim(regexp_replace(regexp_replace({_replace(title, tx.ENTITIES)}, '[^\\p{{L}}\\p{{N}} .,''-]+', ' ', 'g'), ' +', ' ', 'g')) AS title FROM pages",
        "near_dups": f"WITH {classes}, {met} SELECT a, b, jaccard FROM met WHERE jaccard >= 0.8 UNION ALL SELECT rep, doc_id, 1.0::DOUBLE FROM m WHERE doc_id <> rep",
        "near_dup_members": f"WITH {classes} SELECT doc_id, rep FROM m",
        "heur_length": f"{H} SELECT pair_id, len(raw_text) BETWEEN 5 AND 40 AND length(array_to_string(raw_text, ' ')) <= 400 AS kept FROM h",
        "heur_noun": f"{H}, {flags} SELECT pair_id, noun AS kept FROM flags",
        "heur_complexity": f"{H}, {flags} SELECT pair_id, complexity AS kept FROM flags",
        "heur_aspect": f"SELECT pair_id, greatest(w, hh) / least(w, hh) <= 3 AS kept FROM ({sizes})",
        "heur_min_size": f"SELECT pair_id, least(w, hh) >= 200 AS kept FROM ({sizes})",
        "heur_source": "WITH r AS (SELECT source, avg(quality) AS rate FROM documents JOIN labels USING (doc_id) GROUP BY source) SELECT doc_id AS pair_id, source, round(rate, 6) AS rate FROM documents JOIN r USING (source) WHERE rate >= 0.85",
        "heur_objects": f"WITH {q.VECTORS.strip()}, {q.GATE.strip()}, {q.HASHED.strip()}, pl AS (SELECT h.pair_id, raw_text AS words, a.cid FROM h JOIN pairs USING (pair_id) JOIN assigned a USING (image_id)), cnt AS (SELECT cid, token, count(*) AS n FROM (SELECT cid, unnest(list_distinct(words)) AS token FROM pl) WHERE length(token) >= 4 GROUP BY ALL), tops AS (SELECT cid, list(token) AS concepts FROM (SELECT *, row_number() OVER (PARTITION BY cid ORDER BY n DESC, token) AS rn FROM cnt) WHERE rn <= 20 GROUP BY cid) SELECT pair_id, coalesce(len(list_intersect(words, concepts)) > 0, FALSE) AS kept FROM pl LEFT JOIN tops USING (cid)",
        "heur_discard": f"{H}, {flags} " + " UNION ALL ".join(f"SELECT '{n}' AS rule, count(*) AS n_rows, count(*) FILTER ({t}) AS n_kept, round(1 - count(*) FILTER ({t}) / count(*), 6) AS discard_rate FROM flags" for n, t in [*((r, r) for r in rules), ("all_of_them", " AND ".join(rules))]),
        "pages_pool": f"WITH {pages} SELECT pair_id, raw_text, md5(content) AS content_md5, source, lang FROM pages0",
        "pages_sel": rf"WITH {pages}, t AS (SELECT pair_id, list_distinct(regexp_extract_all(lower(raw_text), '\p{{L}}+')) AS t, list_distinct(regexp_extract_all(lower(content), '\p{{L}}+')) AS c FROM pages0) SELECT pair_id, round(len(list_intersect(t, c)) / len(t), 6) AS share FROM t WHERE len(t) > 0 AND round(len(list_intersect(t, c)) / len(t), 6) >= 0.5",
    }
