"""SQL of the fixtures and of common steps, for the oracles: written apart from the DataFrame code."""

from __future__ import annotations

from ..sources.fixtures import EVAL_WEIGHT, GEN_WEIGHT

#: Vectors and the planted pool's narrow rows.
VECTORS = """
n AS (SELECT count(*) AS n FROM embeddings),
e AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings),
pairs AS (
  SELECT d.doc_id AS pair_id, n // 5 + d.doc_id % (n - n // 5) AS image_id, (7 * d.doc_id + 13) % n AS r, (11 * d.doc_id + 29) % n AS g,
    CASE quality WHEN 1 THEN 3.5 WHEN 0 THEN 6.0 ELSE 4.7 END::DOUBLE AS w, quality, toxic, lang, source
  FROM documents d CROSS JOIN n LEFT JOIN labels l ON l.doc_id = d.doc_id
)"""


def mixed(a: str, b: str, w: str) -> str:
    """a + w b over lists."""
    return f"list_transform(list_zip({a}, {b}), lambda z: z[1] + {w} * z[2])"


#: s: the score sheet.
SHEET = f"""{VECTORS},
s AS (
  SELECT pair_id, image_id, list_cosine_similarity(i.v, {mixed("i.v", "rv.v", "w")}) AS raw_sim, list_cosine_similarity(i.v, {mixed("i.v", "gv.v", f"{GEN_WEIGHT}::DOUBLE")}) AS gen_sim,
    quality, toxic, lang, source
  FROM pairs JOIN e i ON i.vec_id = image_id JOIN e rv ON rv.vec_id = pairs.r JOIN e gv ON gv.vec_id = pairs.g
)"""

#: assigned, hits, kept: the gate, with nearest centres by a window; k: centres in proportion to the images.
GATE = """
k AS (SELECT greatest(16, 4 * n // 125) AS k FROM n),
pool_images AS (SELECT vec_id AS image_id, v FROM e, n WHERE vec_id >= n // 5),
centres AS (SELECT cid, v FROM (SELECT row_number() OVER (ORDER BY image_id) - 1 AS cid, v FROM pool_images), k WHERE cid < k),
nearest AS (
  SELECT vec_id, cid FROM (
    SELECT e.vec_id, c.cid, row_number() OVER (PARTITION BY e.vec_id ORDER BY list_inner_product(e.v, c.v) DESC, c.cid) AS rn FROM e CROSS JOIN centres c
  ) WHERE rn = 1
),
assigned AS (SELECT vec_id AS image_id, cid FROM nearest, n WHERE vec_id >= n // 5),
hits AS (SELECT cid, count(*) AS n_hits FROM nearest JOIN e USING (vec_id), n WHERE vec_id < n // 10 AND label < 5 GROUP BY cid),
kept AS (SELECT image_id, cid FROM assigned WHERE cid IN (SELECT cid FROM hits))"""


def top(score: str, x: float, source: str = "s") -> str:
    """Pair ids of the best x percent by a global window."""
    return f"(SELECT pair_id FROM (SELECT pair_id, row_number() OVER (ORDER BY {score} DESC NULLS LAST, pair_id) AS rn FROM {source}) WHERE rn <= (SELECT ceil({x} * count(*) / 100.0) FROM {source}))"


#: t30: the raw top set; cut: its least score.
TOP30 = f"""
t30 AS (SELECT * FROM s WHERE pair_id IN {top("raw_sim", 30)}),
cut AS (SELECT min(raw_sim) AS cut FROM t30),
rest AS (SELECT * FROM s WHERE pair_id NOT IN (SELECT pair_id FROM t30))"""

RAW = "pair_id, image_id, 'raw' AS origin, raw_sim AS sim"
GEN = "pair_id, image_id, 'gen' AS origin, gen_sim AS sim"
GATED = "image_id IN (SELECT image_id FROM kept)"

#: Recipe bodies over s, t30, rest, cut and kept: unions of arms.
RECIPES = {
    "raw_all": f"SELECT {RAW} FROM s",
    "gen_all": f"SELECT {GEN} FROM s",
    "raw_top30": f"SELECT {RAW} FROM t30",
    "gen_top30": f"SELECT {GEN} FROM s WHERE pair_id IN {top('gen_sim', 30)}",
    "gen_top50": f"SELECT {GEN} FROM s WHERE pair_id IN {top('gen_sim', 50)}",
    "raw_gate": f"SELECT {RAW} FROM s WHERE {GATED}",
    "gen_gate": f"SELECT {GEN} FROM s WHERE {GATED}",
    "raw_top30_gate": f"SELECT {RAW} FROM t30 WHERE {GATED}",
    "gen_top75_gate": f"SELECT {GEN} FROM s WHERE pair_id IN {top('gen_sim', 75)} AND {GATED}",
    "mix30": f"SELECT {RAW} FROM t30 UNION ALL SELECT {GEN} FROM rest",
    "mix30_filtered": f"SELECT {RAW} FROM t30 UNION ALL SELECT {GEN} FROM rest, cut WHERE gen_sim >= cut",
    "mix30_filtered_gate": f"SELECT {RAW} FROM t30 WHERE {GATED} UNION ALL SELECT {GEN} FROM rest, cut WHERE gen_sim >= cut AND {GATED}",
    "rest_filtered": f"SELECT {GEN} FROM rest, cut WHERE gen_sim >= cut",
    "swap30": f"SELECT {GEN} FROM t30",
    "raw_min": f"SELECT {RAW} FROM s WHERE raw_sim >= 0.3",
    "gen_min": f"SELECT {GEN} FROM s WHERE gen_sim >= 0.3",
}


def recipe(name: str) -> str:
    body = RECIPES[name]
    parts = [SHEET, *([GATE] if "kept" in body else []), *([TOP30] if re_any(body, ("t30", "rest", "cut")) else [])]
    return f"WITH {', '.join(p.strip() for p in parts)} {body}"


def re_any(body: str, words: tuple[str, ...]) -> bool:
    import re

    return any(re.search(rf"\b{w}\b", body) for w in words)


def everything(extra: str = "") -> str:
    return f"WITH {SHEET.strip()}, {GATE.strip()}, {TOP30.strip()}{',' + extra if extra else ''}"


#: Evaluation items: item_id, iv, tv.
EVALUATION = f"""{VECTORS},
items AS (
  SELECT a.vec_id AS item_id, a.v AS iv, {mixed("a.v", "b.v", f"{EVAL_WEIGHT}::DOUBLE")} AS tv
  FROM n, e a JOIN e b ON b.vec_id = (11 * a.vec_id + 29) % (SELECT n FROM n) WHERE a.vec_id >= n // 10 AND a.vec_id < n // 5
),
sims AS (SELECT t.item_id AS text_id, i.item_id AS image_id, list_cosine_similarity(t.tv, i.iv) AS sim FROM items t CROSS JOIN items i),
t2i AS (SELECT rn FROM (SELECT text_id, image_id, row_number() OVER (PARTITION BY text_id ORDER BY sim DESC, image_id) AS rn FROM sims) WHERE text_id = image_id),
i2t AS (SELECT rn FROM (SELECT text_id, image_id, row_number() OVER (PARTITION BY image_id ORDER BY sim DESC, text_id) AS rn FROM sims) WHERE text_id = image_id)"""

#: h: the hashed-text pool (pair_id, raw_text, gen_text, raw_sim, gen_sim).
HASHED = r"""
tok AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(lower(coalesce(text, '')), '\p{L}+') AS t FROM documents),
content AS (SELECT doc_id, list_transform(range(64), lambda b: len(list_filter(bk, lambda x: x = b))::DOUBLE) AS v FROM (SELECT doc_id, list_transform(t, lambda x: ('0x' || substr(md5(x), 1, 8))::BIGINT % 64) AS bk FROM tok)),
firsts AS (SELECT doc_id, regexp_extract_all(lower(split_part(text, chr(10), 1)), '\p{L}+') AS words FROM tok),
parts AS (SELECT doc_id, k, regexp_extract_all(lower(p), '\p{L}+') AS words FROM (SELECT doc_id, unnest(string_split_regex(text, '[.\n]')) AS p, generate_subscripts(string_split_regex(text, '[.\n]'), 1) AS k FROM tok)),
captions AS (SELECT doc_id, 0 AS k, words FROM firsts WHERE len(words) > 0 UNION ALL SELECT doc_id, k, words FROM parts WHERE len(words) BETWEEN 5 AND 40),
vecs AS (SELECT doc_id, k, words, list_transform(range(64), lambda b: len(list_filter(bk, lambda x: x = b))::DOUBLE) AS v FROM (SELECT doc_id, k, words, list_transform(words, lambda x: ('0x' || substr(md5(x), 1, 8))::BIGINT % 64) AS bk FROM captions)),
sc AS (SELECT v.doc_id, k, words, list_cosine_similarity(v.v, c.v) AS sim FROM vecs v JOIN content c ON c.doc_id = v.doc_id),
best AS (SELECT doc_id, words, sim FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY round(sim, 6) DESC, k) AS rn FROM sc WHERE k > 0) WHERE rn = 1),
h AS (SELECT f.doc_id AS pair_id, f.words AS raw_text, b.words AS gen_text, r.sim AS raw_sim, b.sim AS gen_sim FROM firsts f LEFT JOIN best b ON b.doc_id = f.doc_id LEFT JOIN sc r ON r.doc_id = f.doc_id AND r.k = 0),
long AS (SELECT pair_id, 'raw' AS origin, raw_text AS words FROM h UNION ALL SELECT pair_id, 'gen', gen_text FROM h WHERE gen_text IS NOT NULL),
lex AS (SELECT DISTINCT token FROM (SELECT unnest(regexp_extract_all(lower(text), '\p{L}+')) AS token FROM benchmark) WHERE length(token) >= 4)"""

GRAMS3 = "grams AS (SELECT pair_id, origin, words[k] || ' ' || words[k + 1] || ' ' || words[k + 2] AS gram FROM (SELECT pair_id, origin, words, unnest(range(1, len(words) - 1)) AS k FROM long WHERE len(words) >= 3))"


def salted(key: str, salt: str) -> str:
    return f"('0x' || substr(md5({key}::VARCHAR || ':{salt}'), 1, 8))::BIGINT"
