"""The registered queries of the ten operators and of the pipeline, and their SQL."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontamination, neighbours, packing, quality, repeats, sharding, simhash, token_files, toxicity
from .common import shared_path

SHARDS, END_ID, TOP, QUERY_STEP = 24, 2, 20, 20
DEMO = "<|im_end|><|im_start|>assistant ok"


def tokenizer_path(name: str) -> str:
    """A public tokenizer's file; CAPMIX_TOKENIZERS names another folder."""
    if folder := os.environ.get("CAPMIX_TOKENIZERS"):
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = tokenizer_path("byte_bpe_50k.json")
    demo = spark.range(2).select(F.lit(-1).cast("bigint").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(DEMO).alias("text"))
    rows = _read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(demo)
    return chat.read_back(chat.format_chat(rows, path), path, in_order=True).drop("n_tokens", "n_loss_tokens")


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _read(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return neighbours.search(rows, rows.filter(F.col("vec_id") % QUERY_STEP == 0), TOP)


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "tokens")
    token_files.write_tokens(_read(spark, sf_dir, "documents").select("doc_id", "text"), path, tokenizer_path("word_bpe_49k.json"), END_ID)
    return token_files.read_tokens(spark, path, digest=True).withColumnRenamed("id", "doc_id")


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = _read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark")
    return decontamination.decontaminate(docs.select("doc_id", "text"), items, keep=["doc_id"]).select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.shard(_read(spark, sf_dir, "documents"), SHARDS)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.repeated_passages(_read(spark, sf_dir, "documents"))


def repeat_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, n_redundant): words of each document that op6's matches cover. SQL can state this part."""
    spans = repeats.redundant_spans(repeats.repeated_passages(_read(spark, sf_dir, "documents")))
    return spans.select("doc_id", F.aggregate("spans", F.lit(0).cast("bigint"), lambda n, s: n + s["end"] - s["start"]).alias("n_redundant"))


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_read(spark, sf_dir, "documents"))
    return found.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_read(spark, sf_dir, "documents"))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "text")
    trees = quality.train(docs, _read(spark, sf_dir, "labels"))
    return quality.score_quality(docs, trees, keep=["doc_id"]).select("doc_id", quality.held_out_column().alias("held_out"), "score", "predicted")


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents").select("doc_id", "text")
    lexicon = toxicity.train(docs, _read(spark, sf_dir, "labels"))
    return toxicity.score_toxicity(docs, lexicon, keep=["doc_id"]).select("doc_id", toxicity.held_out_column().alias("held_out"), "score", "predicted")


def _pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_chat_format": op1,
        "op2_neighbours": op2,
        "op3_token_files": op3,
        "op4_decontaminate": op4,
        "op5_shard": op5,
        "op6_repeated_passages": op6,
        "op7_simhash": op7,
        "op8_pack": op8,
        "op9_quality": op9,
        "op10_toxicity": op10,
        "pipeline": _pipeline,
        "repeat_coverage": repeat_coverage,
    }


_ESCAPED = r"regexp_replace({0}, '<\|(\\*)(im_start|im_sep|im_end|endoftext)\|>', '<|\\\1\2|>', 'g')"

_OP1 = f"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS r, coalesce(text, '') AS t FROM conversations
  UNION ALL
  SELECT -1, k, CASE k WHEN 0 THEN 'user' ELSE 'assistant' END, '{DEMO}' FROM range(2) AS x(k)
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(r || chr(10) || t || chr(10), '' ORDER BY turn NULLS FIRST, r, t)) AS turns_sha256,
  sum(CASE WHEN r = 'assistant' THEN length(t) ELSE 0 END)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN r = 'assistant' THEN t END, '' ORDER BY turn NULLS FIRST, r, t), '')) AS loss_sha256,
  sum({sum(map(len, chat.MARKS))} + length({_ESCAPED.format("r")}) + length({_ESCAPED.format("t")}))::BIGINT AS formatted_chars
FROM turns GROUP BY conv_id
"""

_LOWER = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

_OP4 = rf"""
WITH d AS (SELECT doc_id, coalesce({_WORDS}, []) AS w FROM documents),
i AS (SELECT item_id, coalesce({_WORDS}, []) AS w FROM benchmark),
windows AS (
  SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[k : k + least(len(w), 13) - 1], ' ') AS gram
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 13, 0) + 2)) AS k FROM i WHERE len(w) > 0)
),
sizes AS (SELECT DISTINCT n FROM windows),
grams AS (
  SELECT doc_id, k, n, array_to_string(w[k : k + n - 1], ' ') AS gram
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM d, sizes WHERE len(w) >= n)
),
hits AS (SELECT doc_id, k, g.n, item_id FROM grams g JOIN windows x ON g.gram = x.gram AND g.n = x.n),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM hits) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM hits) GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(d.w) AS contaminated
FROM d LEFT JOIN words ON d.doc_id = words.doc_id LEFT JOIN items ON d.doc_id = items.doc_id
"""


_COVERAGE = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') AS w FROM documents),
windows AS (SELECT doc_id, k, md5(array_to_string(w[k : k + 49], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS k FROM d WHERE len(w) >= 50)),
later AS (SELECT doc_id, k FROM windows QUALIFY row_number() OVER (PARTITION BY h ORDER BY doc_id, k) > 1)
SELECT doc_id, count(DISTINCT p) AS n_redundant FROM (SELECT doc_id, unnest(range(k, k + 50)) AS p FROM later) GROUP BY doc_id
"""

_DRAW = "('0x' || substr(md5('capmix:' || k || ':' || {0}), 1, 15))::BIGINT"

_OP5 = f"""
WITH RECURSIVE crc(t) AS (
  SELECT list_transform(range(256), lambda c: list_reduce(list_prepend(c, range(8)), lambda x, k: CASE WHEN x % 2 = 1 THEN xor(x // 2, 3988292384) ELSE x // 2 END))
),
d AS (
  SELECT doc_id, (strlen(coalesce(text, '')) + 8)::BIGINT AS size,
    xor(4294967295, list_reduce(list_prepend(4294967295, list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda h: ('0x' || h)::BIGINT)),
      lambda x, byte: xor(x // 256, t[xor(x % 256, byte) + 1]))) AS text_crc32
  FROM documents, crc
),
n AS (SELECT n, a, greatest(1, (n + a - 1) // a) AS b FROM (SELECT n, CASE WHEN n > 1 THEN floor(sqrt(n - 1))::BIGINT + 1 ELSE 1 END AS a FROM (SELECT count(*) AS n FROM d))),
g AS (SELECT d.*, row_number() OVER (ORDER BY doc_id NULLS FIRST, text_crc32, size) - 1 AS g FROM d),
walk AS (
  SELECT g, g AS p, 0 AS k, g // b AS l, g % b AS r FROM g, n
  UNION ALL
  SELECT g, p, k, l, r FROM (
    SELECT g, l * b + r AS p, CASE WHEN k = {sharding.ROUNDS} THEN 0 ELSE k + 1 END AS k, l * b + r < n AND k = {sharding.ROUNDS} AS done,
      CASE WHEN k < {sharding.ROUNDS} AND k % 2 = 0 THEN (l + {_DRAW.format("r")} % a) % a ELSE l END AS l,
      CASE WHEN k < {sharding.ROUNDS} AND k % 2 = 1 THEN (r + {_DRAW.format("l")} % b) % b ELSE r END AS r
    FROM walk, n
  ) WHERE NOT done
),
placed AS (SELECT g, l * b + r AS p FROM walk, n WHERE k = {sharding.ROUNDS} AND l * b + r < n)
SELECT doc_id, size, text_crc32, 'rows' AS law, (p % {SHARDS})::INTEGER AS shard, p // {SHARDS} AS slot, NULL::INTEGER AS grown_shard FROM g JOIN placed USING (g)
"""


def oracle_sql() -> dict[str, str]:
    return {"op5_shard": _OP5, "op1_chat_format": _OP1, "op4_decontaminate": _OP4, "repeat_coverage": _COVERAGE}
