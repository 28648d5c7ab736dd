"""Queries of the surrounding operators on the star tables, events and text tables."""

from __future__ import annotations


from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import tables
from ..functions import text as tx
from ..functions import vectors as vx
from ..operators import relational as rel
from ..operators.encoders import HashedEncoder, StoredEncoder
from ..sources import fixtures as fx
from ..sources.tables import load
from ..storage import shared_path
from . import ctes as q



def _m(c):
    return F.col(c).cast("decimal(14,2)") if isinstance(c, str) else c


def rel_pricing(spark, d):
    li = load(spark, d, "lineitem").filter(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp_ntz"))
    return li.groupBy("l_returnflag", "l_linestatus").agg(F.sum(_m("l_quantity")).cast("double").alias("sum_qty"), F.sum(_m("l_extendedprice")).cast("double").alias("sum_price"), F.count("*").alias("n"))


def rel_nation_revenue(spark, d):
    li, o, c, n, r = (load(spark, d, t) for t in ("lineitem", "orders", "customer", "nation", "region"))
    joined = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return joined.groupBy("r_name", "n_name").agg(F.sum(_m("l_extendedprice")).cast("double").alias("revenue"), F.count("*").alias("n"))


def rel_top_customers(spark, d):
    o, c = load(spark, d, "orders"), load(spark, d, "customer")
    spent = o.groupBy("o_custkey").agg(F.sum(_m("o_totalprice")).cast("double").alias("spent"))
    return spent.join(c, spent.o_custkey == c.c_custkey).orderBy(F.desc("spent"), "c_custkey").limit(20).select("c_custkey", "c_name", "spent")


def rel_rollup(spark, d):
    return load(spark, d, "documents").rollup("lang", "source").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("gid"))


def rel_cube(spark, d):
    return load(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(_m("l_quantity")).cast("double").alias("qty"))


def rel_grouping_sets(spark, d):
    load(spark, d, "documents").createOrReplaceTempView("capmix_documents")
    return spark.sql("SELECT lang, source, count(*) AS n, CAST(grouping_id(lang, source) AS BIGINT) AS gid FROM capmix_documents GROUP BY GROUPING SETS ((lang), (source), ())")


def rel_semi(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders").withColumnRenamed("o_custkey", "c_custkey"), "c_custkey", "left_semi").select("c_custkey")


def rel_anti(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders").withColumnRenamed("o_custkey", "c_custkey"), "c_custkey", "left_anti").select("c_custkey")


def rel_outer(spark, d):
    """Documents and labels, all rows of both sides, by a null-safe key."""
    a, b = load(spark, d, "documents").select("doc_id", "lang"), load(spark, d, "labels").select(F.col("doc_id").alias("label_id"), "quality")
    return a.join(b, F.col("doc_id").eqNullSafe(F.col("label_id")), "full").select("doc_id", "label_id", "lang", "quality")


def rel_asof(spark, d):
    """The latest purchase value of the same user before each error."""
    e = load(spark, d, "events")
    errors = e.filter("event_type = 'error'").select("event_id", "user_id", "ts")
    bought = e.filter("event_type = 'purchase'").select("user_id", "ts", "value")
    return rel.asof_join(errors, bought, "ts", "user_id", "value").select("event_id", "user_id", "value")


def rel_range_join(spark, d):
    """Orders in price bands of uneven width."""
    bands = spark.createDataFrame([(k, float(a), float(b)) for k, (a, b) in enumerate([(0, 20_000), (20_000, 50_000), (50_000, 120_000), (120_000, 260_000), (260_000, 1_000_000)])], "band bigint, low double, high double")
    got = rel.range_join(load(spark, d, "orders").select("o_orderkey", "o_totalprice"), bands, "o_totalprice", "low", "high", 10_000.0)
    return got.groupBy("band").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("first_order"))


def rel_interval_join(spark, d):
    e = load(spark, d, "events")
    a = e.filter("event_type = 'view'").select(F.col("event_id").alias("a_id"), "user_id", F.col("ts").alias("a_ts"))
    b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("b_id"), "user_id", F.col("ts").alias("b_ts"))
    return rel.interval_join(a, b, "user_id", "a_ts", "b_ts", 3600).select("a_id", "b_id", "user_id")


def rel_lateral(spark, d):
    """The dearest order of each customer."""
    top = rel.top_per_group(load(spark, d, "orders"), ["o_custkey"], [F.desc("o_totalprice"), F.asc("o_orderkey")], 1)
    return load(spark, d, "customer").join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey", "o_totalprice")


def rel_topk_group(spark, d):
    return rel.top_per_group(load(spark, d, "lineitem"), ["l_returnflag"], [F.desc("l_extendedprice"), F.asc("l_orderkey"), F.asc("l_linenumber")], 5).select("l_returnflag", "l_orderkey", "l_linenumber", "l_extendedprice")


def rel_window_frames(spark, d):
    o = load(spark, d, "orders")
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return o.select(
        "o_orderkey", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(4).over(w).cast("bigint").alias("nt"),
        F.lag("o_orderkey").over(w).alias("prev"), F.lead("o_orderkey").over(w).alias("next"), F.sum(_m("o_totalprice")).over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("double").alias("running"), F.count("*").over(Window.partitionBy("o_custkey").orderBy(F.unix_seconds(F.col("o_orderdate").cast("timestamp"))).rangeBetween(-90 * 86400, 0)).alias("last_90_days"),
    )


def rel_union(spark, d):
    a, b = load(spark, d, "nation").select(F.col("n_name").alias("name")), load(spark, d, "region").select(F.col("r_name").alias("name"))
    return a.unionByName(b).distinct()


def rel_intersect(spark, d):
    """R06 written as a set operation: ids of the raw top set that are gated."""
    from . import pool_queries as pq

    s = pq.gated(spark, d)
    top = pq.rank.top_percent(s, "raw_sim", 30.0).select("pair_id")
    return top.intersect(s.filter("gated").select("pair_id"))


def rel_except(spark, d):
    from . import pool_queries as pq

    s = pq.sheet(spark, d)
    return s.select("pair_id").exceptAll(pq.rank.top_percent(s, "raw_sim", 30.0).select("pair_id"))


def rel_pivot(spark, d):
    return load(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


def rel_unpivot(spark, d):
    return rel_pivot(spark, d).unpivot("source", ["de", "en", "es", "fr"], "lang", "n")


def rel_json(spark, d):
    k = F.from_json("props", "k int")["k"]
    return load(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("total"), F.max(F.get_json_object("props", "$.k").cast("bigint")).alias("most"), F.count(k).alias("n"))


def rel_variant(spark, d):
    return load(spark, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


def rel_dates(spark, d):
    o = load(spark, d, "orders")
    return o.groupBy(F.year("o_orderdate").cast("bigint").alias("y"), F.month(F.date_trunc("quarter", "o_orderdate")).cast("bigint").alias("q_month")).agg(F.count("*").alias("n"), F.max(F.datediff(F.col("o_orderdate").cast("date") + F.expr("INTERVAL 30 DAYS"), F.col("o_orderdate").cast("date"))).cast("bigint").alias("gap"))


def rel_strings(spark, d):
    c = load(spark, d, "customer")
    return c.select("c_custkey", F.initcap(F.lower("c_mktsegment")).alias("seg"), F.length("c_name").cast("bigint").alias("len"), F.levenshtein("c_name", F.lit("Customer#000000001")).cast("bigint").alias("lev"), F.instr("c_name", "#").cast("bigint").alias("at"), F.translate("c_name", "0", "o").alias("tr"), F.md5(F.col("c_name").cast("binary")).alias("h"))


def rel_arrays(spark, d):
    t = load(spark, d, "benchmark").select("item_id", tx.tokens("text").alias("t"))
    return t.select("item_id", F.size(F.array_distinct("t")).cast("bigint").alias("n_distinct"), F.aggregate("t", F.lit(0).cast("bigint"), lambda a, w: a + F.length(w)).alias("letters"), F.array_join(F.slice("t", 1, 3), "-").alias("head"), F.size(F.filter("t", lambda w: F.length(w) > 5)).cast("bigint").alias("n_long"), F.arrays_overlap("t", F.array(F.lit("the"), F.lit("der"))).alias("has_article"))


def rel_maps(spark, d):
    t = load(spark, d, "conversations").groupBy("conv_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("turn", F.length(F.coalesce("text", F.lit("")))))) ).alias("m"))
    kept = F.map_filter("m", lambda k, v: v > 200)
    return t.select("conv_id", F.size("m").cast("bigint").alias("n"), F.size(kept).cast("bigint").alias("n_long"), F.coalesce(F.element_at("m", F.lit(0).cast("bigint")), F.lit(-1)).cast("bigint").alias("first_len"))


def rel_math(spark, d):
    p = load(spark, d, "part")
    return p.groupBy(F.width_bucket("p_retailprice", F.lit(900.0), F.lit(2000.0), F.lit(11)).alias("bucket")).agg(F.count("*").alias("n"), F.round(F.avg(F.sqrt("p_retailprice")), 6).alias("mean_root"), F.round(F.sum(F.log1p(F.col("p_size"))), 4).alias("logs"), F.max(F.greatest(F.col("p_size"), F.lit(10))).cast("bigint").alias("most"))


def rel_regression(spark, d):
    return load(spark, d, "lineitem").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 3).alias("slope"), F.round(F.percentile("l_discount", 0.5), 6).alias("median_discount"))


def rel_count_distinct(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("n_parts"), F.count_distinct("l_suppkey").alias("n_suppliers"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"))


def rel_skew_sum(spark, d):
    return rel.salted_sum(load(spark, d, "lineitem").withColumn("l_quantity", _m("l_quantity")), "l_returnflag", "l_quantity").withColumn("l_quantity", F.col("l_quantity").cast("double"))


def rel_filters(spark, d):
    c = load(spark, d, "documents")
    return c.filter(F.col("lang").isin("en", "de") & F.col("n_chars").between(500, 3000) & F.col("source").rlike("^src[0-4]$") & ~F.col("source").eqNullSafe("src2")).select("doc_id", F.when(F.col("n_chars") > 1500, "long").otherwise("short").alias("size"))


def rel_sample_lang(spark, d):
    """A stratified sample: other shares for each language, by a salted number."""
    u = fx.salted("doc_id", "strata") / float(1 << 32)
    share = F.when(F.col("lang") == "en", 0.1).when(F.col("lang") == "de", 0.5).otherwise(1.0)
    return load(spark, d, "documents").filter(u < share).select("doc_id", "lang")


def rel_mean_vector(spark, d):
    """A pandas grouped aggregate: the norm of each label's mean vector."""
    means = load(spark, d, "embeddings").groupBy("label").agg(vx.mean_vector(F.col("embedding").cast("array<double>")).alias("m"))
    return means.select(F.col("label").cast("bigint").alias("label"), F.round(vx.norm("m"), 6).alias("norm"))


def rel_sort_within(spark, d):
    """A range-partitioned, sorted layout; the first rows by price."""
    return load(spark, d, "part").repartitionByRange(4, "p_retailprice").sortWithinPartitions("p_retailprice", "p_partkey").select("p_partkey", "p_retailprice").orderBy("p_retailprice", "p_partkey").limit(30)


def rel_udtf(spark, d):
    """Trigrams of benchmark texts by a table function in a lateral join."""
    tables.register(spark)
    load(spark, d, "benchmark").createOrReplaceTempView("capmix_benchmark")
    return spark.sql("SELECT item_id, count(*) AS n_grams, count(DISTINCT gram) AS n_unique FROM capmix_benchmark, LATERAL capmix_ngrams(text, 3) GROUP BY item_id")


def rel_formats(spark, d):
    """Nations through every text format: written and read with declared schemas, and counted."""
    path = shared_path(spark, "formats")
    nations = load(spark, d, "nation").select(F.col("n_nationkey").cast("bigint").alias("k"), F.col("n_name").alias("name"))
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        nations.write.format(kind).save(f"{path}/{kind}")
        one = spark.read.schema("k bigint, name string").format(kind).load(f"{path}/{kind}").agg(F.count("*").alias("n"), F.sum("k").alias("total"), F.max("name").alias("last")).select(F.lit(kind).alias("kind"), "*")
        out = one if out is None else out.union(one)
    nations.select("name").write.text(f"{path}/text")
    return out.union(spark.read.text(f"{path}/text").agg(F.count("*").alias("n"), F.lit(None).cast("bigint").alias("total"), F.max("value").alias("last")).select(F.lit("text").alias("kind"), "*"))


def enc_hashed(spark, d):
    vecs = HashedEncoder().encode(load(spark, d, "benchmark"), "item_id", "text")
    return vecs.select(F.col("key").alias("item_id"), F.posexplode("vec").alias("dim", "value")).filter("value <> 0").select("item_id", F.col("dim").cast("bigint").alias("dim"), F.round("value", 6).alias("value"))


def enc_stored(spark, d):
    """The stored-vector encoder: pool images of the first documents and their vectors' sums."""
    pairs = fx.planted_pairs(spark, d).select("pair_id", "image_id")
    got = StoredEncoder(load(spark, d, "embeddings"), "vec_id", "embedding").encode(pairs, "image_id")
    return got.groupBy("key").agg(F.count("*").alias("n"), F.round(F.first(vx.norm("vec")), 4).alias("norm")).withColumnRenamed("key", "image_id")


def queries():
    return {k: v for k, v in globals().items() if k.startswith(("rel_", "enc_"))}


def oracle_sql():
    asof = "SELECT a.event_id, a.user_id, b.value FROM (SELECT * FROM events WHERE event_type = 'error') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') b ON a.user_id = b.user_id AND a.ts >= b.ts"
    return {
        "rel_pricing": "SELECT l_returnflag, l_linestatus, sum(l_quantity::DECIMAL(14,2))::DOUBLE AS sum_qty, sum(l_extendedprice::DECIMAL(14,2))::DOUBLE AS sum_price, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL",
        "rel_nation_revenue": "SELECT r_name, n_name, sum(l_extendedprice::DECIMAL(14,2))::DOUBLE AS revenue, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
        "rel_top_customers": "SELECT c_custkey, c_name, sum(o_totalprice::DECIMAL(14,2))::DOUBLE AS spent FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL ORDER BY spent DESC, c_custkey LIMIT 20",
        "rel_rollup": "SELECT lang, source, count(*) AS n, grouping_id(lang, source)::BIGINT AS gid FROM documents GROUP BY ROLLUP (lang, source)",
        "rel_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::DECIMAL(14,2))::DOUBLE AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
        "rel_grouping_sets": "SELECT lang, source, count(*) AS n, grouping_id(lang, source)::BIGINT AS gid FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
        "rel_semi": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
        "rel_anti": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
        "rel_outer": "SELECT d.doc_id, l.doc_id AS label_id, lang, quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id",
        "rel_asof": asof,
        "rel_range_join": "WITH b(band, low, high) AS (VALUES (0, 0, 20000), (1, 20000, 50000), (2, 50000, 120000), (3, 120000, 260000), (4, 260000, 1000000)) SELECT band::BIGINT AS band, count(*) AS n, min(o_orderkey) AS first_order FROM orders JOIN b ON o_totalprice >= low AND o_totalprice < high GROUP BY band",
        "rel_interval_join": "SELECT a.event_id AS a_id, b.event_id AS b_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'",
        "rel_lateral": "SELECT c_custkey, o_orderkey, o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1)",
        "rel_topk_group": "SELECT l_returnflag, l_orderkey, l_linenumber, l_extendedprice FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) <= 5",
        "rel_window_frames": "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(4) OVER w AS nt, lag(o_orderkey) OVER w AS prev, lead(o_orderkey) OVER w AS next, sum(o_totalprice::DECIMAL(14,2)) OVER (w ROWS UNBOUNDED PRECEDING)::DOUBLE AS running, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 90 DAYS PRECEDING AND CURRENT ROW) AS last_90_days FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
        "rel_union": "SELECT n_name AS name FROM nation UNION SELECT r_name FROM region",
        "rel_intersect": f"SELECT pair_id FROM ({q.recipe('raw_top30_gate')})",
        "rel_except": f"WITH {q.SHEET.strip()}, {q.TOP30.strip()} SELECT pair_id FROM s EXCEPT ALL SELECT pair_id FROM t30",
        "rel_pivot": "SELECT source, " + ", ".join(f"count(*) FILTER (lang = '{x}') AS {x}" for x in ("de", "en", "es", "fr")) + " FROM documents GROUP BY source",
        "rel_unpivot": "SELECT s.source, l.lang, count(d.doc_id) AS n FROM (SELECT DISTINCT source FROM documents) s CROSS JOIN (VALUES ('de'), ('en'), ('es'), ('fr')) l(lang) LEFT JOIN documents d ON d.source = s.source AND d.lang = l.lang GROUP BY ALL",
        "rel_json": "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS total, max((props->>'k')::BIGINT) AS most, count(props->>'k') AS n FROM events GROUP BY event_type",
        "rel_variant": "SELECT event_id, (props->>'k')::BIGINT AS k FROM events",
        "rel_dates": "SELECT year(o_orderdate) AS y, month(date_trunc('quarter', o_orderdate)) AS q_month, count(*) AS n, 30::BIGINT AS gap FROM orders GROUP BY ALL",
        "rel_strings": "SELECT c_custkey, upper(c_mktsegment[1]) || lower(c_mktsegment[2:]) AS seg, length(c_name) AS len, levenshtein(c_name, 'Customer#000000001') AS lev, instr(c_name, '#') AS at, translate(c_name, '0', 'o') AS tr, md5(c_name) AS h FROM customer",
        "rel_arrays": r"SELECT item_id, len(list_distinct(t)) AS n_distinct, list_sum(list_transform(t, lambda x: length(x)))::BIGINT AS letters, array_to_string(t[1:3], '-') AS head, len(list_filter(t, lambda x: length(x) > 5)) AS n_long, list_has_any(t, ['the', 'der']) AS has_article FROM (SELECT item_id, regexp_extract_all(lower(text), '\p{L}+') AS t FROM benchmark)",
        "rel_maps": "SELECT conv_id, count(*) AS n, count(*) FILTER (length(coalesce(text, '')) > 200) AS n_long, coalesce(max(length(coalesce(text, ''))) FILTER (turn = 0), -1) AS first_len FROM conversations GROUP BY conv_id",
        "rel_math": "SELECT CASE WHEN p_retailprice < 900 THEN 0 WHEN p_retailprice >= 2000 THEN 12 ELSE floor((p_retailprice - 900) / 100)::BIGINT + 1 END::BIGINT AS bucket, count(*) AS n, round(avg(sqrt(p_retailprice)), 6) AS mean_root, round(sum(ln(p_size + 1)), 4) AS logs, max(greatest(p_size, 10)) AS most FROM part GROUP BY ALL",
        "rel_regression": "SELECT round(corr(l_quantity, l_extendedprice), 6) AS corr, round(regr_slope(l_extendedprice, l_quantity), 3) AS slope, round(quantile_cont(l_discount, 0.5), 6) AS median_discount FROM lineitem",
        "rel_count_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS n_parts, count(DISTINCT l_suppkey) AS n_suppliers, (array_agg(l_orderkey ORDER BY l_extendedprice DESC, l_orderkey DESC))[1] AS dearest FROM lineitem GROUP BY l_returnflag",
        "rel_skew_sum": "SELECT l_returnflag, sum(l_quantity::DECIMAL(14,2))::DOUBLE AS l_quantity FROM lineitem GROUP BY l_returnflag",
        "rel_filters": "SELECT doc_id, CASE WHEN n_chars > 1500 THEN 'long' ELSE 'short' END AS size FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 500 AND 3000 AND regexp_matches(source, '^src[0-4]$') AND source IS DISTINCT FROM 'src2'",
        "rel_sample_lang": f"SELECT doc_id, lang FROM documents WHERE {q.salted('doc_id', 'strata')} / 4294967296.0 < CASE lang WHEN 'en' THEN 0.1 WHEN 'de' THEN 0.5 ELSE 1.0 END",
        "rel_mean_vector": "WITH m AS (SELECT label, dim, avg(x) AS x FROM (SELECT label, unnest(range(64)) AS dim, unnest(embedding::DOUBLE[]) AS x FROM embeddings) GROUP BY ALL) SELECT label::BIGINT AS label, round(sqrt(sum(x * x)), 6) AS norm FROM m GROUP BY label",
        "rel_udtf": r"SELECT item_id, count(*) AS n_grams, count(DISTINCT gram) AS n_unique FROM (SELECT item_id, array_to_string(t[k : k + 2], ' ') AS gram FROM (SELECT item_id, t, unnest(range(1, len(t) - 1)) AS k FROM (SELECT item_id, regexp_extract_all(lower(text), '\p{L}+') AS t FROM benchmark) WHERE len(t) >= 3)) GROUP BY item_id",
        "rel_formats": "SELECT kind, count(*) AS n, CASE WHEN kind <> 'text' THEN sum(n_nationkey)::BIGINT END AS total, max(n_name) AS last FROM nation CROSS JOIN (VALUES ('csv'), ('json'), ('orc'), ('parquet'), ('text')) f(kind) GROUP BY kind",
        "enc_hashed": r"WITH b AS (SELECT item_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS t FROM benchmark), c AS (SELECT item_id, ('0x' || substr(md5(t), 1, 8))::BIGINT % 64 AS dim, count(*) AS n FROM b GROUP BY ALL) SELECT item_id, dim, round(n / sqrt(sum(n * n) OVER (PARTITION BY item_id)), 6) AS value FROM c",
        "enc_stored": f"WITH {q.VECTORS.strip()} SELECT image_id, count(*) AS n, round(sqrt(list_inner_product(any_value(v), any_value(v))), 4) AS norm FROM pairs JOIN e ON vec_id = image_id GROUP BY image_id",
        "rel_sort_within": "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice, p_partkey LIMIT 30",
    }
