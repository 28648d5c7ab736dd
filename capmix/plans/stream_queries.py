"""Queries of the streaming surface; each equals a batch query on the same rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import rank
from ..sources.tables import load
from ..streaming import arrivals as st
from . import ctes as q
from . import pool_queries as pq


def _events(spark, d):
    return st.event_stream(spark, f"{d}/event[s].parquet")


def _ntz(df, *names):
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in names})


def stream_admit(spark, d):
    s = pq.sheet(spark, d)
    cut = rank.cuts(s, "raw_sim", [30.0])[30.0]
    got = st.run_to_table(st.admitted(_events(spark, d), s, cut, load(spark, d, "documents").count()), "admit")
    return got.groupBy("origin").agg(F.count("*").alias("n"), F.count_distinct("pair_id").alias("n_pairs"))


def stream_tumbling(spark, d):
    out = st.run_to_table(st.tumbling(_events(spark, d)), "tumbling", "complete")
    return _ntz(out, "start").withColumn("total", F.round("total", 4))


def stream_sliding(spark, d):
    return _ntz(st.run_to_table(st.sliding(_events(spark, d)), "sliding", "complete"), "start")


def stream_session(spark, d):
    return _ntz(st.run_to_table(st.sessions(_events(spark, d)), "session", "complete"), "start", "end")


def stream_dedup(spark, d):
    twice = _events(spark, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return st.run_to_table(st.deduplicated(twice), "dedup").select("event_id", "user_id")


def stream_hist(spark, d):
    n = load(spark, d, "documents").count()
    return st.run_to_table(st.live_histogram(_events(spark, d), pq.sheet(spark, d), n), "hist", "update").groupBy("bin").agg(F.max("n").alias("n"))


def stream_join(spark, d):
    return st.run_to_table(st.interval_join(_events(spark, d), "view", "purchase"), "join")


def queries():
    return {k: v for k, v in globals().items() if k.startswith("stream_")}


def oracle_sql():
    ev = "ev AS (SELECT event_id, event_id % (SELECT count(*) FROM documents) AS pair_id FROM events)"
    return {
        "stream_admit": f"WITH {q.SHEET.strip()}, {q.TOP30.strip()}, {ev}, a AS (SELECT event_id, s.pair_id, CASE WHEN s.pair_id IN (SELECT pair_id FROM t30) THEN 'raw' WHEN gen_sim >= (SELECT cut FROM cut) THEN 'gen' END AS origin FROM ev JOIN s ON s.pair_id = ev.pair_id) SELECT origin, count(*) AS n, count(DISTINCT pair_id) AS n_pairs FROM a WHERE origin IS NOT NULL GROUP BY origin",
        "stream_tumbling": "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL",
        "stream_sliding": "SELECT time_bucket(INTERVAL 6 HOURS, ts, TIMESTAMP '2024-01-01') - to_hours(6 * k) AS start, count(*) AS n FROM events CROSS JOIN range(4) r(k) GROUP BY ALL",
        "stream_session": "WITH a AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM a) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTES AS \"end\", count(*) AS n FROM b GROUP BY user_id, sid",
        "stream_dedup": "SELECT event_id, user_id FROM events",
        "stream_hist": f"WITH {q.SHEET.strip()}, {ev} SELECT least(floor((raw_sim + 1) * 32), 63)::BIGINT AS bin, count(*) AS n FROM ev JOIN s ON s.pair_id = ev.pair_id GROUP BY ALL",
        "stream_join": "SELECT a.event_id AS a_id, b.event_id AS b_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'",
    }
