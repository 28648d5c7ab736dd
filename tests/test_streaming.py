"""Streams: exactly-once sink, late rows, live histogram cut."""

import glob
import os

from pyspark.sql import functions as F

from capmix.streaming import arrivals as st


def write_events(spark, path, batches):
    for k, data in enumerate(batches):
        df = spark.createDataFrame(data, "event_id bigint, ts string, user_id bigint, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp_ntz")).withColumn("props", F.lit("{}"))
        df.coalesce(1).write.parquet(f"{path}/b{k}")
        for f in glob.glob(f"{path}/b{k}/*.parquet"):
            os.utime(f, (1_700_000_000 + 10 * k,) * 2)  # files are taken in order of their times


def test_late_rows_are_dropped(spark, tmp_path):
    write_events(spark, tmp_path, [[(1, "2024-01-02 10:00:00", 1, "view", 1.0)], [(2, "2024-01-02 18:00:00", 1, "view", 1.0)], [(5, "2024-01-02 18:10:00", 1, "view", 1.0)], [(3, "2024-01-02 10:30:00", 1, "view", 1.0), (4, "2024-01-03 10:00:00", 1, "view", 1.0)]])
    stream = st.event_stream(spark, f"{tmp_path}/b*", files_per_batch=1)
    got = st.run_to_table(st.tumbling(stream, "1 hour"), "late", "append").collect()
    seen = {(str(r["start"]), r["n"]) for r in got}
    assert ("2024-01-02 10:00:00", 1) in seen  # the third event came too late for its window


def test_shard_sink_is_idempotent(spark, tmp_path):
    write_events(spark, tmp_path / "in", [[(k, "2024-01-01 00:00:00", k, "view", 1.0) for k in range(5)], [(9, "2024-01-01 01:00:00", 1, "view", 1.0)]])
    for _ in range(2):  # a second run finds nothing new
        st.shard_sink(st.event_stream(spark, f"{tmp_path}/in/b*", 1), f"{tmp_path}/out", f"{tmp_path}/cp")
    assert spark.read.parquet(f"{tmp_path}/out").count() == 6


def test_cut_from_histogram():
    counts = {10: 50, 40: 30, 60: 20}
    assert st.cut_from_histogram(counts, 20) == 60 * 2 / 64 - 1
    assert st.cut_from_histogram(counts, 21) == 40 * 2 / 64 - 1


def test_rows_of_a_stream_stay_off_the_driver(spark, tmp_path):
    write_events(spark, tmp_path, [[(k, f"2024-01-0{b + 1} 00:00:00", k % 3, "view", 1.0) for k in range(20 * b, 20 * b + 20)] for b in range(3)])

    def stream():
        return st.event_stream(spark, f"{tmp_path}/b*", files_per_batch=1)

    for got, want in ((st.run_to_table(stream().select("event_id"), "all"), 60), (st.run_to_table(st.sessions(stream()), "last", "complete"), 9)):
        assert got.count() == want and got.inputFiles()  # written by executors: a table in memory has no files
    nothing = st.run_to_table(stream().filter("event_id < 0").select("event_id"), "none")
    assert nothing.columns == ["event_id"] and nothing.count() == 0
