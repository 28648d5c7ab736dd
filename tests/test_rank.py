"""Percent cuts: worked cases, the window reference, oversized bins, ties and missing scores."""

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from capmix.operators import rank

CASE = [(1, 0.5), (2, 0.4), (3, 0.4), (4, 0.4), (5, 0.1)]


def sheet(spark, data):
    return spark.createDataFrame([(i, None if s is None else float(s)) for i, s in data], "pair_id bigint, s double")


def ids(df):
    return sorted(r["pair_id"] for r in df.select("pair_id").collect())


def test_worked_case(spark):
    s = sheet(spark, CASE)
    cut = rank.cuts(s, "s", [40])[40]
    assert (cut.k, cut.sim, cut.id) == (2, 0.4, 2)
    assert ids(rank.top_percent(s, "s", 40)) == [1, 2]
    assert ids(rank.top_percent(s, "s", 40, ties="include")) == [1, 2, 3, 4]
    assert ids(rank.top_percent(s, "s", 0)) == []
    assert ids(rank.top_percent(s, "s", 100)) == [1, 2, 3, 4, 5]
    assert ids(rank.top_percent(s, "s", 1)) == [1]


def test_all_percents_equal_the_window(spark):
    s = sheet(spark, [(i, None if i % 7 == 0 else ((i * 37) % 11) / 10 - 0.5) for i in range(90)]).cache()
    cuts = rank.cuts(s, "s", [float(x) for x in range(0, 101, 9)])
    for x, cut in cuts.items():
        want = ids(rank.top_percent_window(s, "s", x))
        assert ids(s.filter(cut.covers_rank(s.s, s.pair_id))) == want
        assert len(want) == min(rank.rows_wanted(x, 90), s.filter("s IS NOT NULL").count())


def test_missing_scores_never_pass_and_count(spark):
    s = sheet(spark, [(1, float("nan")), (2, None), (3, 0.2), (4, 0.1)])
    assert ids(rank.top_percent(s, "s", 25)) == [3]
    assert ids(rank.top_percent(s, "s", 100)) == [3, 4]


def test_oversized_and_equal_bins(spark):
    equal = sheet(spark, [(i, 0.25) for i in range(50)])
    assert ids(rank.top_percent(equal, "s", 30, bin_rows=4)) == list(range(15))
    close = sheet(spark, [(i, 0.25 + (i % 13) * 1e-9) for i in range(60)])
    assert ids(rank.top_percent(close, "s", 30, bin_rows=4)) == ids(rank.top_percent_window(close, "s", 30))


def test_empty_and_single(spark):
    assert ids(rank.top_percent(sheet(spark, []), "s", 30)) == []
    assert ids(rank.top_percent(sheet(spark, [(7, 0.1)]), "s", 1)) == [7]


def test_sketch_cut_is_close(spark):
    s = sheet(spark, [(i, i / 1000) for i in range(1000)])
    assert abs(rank.approx_cut(s, "s", 30) - 0.7) < 0.01
    assert abs(rank.kll_cut(s, "s", 30) - 0.7) < 0.05


@given(st.floats(0, 100), st.integers(0, 10_000))
@settings(max_examples=200)
def test_rows_wanted_bounds(x, n):
    assert 0 <= rank.rows_wanted(x, n) <= n


def test_percent_range():
    with pytest.raises(ValueError):
        rank.rows_wanted(101, 5)


def test_no_single_partition_in_the_cut(spark):
    s = sheet(spark, CASE)
    plan = rank.top_percent(s, "s", 40)._jdf.queryExecution().toString()
    assert "SinglePartition" not in plan and "CartesianProduct" not in plan
