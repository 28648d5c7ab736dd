"""A spread of registered queries against DuckDB; the driver compares all of them."""

import pytest

from capmix.plans import catalogue
from tests.conftest import ORACLE, rows

QUERIES, SQL = catalogue.queries(), catalogue.oracle_sql()
CHECKED = (
    "sim_rows sim_rows_arrow sel_mix30_filtered sel_mix30_filtered_gate sel_gen_top75_gate sel_swap30 cut_points recipe_sheet sweep_curves scale_grid gate_centres_iter1 gate_report "
    "budget_draws gram retr_rk zs_cluster metric_agreement words_hist uniq_trigrams_hashed div_curve noise_div cap_extract consensus heur_discard near_dups near_dup_members prep_titles pages_pool rel_asof rel_interval_join rel_window_frames stream_session"
).split()


def test_every_oracle_has_a_query():
    assert set(SQL) <= set(QUERIES)
    assert len(QUERIES) > 140


@pytest.mark.parametrize("name", CHECKED)
def test_query_matches_sql(spark, duck, name):
    got, want = QUERIES[name](spark, ORACLE).toPandas(), duck.sql(SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)
