import pytest

import __spark_entry__
from stationlink.plans import experiments

#: One of each kind; the driver compares all of them at a larger scale.
NAMES = (
    "st_identifiers st_pairs_truth pg_pairs_truth x_spice_labels x_spice_positions m_edit m_prefix_edit m_jaro_winkler m_bts_literal m_tfidf "
    "t_normalize t_trigrams f_delta f_grid e_dimensions e_best_table e_combo_table e_best_table_pg e_spice_p e_worst_tfidf r_join_outer r_asof r_feed_roundtrip u_merged_stations s_window_session s_static_match "
    "f_order x_spelling r_distinct_approx r_match_feeds s_late"
).split()


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(name, same):
    same(name, experiments.QUERIES[name], experiments.ORACLES[name])


def test_every_oracle_has_a_query():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_entry_gives_rows(spark):
    assert __spark_entry__.entry(spark).count() == 5
