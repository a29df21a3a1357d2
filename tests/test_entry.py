import fnmatch

import pytest

import __spark_entry__ as entry
from lexbridge import workloads
from tests.oracle import check

FAST = "text_* domain_counts split_counts pivot_p* pivot_i* pivot_en* bank_init bank_td_* bank_refresh_epoch bank_error evidence_routing nb_accuracy metrics_* kg_merged kg_noise inject_scoped inject_visible_pairs inject_stats mask_pivots pivot_predictor_counts wl_false_links att_head_mean att_piece_mean grid_average winners gain_table wl_orders_polarity wl_stream_bank op_join_* op_window_r* op_cube op_fn_* op_stream_tumbling op_stream_interval_join".split()
NAMES = [n for n in workloads.ORACLES if any(fnmatch.fnmatch(n, p) for p in FAST)]


def test_entry_has_rows(spark):
    assert entry.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, small, name):
    check(spark, workloads.QUERIES[name], workloads.ORACLES[name], small)
