"""Floating columns of the registered queries, rounded alike in a query and its oracle.

Sums of doubles depend on the order in which they are added, in the last digits; six decimals are what two engines can agree on.
"""

from __future__ import annotations

from pyspark.sql import functions as F

DIGITS = 6
#: Columns, and the queries whose results hold just these as doubles.
FLOATS = {
    ('p',): 'pivot_polarity pivot_polarity_occurrence pivot_polarity_centred bank_init bank_td_exact bank_td_fold bank_td_stepmean bank_td_tail wl_orders_polarity op_sql_function wl_stream_bank',
    ('entropy',): 'pivot_entropy',
    ('p_s', 'p_t', 'score'): 'pivot_pair_score',
    ('score',): 'pivot_initial_topk pivot_true_topk bank_refresh_epoch',
    ('N1', 'N2', 'N3', 'N4', 'FAR'): 'pivot_behaviour',
    ('error',): 'bank_error',
    ('conf',): 'pseudo_labels kg_candidates_vector kg_entity_facts',
    ('precision',): 'pseudo_quality',
    ('score', 'p_pos'): 'nb_predict',
    ('accuracy', 'balanced', 'f1'): 'nb_accuracy majority_accuracy pivot_vote_accuracy',
    ('auc',): 'metrics_auc',
    ('total', 'top'): 'att_cooc_matrix',
    ('a',): 'att_vector_heads att_head_mean att_piece_mean',
    ('tau', 'share'): 'kg_confidence_profile',
    ('tau',): 'kg_suggested_tau',
    ('outside_share', 'diversity'): 'kg_noise',
    ('average',): 'grid_average',
    ('accuracy',): 'winners',
    ('gain',): 'gain_table',
    ('twice',): 'op_projection',
    ('o_totalprice',): 'op_join_lateral op_top_k',
    ('quantity', 'discount'): 'op_aggregate',
    ('sd', 'r'): 'op_aggregate_stats',
    ('pr', 'cd'): 'op_window_distribution',
    ('before', 'after', 'first'): 'op_window_analytic',
    ('s3',): 'op_window_rows',
    ('l', 'e', 's', 'g', 'top'): 'op_fn_math',
    ('norm2',): 'op_fn_array',
    ('mean',): 'op_group_map',
}
COLUMNS = {name: columns for columns, names in FLOATS.items() for name in names.split()}


def rounded_query(name: str, query):
    columns = COLUMNS.get(name)
    if not columns:
        return query

    def run(spark, sf_dir):
        return query(spark, sf_dir).withColumns({c: F.round(c, DIGITS) + F.lit(0.0) for c in columns})

    run.__name__, run.__doc__ = name, query.__doc__
    return run


def rounded_oracle(name: str, sql: str) -> str:
    columns = COLUMNS.get(name)
    if not columns:
        return sql
    swaps = ", ".join(f'round("{c}", {DIGITS}) + 0.0::DOUBLE AS "{c}"' for c in columns)
    return f"SELECT * REPLACE ({swaps}) FROM (\n{sql}\n) AS r"
