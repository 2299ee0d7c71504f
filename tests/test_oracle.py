"""Queries against their SQL in DuckDB. The driver runs them all; here are some of each kind."""

import pytest
from conftest import MIDDLE, same

from pivotrank.plans import registry

NAMES = """exact_l2 exact_kl_right exact_js exact_levenshtein exact_cosine_sparse pivots permutation_rank permutation_rank_native permutation_order
binarised_bits toy_example perm_rho perm_rho_scan perm_hamming perm_counting_select prefix_copies prefix_fallback postings_full_rho
postings_truncated postings_maxdiff postings_toy shared_threshold shared_scan shared_forward seqindex_simulations pivot_table_exact
balltree_metric_l2 permtree mplsh_home random_projection_l2 median_rank_pivot fraction_for_recall triangle_rate mu_defect_angular counterexample_1d
asof_events interval_events setops_candidates stream_mixes index_append_delete""".split()


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    assert same(registry.queries()[name](spark, MIDDLE), duck.sql(registry.oracle_sql()[name]))


def test_entry_runs(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
