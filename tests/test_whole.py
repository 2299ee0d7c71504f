"""Queries over all rows beside those whose SQL covers a part."""

import pytest
from conftest import MIDDLE, same

from pivotrank.plans import registry
from pivotrank.sources import workloads as W

TRIPLES = "triangle_rate_all triangle_rate_l2_all triangle_rate_kl_all mu_defect_angular_all mu_defect_sqrt_js_all mu_defect_sqrt_kl_all".split()


@pytest.mark.parametrize("name", TRIPLES)
def test_all_triples_equal_sql(spark, duck, name):
    assert same(registry.queries()[name](spark, MIDDLE), duck.sql(registry.oracle_sql()[name]))


def test_all_points_give_a_triple(spark):
    got = registry.queries()["triangle_rate_l2_all"](spark, MIDDLE).first()["triples"]
    assert got >= 0.95 * W.embeddings(spark, MIDDLE).count()


@pytest.mark.parametrize("name", ["exact_levenshtein_drawn", "perm_levenshtein_bits_drawn", "dataset_summary_drawn"])
def test_drawn_sequences_equal_sql(spark, duck, name):
    assert same(registry.queries()[name](spark, MIDDLE), duck.sql(registry.oracle_sql()[name]))


def test_drawn_sequences_begin_anywhere(spark):
    heads, drawn = (W.BUILDERS[n](spark, MIDDLE).select("x").distinct().count() for n in ("sequences", "sequences_drawn"))
    print("distinct heads, drawn:", heads, drawn)
    assert drawn > heads


def test_every_conversation_has_a_row(spark):
    import duckdb

    large = MIDDLE.replace("0.01", "0.1")  # 1,000 conversations; the middle tables have 100
    con = duckdb.connect()
    con.sql(f"create view conversations as select * from '{large}/conversations.parquet'")
    got = registry.queries()["conversation_turns_all"](spark, large)
    assert same(got, con.sql(registry.oracle_sql()["conversation_turns_all"]))
    assert got.count() == con.sql("SELECT count(DISTINCT conv_id) FROM conversations").fetchall()[0][0] == 1000
