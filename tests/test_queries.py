"""Registered queries against their SQL twins on the smallest tables, and the entry point."""

import duckdb
import pytest

import __spark_entry__ as entry_point
from bucketseed.experiments import registry
from bucketseed.tables import NAMES
from tests.conftest import SF

CHECKED = [
    "b_word_sets", "b_shingles", "b_kl_buckets_docs", "b_doph_docs", "b_minhash_nns", "t_dense_letters", "t_ranked_equals_window",
    "t_hetero_events", "t_discretise_joint", "s_full_docs", "s_dedup_drop", "s_local_vote", "s_multi_load", "a_centroids",
    "a_assign_dense", "a_assign_match", "a_two_passes", "l_lloyd_3", "x_ivf_search", "o_windows", "o_asof", "o_udtf", "st_session",
]


@pytest.fixture(scope="module")
def twin():
    con = duckdb.connect()
    for name in NAMES:
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{SF}/{name}.parquet'")
    return con


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_twin(spark, twin, name):
    a = registry.queries()[name](spark, SF).toPandas()
    b = twin.execute(registry.oracle_sql()[name]).df()
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    rows = lambda df: sorted(map(str, df[cols].itertuples(index=False, name=None)))
    assert rows(a) == rows(b)


def test_entry_and_names(spark):
    assert entry_point.entry(spark).count() >= 1
    assert set(entry_point.oracle_sql()) <= set(entry_point.queries())
