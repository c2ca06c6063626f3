import pytest

from keyless import claims, flows, relational, surface, variants, workloads  # noqa: F401
from tests.compare import connect, same

ALL = workloads.QUERIES | relational.QUERIES
SQL = workloads.SQL | relational.SQL
#: Held to bounds in test_measures.
BOUNDED = {"build_scaling", "overflow_small_tables", "store_measures", "overflow_by_reason", "overflow_by_block_size", "tries_histogram", "store_bits", "filter_rates", "success_curves", "rank_success_curve", "peel_threshold_curve", "kary_vs_rank_threshold", "two_run_rank_rate"}


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


def test_every_query_has_sql_or_bounds():
    assert set(ALL) - set(SQL) == BOUNDED


@pytest.mark.parametrize("name", sorted(SQL))
def test_query(spark, sf, con, name):
    same(ALL[name](spark, sf), con, SQL[name])
    spark.catalog.clearCache()
