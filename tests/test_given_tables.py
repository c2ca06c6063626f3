"""Tables of formulas and counted chances are made from the keys of the orders."""

import pytest

from keyless import claims, thresholds as T, workloads  # noqa: F401


@pytest.mark.parametrize("name", [
    "filter_space_table", "kary_vs_rank_threshold", "peel_threshold_curve", "rank_success_curve", "retrieval_space_table", "square_success_constant",
    "square_success_rate", "success_curves", "threshold_sides", "threshold_table", "two_run_rank_rate",
])
def test_orders_are_read(spark, sf, name):
    assert any("orders.parquet" in f for f in workloads.QUERIES[name](spark, sf).inputFiles())


def test_published_thresholds(spark, sf):
    got = {r["k"]: r["theta"] for r in workloads.QUERIES["threshold_table"](spark, sf).collect()}
    assert all(abs(got[k] - x) <= 1e-5 for k, x in {3: 0.88949, 4: 0.96714, 5: 0.98916, 6: 0.99622}.items())
    assert workloads.QUERIES["square_success_constant"](spark, sf).first()[0] == T.SQUARE_SUCCESS
