"""A short rank is reported, not drawn away."""

import pytest

from keyless import allocation, workloads


def test_short_rank_is_false():
    assert allocation.rank_and_pivots([[0, 1], [1, 2]], [{0: 3, 1: 5}, {1: 7, 2: 1}], 3)
    assert not allocation.rank_and_pivots([[0, 1], [0, 1]], [{0: 3, 1: 5}, {0: 6, 1: 10}], 2)


@pytest.mark.parametrize("rank_ok", [None, False])
def test_missing_rank_is_a_violation(spark, sf, monkeypatch, rank_ok):
    rows = [(0, 1, 0, 2, True, True), (0, 2, 1, 2, True, rank_ok)]
    monkeypatch.setattr(allocation, "place", lambda *a, **b: spark.createDataFrame(rows, allocation.ROWS))
    assert workloads.QUERIES["placement_implies_rank"](spark, sf).first()["violations"] == 1
