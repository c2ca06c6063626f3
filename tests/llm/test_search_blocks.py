"""Blocks of queries and of cells of the vector search."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from keyless.llm import vafile


def vectors(n, width=6, seed=5):
    rng = np.random.default_rng(seed)
    x = np.round(rng.normal(size=(n, width)), 3)
    x[n // 2 :] = x[: n - n // 2]  # copies, so that scores tie
    return [(i, v) for i, v in enumerate(x.tolist())]


def brute(rows, each, k):
    x = np.floor(256 * np.array([v for _, v in rows]))
    out = set()
    for q in range(0, len(rows), each):
        score = (x @ x[q]).astype(int).tolist()
        best = sorted((-s, i) for i, s in enumerate(score) if i != q)[:k]
        out |= {(q, r + 1, i, -s) for r, (s, i) in enumerate(best)}
    return out


@pytest.mark.parametrize("held", [1, 1 << 20])
def test_queries_visit_many_groups_without_a_broadcast_of_their_copies(spark, monkeypatch, held):
    plans, keep = {}, vafile.Workspace.keep

    def watched(self, df, name, **options):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        return keep(self, df, name, **options)

    monkeypatch.setattr(vafile.Workspace, "keep", watched)
    monkeypatch.setattr(vafile, "HELD", held, raising=False)
    rows = vectors(400)
    got = vafile.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") % 20 == 0, k=4, block=8, queries=3)
    assert {tuple(r) for r in got.collect()} == brute(rows, 20, 4)
    assert "Broadcast" not in plans["found"]


def test_queries_are_packed_in_the_least_type():
    for most, kind in ((32767, np.int16), (32768, np.int32), (2**31, np.float64)):
        assert vafile.query_type(np.array([-5.0]), np.array([float(most)])) == kind
    assert vafile.query_type(np.zeros(0), np.zeros(0)) == np.int16
    assert vafile.query_type(np.array([-32769.0]), np.array([0.0])) == np.int32


def test_values_of_more_than_two_bytes_are_asked_exactly(spark):
    rows = [(i, [200000.0 + 7 * i, 1.0]) for i in range(8)]
    got = vafile.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") == 0, k=2, block=3, queries=1)
    x = np.array([v for _, v in rows]) * 256
    assert sorted((r.vec_id, r.score) for r in got.collect()) == [(i, int(x[i] @ x[0])) for i in (6, 7)]
