"""Queries without SQL, held to their bounds; what the verdicts of a round found."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import linalg as A
from keyless import claims, flows, sharing, surface  # noqa: F401
from keyless import store as S
from keyless import thresholds as T
from keyless import workloads as W


def rows(spark, sf, name):
    return [r.asDict() for r in W.QUERIES[name](spark, sf).collect()]


def test_store_measures(spark, sf):
    got = {r["kind"]: r for r in rows(spark, sf, "store_measures")}
    assert all(r["logical_bits"] >= 8 * r["n"] and r["stored_bits"] >= 8 * r["n"] and r["excess_bits"] >= 0 for r in got.values())
    assert got["square"]["factor"] < got["sparse"]["factor"] < got["peel"]["factor"]
    assert (got["sparse"]["slots_read"], got["overflow"]["slots_read"]) == (4, 7)
    assert [k for k, r in got.items() if r["adaptive"]] == ["compressed", "overflow"]


def test_overflow_falls_with_the_block(spark, sf):
    got = rows(spark, sf, "overflow_by_reason")
    for block in (32, 64, 128, 256):
        assert sum(r["share"] for r in got if r["block"] == block) == pytest.approx(1)
    over = {r["block"]: r["share"] for r in rows(spark, sf, "overflow_by_block_size")}
    assert set(over) == {32, 64, 128, 256} and all(0 <= x <= 1 for x in over.values())
    assert sum(r["share"] for r in got if r["reason"] == "oversize" and r["block"] == 256) <= sum(r["share"] for r in got if r["reason"] == "oversize" and r["block"] == 32)


def test_tries_and_bits(spark, sf):
    tries = rows(spark, sf, "tries_histogram")
    assert {r["kind"] for r in tries} == {"sparse", "square", "peel"} and all(r["tries"] >= 1 and r["blocks"] > 0 for r in tries)
    mean = sum(r["tries"] * r["blocks"] for r in tries if r["kind"] == "square") / sum(r["blocks"] for r in tries if r["kind"] == "square")
    assert mean < 12  # 3.5 expected
    bits = {r["kind"]: r for r in rows(spark, sf, "store_bits")}
    assert bits["square"]["slot_bits_per_key"] == 8 and bits["sparse"]["slot_bits_per_key"] < 8.8 and bits["peel"]["slot_bits_per_key"] >= 8 * 1.22


def test_rates(spark, sf):
    for r in rows(spark, sf, "filter_rates"):
        p = r["expected"]
        assert r["rate"] == pytest.approx(r["hits"] / r["n"]) and abs(r["hits"] - r["n"] * p) <= 5 * math.sqrt(r["n"] * p * (1 - p)) + 1


@pytest.mark.parametrize("name", ["success_curves", "rank_success_curve", "peel_threshold_curve", "kary_vs_rank_threshold", "two_run_rank_rate"])
def test_curves(spark, sf, name):
    for r in rows(spark, sf, name):
        assert r["peel"] <= r["rank"] <= 1 and (r["kind"] if "kind" in r else "") == "repeat" or r["rank"] <= r["place"]
        if name == "rank_success_curve" and r["load"] < T.theta(r["k"]) - 0.05:
            assert r["rank"] >= 0.7
        if name == "rank_success_curve" and r["load"] > T.theta(r["k"]) + 0.02:
            assert r["rank"] <= 0.5


def test_long_form_asks_the_overflow_store(spark):
    df = spark.range(3000).select(F.col("id").alias("k"))
    for combine, equal in (("flag", False), ("compensate", True)):
        st = S.build(df, ["k"], F.col("k") % 8, S.Plan(width=3, block=64, headroom=0.05, tries=1, combine=combine, equal_segments=equal))
        assert st.overflow.n_keys > 0
        got = S.lookup_long(df, st, "k")
        assert got.count() == 3000 and got.filter(F.col("value") != F.col("k") % 8).count() == 0
        bits = S.logical_bits(st).first()
        assert bits["n"] == 3000 and bits["slot_bits"] >= 9000 and S.stored_bits(st) >= 9000


def test_two_and_three_keys_are_no_overflow(spark):
    for n in (1, 2, 3, 5):
        df = spark.range(n).select(F.col("id").alias("k"))
        st = S.build(df, ["k"], F.col("k") % 2, S.Plan(width=1))
        assert st.overflow is None and S.verify(st, df, F.col("k") % 2).first()["errors"] == 0


def test_batch_solver_is_the_row_solver():
    for n, m, seed in ((1, 3, 1), (40, 44, 2), (130, 140, 3), (64, 64, 4)):
        systems = [A.random_rows(n, m, 3 if m > 3 else 2, seed * 100 + i) for i in range(9)]
        values = [[(i * 37 + j * 11) % 251 for j in range(n)] for i in range(9)]
        block, row, cell = (np.array(x) for x in zip(*[(b, r, c) for b, s in enumerate(systems) for r, cells in enumerate(s) for c in cells]))
        slots, pivots = A.solve_batch(A.bit_rows(block, row, cell, np.array(values, np.uint64), (9, n, m)), m)
        for b, s in enumerate(systems):
            want = A.solve2(s, values[b], m, 8)
            assert (pivots[b].sum() == n) == (want is not None)
            if want:
                assert (slots[b].tolist(), np.flatnonzero(pivots[b]).tolist()) == want


def test_split_and_share(spark):
    df = spark.range(700).select(F.col("id").alias("k"))
    st = sharing.build(df, ["k"], F.col("k") % 32, sharing.Plan(width=5))
    assert st.largest <= math.isqrt(700) and st.chunks >= 2 * 700 ** (2 / 3)
    for shared in (True, False):
        assert sharing.lookup(df, st, shared=shared).filter(F.col("value") != F.col("k") % 32).count() == 0
    assert sharing.lookup(spark.createDataFrame([(None,), (5000,)], "k long"), st).filter("k is null and value is null or k = 5000 and value between 0 and 31").count() == 2
    assert not sharing.acyclic([1, 1, 2, 2], [1, 2, 1, 2]) and sharing.acyclic([1, 1, 2], [1, 2, 1])


def test_addresses_agree(spark):
    d = H.digests(spark.range(200).select(F.col("id").alias("k")), ["k"])
    a = sharing.addresses(F.lit(3), 101)
    got = d.select("d1", "d2", a[0].alias("a"), a[1].alias("b")).collect()
    x, y = sharing.np_addresses(np.array([r["d1"] for r in got]), np.array([r["d2"] for r in got]), 3, 101)
    assert x.tolist() == [r["a"] for r in got] and y.tolist() == [r["b"] for r in got]
