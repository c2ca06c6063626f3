"""Hand-sized systems, twins of hashes, bounds and plans."""

import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import linalg as A
from keyless import membership as M
from keyless import store as S
from keyless import streaming
from keyless import thresholds as T

CORE = [[0, 1, 2], [0, 1, 3], [0, 2, 3], [1, 2, 3]]


def test_core_is_regular_but_does_not_peel():
    assert A.peel_order(CORE, 4) is None
    assert A.solve2(CORE, [5, 3, 6, 1], 4, 3)[0] == [0, 7, 2, 4]


def test_dependent_systems_are_refused():
    assert A.solve2([[0, 1, 2], [0, 3, 4], [1, 3, 5], [2, 4, 5]], [1, 2, 4, 0], 6, 3) is None
    assert A.rank2([[0, 1], [1, 2], [0, 2]]) == 2


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 40), st.integers(0, 10**6), st.permutations(range(6)))
def test_solutions_do_not_depend_on_row_order(n, seed, _):
    rows = A.random_rows(n, int(1.3 * n) + 4, 4, seed)
    values = [(seed * (i + 1)) % 256 for i in range(n)]
    got = A.solve2(rows, values, int(1.3 * n) + 4, 8)
    if got:
        for r, v in zip(rows, values):
            x = 0
            for c in r:
                x ^= got[0][c]
            assert x == v
        order = sorted(range(n), key=lambda i: (i * 7919) % 101)
        assert A.solve2([rows[i] for i in order], [values[i] for i in order], int(1.3 * n) + 4, 8) == got


def test_field_and_peel_solutions():
    rows = [{0: 3, 2: 5}, {1: 7, 2: 1}, {0: 1, 1: 1, 3: 9}]
    got = A.solve_field(rows, [10, 20, 30], 4, 101)[0]
    assert [sum(g * got[c] for c, g in r.items()) % 101 for r in rows] == [10, 20, 30]
    assert A.peel_solve([[0, 1], [1, 2]], [3, 5], 3, "add", 16) is not None


def test_matching_uses_augmenting_paths():
    assert sorted(A.match([[0, 1], [0], [1, 2]])) == [0, 1, 2]
    assert A.match([[0], [0]]) is None


def test_slots_are_uniform_ordered_draws():
    seen = set()
    for raw in itertools.product(range(5), range(4), range(3)):
        cells = list(raw)
        for i in range(1, 3):
            for t in sorted(cells[:i]):
                cells[i] += cells[i] >= t
        assert len(set(cells)) == 3
        seen.add(tuple(cells))
    assert len(seen) == 60


def test_numpy_and_expression_slots_agree(spark):
    df = H.digests(spark.range(-50, 50).select(F.col("id").alias("k")), ["k"])
    rows = H.slot_columns(df, 4, 37, 9).collect()
    d1, d2 = (np.array([r[c] for r in rows], np.int64) for c in ("d1", "d2"))
    assert H.np_slots(d1, d2, 4, 37, 9).tolist() == [[r[f"s{i}"] for i in range(4)] for r in rows]
    assert all(len(set(x)) == 4 for x in H.np_slots(d1, d2, 4, 37, 9, how="swap").tolist())


def test_thresholds():
    for k, want in {3: 0.88949, 4: 0.96714, 5: 0.98916, 6: 0.99622}.items():
        assert abs(T.theta(k) - want) < 2e-5
    assert T.bits_for(0.01) == 7 and T.filter_lower_bound(1000, 1 / 16) == 4000
    assert T.plan_for(0.1, 8).k >= 4


def test_edge_keys(spark):
    rows = [(2**63 - 1, 1), (-(2**63), 2), (0, 3), (None, 4), (5, None), (7, 7), (7, 7)]
    df = spark.createDataFrame(rows, "k long, v long")
    got = {r["k"]: r["value"] for r in S.lookup(df, S.build(df, ["k"], F.col("v"), S.Plan(width=63))).collect()}
    assert got[2**63 - 1] == 1 and got[-(2**63)] == 2 and got[0] == 3 and got[7] == 7 and got[None] is None
    with pytest.raises(Exception, match="conflict"):
        S.build(spark.createDataFrame([(1, 1), (1, 2)], "k long, v long"), ["k"], F.col("v"), S.Plan(width=2))


def test_one_bit_and_unicode_keys(spark):
    df = spark.createDataFrame([(f"é中{i}", i % 2) for i in range(300)], "k string, v int")
    for plan in (S.Plan(width=1), S.Plan(width=1, kind="square", tries=64, block=64), S.Plan(width=1, compressed=True)):
        assert tuple(S.verify(S.build(df, ["k"], F.col("v"), plan), df, F.col("v")).first()) == (300, 0)


def test_overflow_takes_what_blocks_refuse(spark):
    df = spark.range(3000).select(F.col("id").alias("k"))
    for combine in ("flag", "compensate"):
        st = S.build(df, ["k"], F.col("k") % 8, S.Plan(width=3, block=64, headroom=0.05, tries=1, combine=combine))
        assert st.overflow.n_keys > 0
        assert S.verify(st, df, F.col("k") % 8).first()["errors"] == 0


def test_lookup_plans(spark):
    df = spark.range(2000).select(F.col("id").alias("k"))
    st = S.build(df, ["k"], F.col("k") % 8, S.Plan(width=3, tries=40))
    text = lambda mode: S.lookup(df, st, mode=mode)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in text("broadcast") and "PythonUDF" not in text("broadcast")
    with_shuffle = text("bucketed")
    assert "ArrowEvalPython" not in with_shuffle


def test_filters_of_other_columns_reach_the_scan(spark, sf):
    orders = spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_custkey", "o_orderstatus")
    st = S.build(orders, ["o_orderkey"], F.length("o_orderstatus"), S.Plan(width=3, block=64, headroom=0.05, tries=1))
    assert st.overflow is not None
    found = S.lookup(orders, st, out="v")
    plan = found.filter("o_custkey = 3 and v = 1")._jdf.queryExecution().executedPlan().toString()
    scans = [x for x in plan.splitlines() if "FileScan parquet" in x]
    assert any("EqualTo(o_custkey,3)" in x for x in scans), plan
    draws = lambda p: p.count("xxhash64")
    assert draws(plan) <= draws(found._jdf.queryExecution().executedPlan().toString())
    assert found.filter("o_custkey = 3 and v = 1").count() == orders.filter("o_custkey = 3").count()


def test_empty_filter_accepts_nothing(spark):
    none = spark.createDataFrame([], "k long")
    assert M.maybe(spark.range(5).select(F.col("id").alias("k")), M.build_filter(none, ["k"], 4)).filter("maybe").count() == 0


def test_stream_probes_a_static_store(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    st = S.build(events, ["event_id"], F.length("event_type"), S.Plan(width=5))
    events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("event_id long, ts timestamp, event_type string").parquet(str(tmp_path / "in"))
    run = streaming.probe(stream, st).writeStream.format("memory").queryName("probed").trigger(availableNow=True).start()
    run.awaitTermination()
    assert spark.table("probed").filter("value != length(event_type)").count() == 0 and spark.table("probed").count() == events.count()
    windows = streaming.tumbling(stream, "ts", "1 day", "1 day").writeStream.format("memory").queryName("days").outputMode("complete").trigger(availableNow=True).start()
    windows.awaitTermination()
    assert spark.table("days").agg(F.sum("n")).first()[0] == events.count()


def test_overlay_wins(spark):
    a = spark.createDataFrame([(1, 5), (2, 6)], "k long, value long")
    b = spark.createDataFrame([(2, 9)], "k long, value long")
    assert sorted(tuple(r) for r in streaming.overlay(a, b, "k").collect()) == [(1, 5), (2, 9)]


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())
