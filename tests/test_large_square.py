"""One large square system by products with its sparse rows."""

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import krylov as K
from keyless import linalg as A
from keyless import store as S


def drawn(n, seed, width):
    rng = np.random.default_rng(seed)
    plan = S.Plan(width=width, kind="square", block=n, tries=64)
    d1, d2 = (rng.integers(-(2**63), 2**63 - 1, n) for _ in range(2))
    return (*S.entries(plan, d1, d2, np.full(n, n), np.full(n, n), 1000 + seed), rng.integers(0, 1 << width, n))


def holds(key, cell, values, slots):
    got = np.zeros(len(values), np.int64)
    np.bitwise_xor.at(got, key, np.array(slots)[cell])
    assert (got == values).all()


def regular(key, cell, n):
    rows = [[] for _ in range(n)]
    for i, c in zip(key.tolist(), cell.tolist()):
        rows[i].append(c)
    return A.solve_lazy(rows, [0] * n, n, 1) is not None


@pytest.mark.parametrize("n,width", [(2100, 2), (2100, 6), (3001, 20)])
def test_regular_systems_are_solved_and_what_is_found_holds(n, width):
    found = 0
    for seed in range(6):
        key, cell, values = drawn(n, seed, width)
        slots = K.solve(key, cell, values, width, seed)
        # dependent rows may still agree with their values
        assert slots is not None or not regular(key, cell, n)
        if slots:
            holds(key, cell, values, slots)
            found += 1
    assert found


def test_values_that_are_all_alike():
    key, cell = next((k, c) for k, c, _ in (drawn(2100, s, 2) for s in range(20)) if regular(k, c, 2100))
    for values in (np.zeros(2100, np.int64), np.full(2100, 3), np.arange(2100) % 2):
        slots = K.solve(key, cell, values, 2, 1)
        assert slots is not None
        holds(key, cell, values, slots)


def test_large_square_system_is_solved_in_time():
    key, cell, values = drawn(40_000, 7, 2)
    began = time.monotonic()
    slots = K.solve(key, cell, values, 2, 1)
    assert time.monotonic() - began < 40
    if slots:
        holds(key, cell, values, slots)


def test_square_store_of_one_system(spark):
    df = spark.range(3000).select("id", F.pmod(F.xxhash64("id"), F.lit(4)).alias("v"))
    for compressed in (False, True):
        st = S.build(df, ["id"], F.col("v"), S.Plan(width=2, kind="square", block=3000, tries=64, compressed=compressed), blocks=1)
        row = st.segments.collect()[0]
        assert (row.status, row.n_slots, st.overflow) == (S.GOOD, 3000, None)
        assert S.verify(st, df, F.col("v")).first() == (3000, 0)
    # the first draw that has a solution, whatever was tried beside it
    rows = H.digests(df, ["id"]).sort("d1", "d2").collect()
    d1, d2, v = (np.array([r[c] for r in rows]) for c in ("d1", "d2", "v"))
    plan = S.Plan(width=2, kind="square", block=3000)
    first = next(t for t in range(64) if K.solve(*S.entries(plan, d1, d2, np.full(3000, 3000), np.full(3000, 3000), 1000 + t), v, 2, t) is not None)
    assert row.seed == first


def test_without_a_solution_the_keys_go_to_the_overflow_store(spark):
    plan = S.Plan(width=2, kind="square", block=2100, tries=3)
    df = spark.range(2100).select("id", (F.col("id") % 4).alias("v"))
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(S, "_try_square", lambda plan, batches: iter(()))
        st = S.build(df, ["id"], F.col("v"), plan, blocks=1)
    assert st.overflow is not None and S.verify(st, df, F.col("v")).first() == (2100, 0)
