"""Blocks solved by tables, rings of cells, weights outside the clip, and the work of the elimination."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from keyless import linalg as A
from keyless import small, variants  # noqa: F401
from keyless import store as S
from keyless import workloads as W


def test_the_table_of_matrices_is_the_solver():
    masks, independent = small.inverses(2, 4)
    for number in range(1 << 8):
        rows = [[c for c in range(4) if number >> (4 * r + c) & 1] for r in range(2)]
        want = A.solve2(rows, [5, 9], 4, 4)
        assert independent[number] == (want is not None)
        if want:
            assert [(5 if m & 1 else 0) ^ (9 if m & 2 else 0) for m in masks[number].tolist()] == want[0]


def test_the_table_of_sums():
    table = small.sums(3)
    for mask, (a, b, c) in itertools.product(range(8), [(1, 2, 4), (15, 9, 3), (0, 7, 7)]):
        assert table[mask, a, b, c] == (a if mask & 1 else 0) ^ (b if mask & 2 else 0) ^ (c if mask & 4 else 0)
    with pytest.raises(ValueError):
        small.inverses(4, 8)


@pytest.mark.parametrize("n", [1, 2, 3, 7, 500])
@pytest.mark.parametrize("plan", [variants.TABLES, S.Plan(kind="field", sets="ring", run=12, block=64, slack=0.0, prime=257, tries=32), S.Plan(kind="square", block=64, tries=64, weights="whole")], ids=["table", "ring", "whole"])
def test_every_key_gives_its_value(spark, n, plan):
    df = spark.range(n).select(F.col("id").alias("k"))
    st = S.build(df, ["k"], F.col("k") % 200, plan)
    assert S.verify(st, df, F.col("k") % 200).first().asDict() == {"n": n, "errors": 0}
    # strangers and null keys do not fail
    assert S.lookup(spark.createDataFrame([(None,), (10**6,)], "k long"), st).count() == 2


def test_share_of_small_blocks(spark, sf):
    got = {r["reason"]: r["share"] for r in W.QUERIES["overflow_small_tables"](spark, sf).collect()}
    # a key is in a block above three where three others or more are with it, by a mean of two
    alone = 1 - sum(math.exp(-2) * 2**i / math.factorial(i) for i in range(3))
    assert got["oversize"] == pytest.approx(alone, abs=0.06) and 0 < got["dependent"] < 0.25 and sum(got.values()) == pytest.approx(1)


def test_work_follows_the_keys_and_the_block(spark, sf):
    rows = {(r["source"], r["block"]): r for r in W.QUERIES["build_scaling"](spark, sf).collect()}
    each = {k: r["row_sums"] / r["keys"] for k, r in rows.items()}
    # one block size: the same work a key in a table of 1,500 keys as in one of 200
    assert each["orders", 64] == pytest.approx(each["part", 64], rel=0.35)
    # larger blocks: the work a key grows, and not faster than the block
    slope = np.polyfit(np.log([32, 64, 128, 256]), np.log([each["orders", b] for b in (32, 64, 128, 256)]), 1)[0]
    assert 0.4 < slope <= 1.05
