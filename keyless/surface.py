"""The stores from SQL text: views, and functions of a user's session for slots, segments and cells."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from keyless import baselines, codecs, hashing as H, linalg as A, store as S
from keyless.workloads import check, check_sql, query, read


def register(spark: SparkSession) -> None:
    """``keyless_slots(d1, d2, seed, k, m)``, ``keyless_rank(cells, m)`` over the rows of a group, and ``keyless_cells(words, width)``."""
    spark.udf.register("keyless_slots", slots_udf())
    spark.udf.register("keyless_rank", rank_udf())
    spark.udtf.register("keyless_cells", cells_udtf())


def slots_udf():
    @F.pandas_udf("array<bigint>")
    def keyless_slots(d1: pd.Series, d2: pd.Series, seed: pd.Series, k: pd.Series, m: pd.Series) -> pd.Series:
        out = pd.Series([None] * len(d1), dtype=object)
        for (s, kk, mm), at in pd.DataFrame({"s": seed, "k": k, "m": m}).groupby(["s", "k", "m"]).groups.items():
            got = H.np_slots(d1[at].to_numpy(np.int64), d2[at].to_numpy(np.int64), int(kk), int(mm), int(s))
            for i, row in zip(at, got):
                out[i] = row
        return out

    return keyless_slots


def rank_udf():
    @F.pandas_udf("bigint")
    def keyless_rank(cells: pd.Series, m: pd.Series) -> int:
        return A.rank2([list(map(int, c)) for c in cells])

    return keyless_rank


def cells_udtf():
    @F.udtf(returnType="slot: bigint, val: bigint")
    class KeylessCells:
        def eval(self, words, width: int):
            q, mask = 64 // width, (1 << width) - 1
            for i, w in enumerate(words or []):
                for j in range(q):
                    yield i * q + j, (w % (1 << 64)) >> j * width & mask

    return KeylessCells


@query(check_sql("udf_slots", "SELECT count(*) FROM orders"))
def udf_slots(spark, sf_dir):
    """The function of the session and the expression give the same slots."""
    register(spark)
    df = H.slot_columns(H.digests(read(spark, sf_dir, "orders", "o_orderkey"), ["o_orderkey"]), 4, 977, 5)
    got = df.withColumn("u", F.call_function("keyless_slots", "d1", "d2", F.lit(5), F.lit(4), F.lit(977)))
    return check(got, "udf_slots", F.count("*"), F.count_if(F.col("u") != F.array(*[F.col(f"s{i}") for i in range(4)])))


@query(check_sql("udaf_rank", "SELECT count(*) FROM part"))
def udaf_segment(spark, sf_dir):
    """Blocks that were built have rows of full rank by the aggregate of the session too."""
    register(spark)
    df = read(spark, sf_dir, "part", "p_partkey")
    st = S.build(df, ["p_partkey"], F.lit(0), S.Plan(width=1, block=64, tries=16))
    rows = H.digests(df, ["p_partkey"]).withColumn("block", H.draw(H.BLOCK, st.plan.seed, 0, st.blocks)).join(st.segments.filter(F.col("status") == S.GOOD).select("block", "n_slots", "seed", "n_keys"), "block")
    rows = H.slot_columns(rows, st.plan.k, F.col("n_slots"), F.lit(st.plan.seed * 1000) + F.col("seed"))
    got = rows.withColumn("cells", F.array(*[F.col(f"s{i}") for i in range(st.plan.k)])).groupBy("block", "n_keys").agg(F.call_function("keyless_rank", "cells", "n_slots").alias("rank"))
    over = st.segments.filter(F.col("status") != S.GOOD).select("block", "n_keys", F.col("n_keys").cast("bigint").alias("rank"))
    return check(got.unionAll(over), "udaf_rank", F.sum("n_keys"), F.count_if(F.col("rank") != F.col("n_keys")))


@query(check_sql("udtf_cells", "SELECT count(*) FROM part"))
def udtf_cells(spark, sf_dir):
    """The cells of the segments by the table function are those of the long form."""
    register(spark)
    st = S.build(read(spark, sf_dir, "part", "p_partkey"), ["p_partkey"], F.col("p_partkey") % 32, S.Plan(width=5))
    st.segments.createOrReplaceTempView("keyless_segments")
    ours = spark.sql("SELECT block, slot, val FROM keyless_segments, LATERAL keyless_cells(words, 5) WHERE slot < n_slots")
    apart = ours.exceptAll(S.long_form(st)).unionAll(S.long_form(st).exceptAll(ours)).agg(F.count("*").alias("apart"))
    return check(st.segments.agg(F.sum("n_keys").alias("n")).join(F.broadcast(apart)), "udtf_cells", F.max("n"), F.max("apart"))  # one row each


@query("SELECT o_orderpriority AS priority, count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def sql_lookup(spark, sf_dir):
    """A lookup as a view that SQL text reads."""
    orders = read(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority")
    c = codecs.dictionary(orders, "o_orderpriority")
    st = S.build(orders, ["o_orderkey"], c.encode(F.col("o_orderpriority")), S.Plan(width=c.width))
    st.decode = c.decode
    S.lookup(read(spark, sf_dir, "lineitem", "l_orderkey"), st, ["l_orderkey"], "priority").createOrReplaceTempView("keyless_items")
    return spark.sql("SELECT priority, count(*) AS n FROM keyless_items GROUP BY priority")


_B = baselines.COEFFICIENTS[3]


@query(f"WITH h AS (SELECT o_orderkey, (({_B[0]}::BIGINT * (o_orderkey % {H.PRIME}) + {_B[1]}) % {H.PRIME}) AS p FROM orders), r AS (SELECT o_orderkey, p % 64 AS region, floor(p / 64)::BIGINT % (SELECT ceil(count(*) / 48.0)::BIGINT FROM orders) AS home FROM h), i AS (SELECT *, row_number() OVER (PARTITION BY region ORDER BY home, o_orderkey) AS i FROM r), c AS (SELECT region, home, max(home - i) OVER (PARTITION BY region ORDER BY home, o_orderkey ROWS UNBOUNDED PRECEDING) + i AS cell FROM i) SELECT region, max(cell - home)::BIGINT AS longest_shift, count(DISTINCT cell)::BIGINT AS cells_used FROM c GROUP BY region")
def probe_longest_shift(spark, sf_dir):
    """Linear probing in 64 regions placed apart: how far a key ends up from its home, and that no cell is used twice."""
    from keyless import allocation

    df = read(spark, sf_dir, "orders", "o_orderkey")
    p = H.poly_hash(F.col("o_orderkey"), _B, H.PRIME)
    homes = df.withColumns({"region": F.pmod(p, F.lit(64)), "home": F.pmod(F.floor(p / 64), F.lit(max(1, -(-df.count() // 48))))})
    return allocation.longest_run(homes, "region", "home", "o_orderkey")
