"""Thresholds, bounds and cost formulas of the methods; the tables are Spark expressions over a grid."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Slots for each key that peeling needs, by fanout; decay exponents of the failure chance, by fanout.
PEEL_RATIO = {3: 1.222, 4: 1.295}
FAILURE_EXPONENT = {3: 2 / 7, 4: 5 / 7}
SQUARE_SUCCESS = 0.28879
GRID = 20_000
#: Beyond this the load only grows, and the logarithm of one plus almost nothing loses its digits.
TOP = 18_000


def load_at(a: Column, k: Column) -> Column:
    """The load at which dependent sets of relative size a start to appear for rows of weight k.

    The exponent of their expected number is -ln 2 + entropy(a) + load * ln(1 + (1 - 2a)^k), linear in the load."""
    entropy = -(a * F.ln(a)) - (1 - a) * F.ln(1 - a)
    return (F.ln(F.lit(2.0)) - entropy) / F.ln(1 + F.pow(1 - 2 * a, k))


#: Points of the grid that an order stands for, and the orders that make it whole.
POINTS, RESIDUES = 12, 1500


def threshold_table(orders: DataFrame, ks: tuple[int, ...] = (3, 4, 5, 6)) -> DataFrame:
    """theta by the grid minimum, its two-term series, and the slots for each key, for each k.  An order stands for the sets of some relative
    sizes, by the remainder of its key."""
    spark = orders.sparkSession
    sets = orders.select(F.pmod("o_orderkey", F.lit(RESIDUES)).alias("b")).distinct().select(F.explode(F.sequence(F.col("b") * POINTS + 1, (F.col("b") + 1) * POINTS)).alias("id")).filter(F.col("id") < TOP)
    grid = sets.select((F.col("id") / (2.0 * GRID)).alias("a")).crossJoin(F.broadcast(spark.createDataFrame([(k,) for k in ks], "k int")))  # one row for each k
    theta = grid.groupBy("k").agg(F.min(load_at(F.col("a"), F.col("k"))).alias("t"))
    k = F.col("k")
    series = 1 - F.exp(-k) / F.ln(F.lit(2.0)) - (F.pow(k, 2) - 2 * k + 2 * k / F.ln(F.lit(2.0)) - 1) / (2 * F.ln(F.lit(2.0))) * F.exp(-2 * k)
    return theta.select("k", F.round("t", 5).alias("theta"), F.round(series, 5).alias("series"), F.round(1 / F.col("t"), 4).alias("slots_per_key"))


THRESHOLD_SQL = f"""
WITH g AS (SELECT i / (2.0 * {GRID})::DOUBLE AS a, k FROM (SELECT b * {POINTS} + j AS i FROM (SELECT DISTINCT o_orderkey % {RESIDUES} AS b FROM orders), range(1, {POINTS} + 1) r(j)) s, (VALUES (3), (4), (5), (6)) v(k) WHERE i < {TOP}),
t AS (SELECT k, min((ln(2.0::DOUBLE) + a * ln(a) + (1 - a) * ln(1 - a)) / ln(1 + pow(1 - 2 * a, k))) AS t FROM g GROUP BY k)
SELECT k::INTEGER AS k, round(t, 5) AS theta,
  round(1 - exp(-k) / ln(2.0::DOUBLE) - (k * k - 2 * k + 2 * k / ln(2.0::DOUBLE) - 1) / (2 * ln(2.0::DOUBLE)) * exp(-2 * k), 5) AS series, round(1 / t, 4) AS slots_per_key FROM t"""


def theta(k: int) -> float:
    grid = (i / (2.0 * GRID) for i in range(1, TOP))
    return min((math.log(2) + a * math.log(a) + (1 - a) * math.log(1 - a)) / math.log(1 + (1 - 2 * a) ** k) for a in grid)


def min_slack(k: int) -> float:
    return 1 / theta(k) - 1


def failure_exponent(k: int) -> float:
    return FAILURE_EXPONENT.get(k, 1.0)


def asymptotic_block(n: int) -> int:
    return max(1, round(0.5 * math.sqrt(math.log2(max(n, 2)))))


def chunk_plan(n: int) -> tuple[int, int]:
    """(chunks, largest chunk allowed)."""
    return math.ceil(2 * n ** (2 / 3)), math.isqrt(n)


def plan_for(gamma: float, width: int):
    """The least fanout whose slack takes at most half of the relative excess."""
    from keyless.store import Plan

    for k in range(3, 12):
        if min_slack(k) <= gamma / 2:
            return Plan(width=width, k=k, slack=gamma / 2, block=1024 if gamma < 0.05 else 256)
    return Plan(width=width, k=12, slack=gamma, block=2048)


def filter_lower_bound(n: int, eps: float, u: float = math.inf) -> float:
    """Bits that any filter needs: an accepted set of n + eps (u - n) keys covers few of the sets of n keys."""
    if math.isinf(u):
        return n * math.log2(1 / eps)
    choose = lambda a, b: math.lgamma(a + 1) - math.lgamma(b + 1) - math.lgamma(a - b + 1)
    return max(0.0, (choose(u, n) - choose(n + eps * (u - n), n)) / math.log(2))


def retrieval_lower_bound(n: int, r: int) -> int:
    return n * r


def bits_for(eps: float) -> int:
    return max(0, math.ceil(-math.log2(eps)))


def square_success(orders: DataFrame) -> DataFrame:
    """Chance that a random square system over two elements with a row for each order is regular: the product of 1 - 2^-i, i being the
    order's key from 1 on."""
    i = F.col("o_orderkey") + 1
    return orders.agg(F.round(F.exp(F.sum(F.ln(1 - F.pow(F.lit(2.0), -i)))), 5).alias("success"))


SQUARE_SQL = "SELECT round(exp(sum(ln(1 - pow(2.0::DOUBLE, -(o_orderkey + 1))))), 5) AS success FROM orders"


def _widths(orders: DataFrame) -> DataFrame:
    """(id, n): widths of 1 to 16 bits, and the number of keys."""
    return orders.sparkSession.range(1, 17).crossJoin(F.broadcast(orders.agg(F.count_distinct("o_orderkey").alias("n"))))  # one row


def _bits(x: Column, name: str) -> Column:
    return F.ceil(x).cast("bigint").alias(name)


def filter_space(orders: DataFrame) -> DataFrame:
    """Bits of a filter on the orders by signature bits: Bloom, minimal perfect hash with signatures, retrieval at slack .06, bound."""
    s, n = F.col("id").cast("double"), F.col("n")
    return _widths(orders).select(F.col("id").cast("int").alias("s"), "n", _bits(n * (s / F.ln(F.lit(2.0))), "bloom"), _bits(n * (s + 1 / F.ln(F.lit(2.0))), "mph_signature"), _bits(n * (1.06 * s), "retrieval"), _bits(n * s, "bound"))


def _widths_sql(name: str, **formulas: str) -> str:
    return f"SELECT i::INTEGER AS {name}, n::BIGINT AS n, " + ", ".join(f"ceil(n * ({x}))::BIGINT AS {c}" for c, x in formulas.items()) + " FROM range(1, 17) t(i), (SELECT count(DISTINCT o_orderkey) AS n FROM orders)"


FILTER_SPACE_SQL = _widths_sql("s", bloom="i / ln(2.0::DOUBLE)", mph_signature="i + 1 / ln(2.0::DOUBLE)", retrieval="1.06::DOUBLE * i", bound="i::DOUBLE")


def retrieval_space(orders: DataFrame) -> DataFrame:
    """Bits of a store on the orders by width: peeling, perfect hash with an array (best and ours), sparse rows with fanout 3 and 4."""
    r, n = F.col("id").cast("double"), F.col("n")
    return _widths(orders).select(F.col("id").cast("int").alias("r"), "n", _bits(n * (1.23 * r), "peel"), _bits(n * (r + 1 / F.ln(F.lit(2.0))), "mph_best"), _bits(n * (r + 2.29), "mph_own"), _bits(n * (1.1243 * r), "sparse_3"), _bits(n * (1.034 * r), "sparse_4"))


RETRIEVAL_SPACE_SQL = _widths_sql("r", peel="1.23::DOUBLE * i", mph_best="i + 1 / ln(2.0::DOUBLE)", mph_own="i + 2.29::DOUBLE", sparse_3="1.1243::DOUBLE * i", sparse_4="1.034::DOUBLE * i")
