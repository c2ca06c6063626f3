"""Baselines: Bloom filter, perfect hash with arrays, peeling, gap codes, plain joins."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyless import hashing as H

#: Fixed coefficients of the polynomial hashes, so that other engines can compute them.
COEFFICIENTS = [[1_103_515_245, 12_345], [69_069, 362_437], [1_664_525, 1_013_904_223], [22_695_477, 7], [214_013, 2_531_011], [134_775_813, 11], [16_807, 3], [48_271, 5]]


def bloom_bits(n: int, eps: float) -> tuple[int, int]:
    """(bits, hashes)."""
    return max(64, math.ceil(n * math.log2(1 / eps) / math.log(2))), max(1, round(math.log2(1 / eps)))


def bloom_build(df: DataFrame, key: str, bits: int, hashes: int) -> DataFrame:
    """(word, mask): the set bits, sixty to a word, by an aggregate with map-side combination."""
    cells = df.select(F.explode(F.array(*[H.poly_hash(F.col(key), c, bits) for c in COEFFICIENTS[:hashes]])).alias("bit"))
    return cells.groupBy(F.floor(F.col("bit") / 60).alias("word")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("bit") % 60).cast("int"))).alias("mask"))


#: Bits of a filter that goes to every task as one array of eight megabytes; a larger one is joined by word.
BROADCAST_BITS = 1 << 26


def bloom_maybe(df: DataFrame, key: str, bloom: DataFrame, bits: int, hashes: int, out: str = "maybe", by_word: bool | None = None) -> DataFrame:
    """``df`` with a boolean: whether all bits of the key are set.  The filter goes to the rows as one array, or, where it is large, the
    bits of the distinct keys go to its words."""
    if bits > BROADCAST_BITS if by_word is None else by_word:
        probe = df.select(F.col(key).alias("__key")).distinct().select("__key", F.explode(F.array(*[H.poly_hash(F.col("__key"), c, bits) for c in COEFFICIENTS[:hashes]])).alias("bit"))
        met = probe.withColumn("word", F.floor(F.col("bit") / 60)).join(bloom, "word", "left")
        is_set = F.call_function("shiftright", F.coalesce("mask", F.lit(0).cast("bigint")), (F.col("bit") % 60).cast("int")).bitwiseAND(F.lit(1)) == 1
        return df.join(met.groupBy("__key").agg(F.bool_and(is_set).alias(out)), F.col(key) == F.col("__key"), "left").drop("__key")
    words = -(-bits // 60)
    # every word has a row, so the words in order are the array
    filled = df.sparkSession.range(words).select(F.col("id").alias("word")).join(bloom, "word", "left").select("word", F.coalesce("mask", F.lit(0).cast("bigint")).alias("mask"))
    arr = filled.agg(F.transform(F.array_sort(F.collect_list(F.struct("word", "mask"))), lambda x: x["mask"]).alias("a"))
    hit: Column = F.lit(True)
    for c in COEFFICIENTS[:hashes]:
        bit = H.poly_hash(F.col(key), c, bits)
        hit = hit & F.coalesce(F.call_function("shiftright", F.try_element_at("a", F.floor(bit / 60).cast("int") + 1), (bit % 60).cast("int")).bitwiseAND(F.lit(1)) == 1, F.lit(False))
    return df.join(F.broadcast(arr)).withColumn(out, hit).drop("a")  # one row


def gap_bits(df: DataFrame, key: str, space: int) -> DataFrame:
    """Cost of sending the sorted hashes as gaps with a Golomb-Rice code: (n, bits)."""
    from pyspark.sql import Window

    parts = 64
    h = df.select(H.poly_hash(F.col(key), COEFFICIENTS[0], space).alias("h")).distinct().withColumn("range", F.floor(F.col("h") * parts / space))
    gap = h.withColumn("gap", F.col("h") - F.coalesce(F.lag("h").over(Window.partitionBy("range").orderBy("h")), F.floor(F.col("range") * space / parts)))
    return gap.agg(F.count("*").cast("bigint").alias("n"), F.sum(F.floor(F.col("gap") / 64) + 7).cast("bigint").alias("bits"))


def cost(what: str, n: int, r: float = 0) -> float:
    """Bits by formula."""
    return {"peel": 1.23 * n * r, "peel_adhoc": 3 * n * r, "mph_optimal": n * math.log2(math.e), "mph_peel": 2.7 * n, "perfect": 2.07 * n, "minimal": 2.29 * n, "mph_map": n * r + n * math.log2(math.e), "bloom": n * r / math.log(2)}[what]
