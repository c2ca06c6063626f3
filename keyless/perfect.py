"""Perfect hashing: every key gets one of its own slots for itself, and a store remembers which of its k choices it is."""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import linalg as A
from keyless import store as S


def _pass(plan: S.Plan, peel: bool, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    out = []
    for block, (d1, d2, _) in S.per_block(batches, ["d1", "d2", "value"]):
        m = max(plan.k, math.ceil((1 + plan.slack) * len(d1)))
        done = None
        # more slots are added where many tries fail, so that every block gets its hash
        for t in range(200):
            if t and t % 25 == 0:
                m = math.ceil(1.05 * m) + 1
            rows = H.np_slots(d1, d2, plan.k, m, plan.seed * 1000 + t).tolist()
            if peel:
                order = A.peel_order(rows, m)
                mine = None if order is None else [c for _, c in sorted(order)]
            else:
                mine = A.match(rows)
            if mine is None:
                continue
            codes = [r.index(c) for r, c in zip(rows, mine)]
            slots = A.peel_solve(rows, codes, m) if peel else (A.solve2(rows, codes, m, plan.width) or [None])[0]
            if slots is not None:
                done = (t, slots, mine)
                break
        if done is None:
            raise S.BuildError(f"block {block} with {len(d1)} keys has no perfect hash")
        # the few slots that no key has, in order; a slot's rank is the slot less those of them before it
        before = sorted(set(range(m)) - set(done[2]))
        out.append({"block": block, "n_keys": len(d1), "n_slots": m, "seed": done[0], "status": S.GOOD, "words": S.pack(done[1], plan.width), "used": [], "before": before, "first": 0})
        if len(out) == 512:
            yield S._segment_batch(out)
            out = []
    if out:
        yield S._segment_batch(out)


def offsets(segments: DataFrame, size: str) -> DataFrame:
    """Segments with ``first``: the prefix sum of ``size`` by block, in two levels so that no task holds all blocks."""
    group = F.floor(F.col("block") / 4096).alias("group")
    sums = segments.groupBy(group).agg(F.sum(size).alias("n"))
    starts = sums.select("group", F.coalesce(F.sum("n").over(Window.orderBy("group").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inner = Window.partitionBy("group").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    return segments.drop("first").withColumn("group", F.floor(F.col("block") / 4096)).join(F.broadcast(starts), "group").withColumn("first", F.col("base") + F.coalesce(F.sum(size).over(inner), F.lit(0))).drop("group", "base")


def build_perfect(df: DataFrame, keys: list[str], k: int = 4, slack: float = 0.06, block: int = 256, minimal: bool = False, peel: bool = False, seed: int = 11) -> S.Store:
    plan = S.Plan(width=max(1, math.ceil(math.log2(k))), k=k, slack=slack, block=block, seed=seed)
    rows = S.normalise(df.select(*keys), keys, None, "min").persist()
    n = rows.count()
    blocks = max(1, math.ceil(n / block))
    segments = S.clustered(rows, blocks, master=seed).mapInArrow(functools.partial(_pass, plan, peel), S.SEGMENTS).persist()
    out = S.Store(plan, keys, offsets(segments, "n_keys" if minimal else "n_slots").persist(), blocks, n)
    out.minimal = minimal
    return out


def phash(df: DataFrame, ph: S.Store, keys: list[str] | None = None, out: str = "h") -> DataFrame:
    """``df`` with the number of each key; a key that was not built in gets some number in range."""
    keys = keys or ph.keys
    p = ph.plan
    rows = H.digests(df.select(F.struct(*[c for c in df.columns if c != out]).alias("__own"), *[F.col(x).alias(f"__k{i}") for i, x in enumerate(keys)]), [f"__k{i}" for i in range(len(keys))])
    side = ph.segments
    joined = rows.withColumn("block", H.draw(H.BLOCK, p.seed, 0, ph.blocks)).join(F.broadcast(side) if ph.size_bytes() <= S.BROADCAST_BYTES else side, "block", "left")
    got = S.read_slots(replace_plan(ph), joined, "__code")
    code = F.pmod(F.col("__code"), F.lit(p.k))
    slot = F.coalesce(*[F.when(code == i, F.col(f"__s{i}")) for i in range(p.k)])
    got = got.withColumn("__slot", slot)
    slot = F.col("__slot")
    if ph.minimal:
        slot = F.least(F.col("__slot") - F.size(F.filter("before", lambda x: x < F.col("__slot"))), F.col("n_keys") - 1)
    return got.select("__own.*", (F.col("first") + slot).cast("bigint").alias(out))


def replace_plan(ph: S.Store) -> S.Store:
    return S.Store(replace(ph.plan, compressed=False), ph.keys, ph.segments, ph.blocks, ph.n_keys)


def build_ordered(df: DataFrame, key: str | list[str], order: list, plan: S.Plan | None = None) -> S.Store:
    """Order-preserving minimal hash: the ordinal itself is the value.  Ordinals come from ranges and their counts."""
    keys = [key] if isinstance(key, str) else key
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.select(*dict.fromkeys([*keys, *order])).repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id()).persist()
    counts = ranged.groupBy("part").agg(F.count("*").alias("n"), F.min("at").alias("zero"))
    base = counts.select("part", "zero", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))  # a row for each range
    numbered = ranged.join(F.broadcast(base), "part").withColumn("ordinal", F.col("base") + F.col("at") - F.col("zero"))
    n = ranged.count()
    return S.build(numbered, keys, F.col("ordinal"), plan or S.Plan(width=max(1, math.ceil(math.log2(n + 1)))))


def hash_bits(ph: S.Store) -> DataFrame:
    """(n, choice_bits, rank_bits): the choices of the slots, and the slots that no key has for the minimal form."""
    width = F.ceil(F.log2(F.col("n_slots") + 1))
    rank = F.sum(F.size("before") * width) if ph.minimal else F.lit(0)
    return ph.segments.agg(F.sum("n_keys").cast("bigint").alias("n"), (F.sum("n_slots") * ph.plan.width).cast("bigint").alias("choice_bits"), rank.cast("bigint").alias("rank_bits"))
