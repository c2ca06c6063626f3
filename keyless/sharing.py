"""Split and share: retrieval without free randomness.

Keys are split in chunks by a polynomial hash of four coefficients, drawn anew until no chunk has more than the square root of all
keys.  All hash functions of all chunks read the same tables of random numbers: the j-th value of a key is the sum of an entry of
each of two tables, at two addresses that the chunk's own pair of linear hashes gives.  A chunk takes the first pair for which its
addresses form a graph without a cycle, which makes the values independent on its keys.  Every chunk is then a sparse system of its own.

The numbers in the tables follow from their place, so tables beyond TABLE_BYTES are not made: a lookup computes the entries it needs.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import store as S
from keyless import thresholds as T

SEGMENTS = "block long, n_keys int, n_slots int, seed int, pair int, status int, words array<long>"
#: Bytes of tables that go to every task; each entry is a 32-bit number.
TABLE_BYTES = 64 << 20
ADDRESS, ENTRY = 121, 122
PAIRS = 64


@dataclass(frozen=True)
class Plan:
    width: int
    k: int = 4
    slack: float = 0.2
    tries: int = 24
    seed: int = 1


@dataclass
class Store:
    plan: Plan
    keys: list[str]
    segments: DataFrame
    coefficients: list[int]
    chunks: int
    largest: int
    rows: int
    n_keys: int
    overflow: S.Store | None = None
    decode: Callable[[Column], Column] = field(default=lambda c: c)

    @property
    def functions(self) -> int:
        return self.plan.k * self.plan.tries

    def table_numbers(self) -> int:
        return 2 * self.rows * self.functions


def fourwise(seed: int) -> list[int]:
    return [int(x) for x in np.random.default_rng(seed).integers(1, H.PRIME, 4)]


def split(rows: DataFrame, chunks: int, limit: int, seed: int, most: int = 64) -> tuple[list[int], int]:
    """(coefficients, keys of the largest chunk) of the first hash whose chunks keep the limit."""
    for t in range(most):
        drawn = fourwise(seed * 1000 + t)
        largest = rows.groupBy(H.poly_hash(F.col("d1"), drawn, chunks)).count().agg(F.max("count")).first()[0] or 0
        if largest <= limit:
            return drawn, largest
    raise S.BuildError(f"no chunk hash keeps {limit} keys a chunk")


def np_addresses(d1: np.ndarray, d2: np.ndarray, pair: int, rows: int) -> list[np.ndarray]:
    """The addresses of keys in the two tables, each by a linear hash over the prime of a digest of its own."""
    out = []
    for side, d in enumerate((d1, d2)):
        a, b = (int(H.xx_longs(ADDRESS, pair, 2 * side + i).astype(np.uint64).view(np.int64)) % H.PRIME for i in range(2))
        out.append((max(a, 1) * np.mod(d, H.PRIME) + b) % H.PRIME % rows)
    return out


def addresses(pair: Column, rows: int) -> list[Column]:
    out = []
    for side, d in enumerate(("d1", "d2")):
        a, b = (F.pmod(F.xxhash64(F.lit(ADDRESS).cast("bigint"), pair.cast("bigint"), F.lit(2 * side + i).cast("bigint")), F.lit(H.PRIME)) for i in range(2))
        out.append(F.pmod(F.pmod(F.greatest(a, F.lit(1).cast("bigint")) * F.pmod(F.col(d), F.lit(H.PRIME)) + b, F.lit(H.PRIME)), F.lit(rows)))
    return out


def np_entry(side: int, function: np.ndarray | int, at: np.ndarray, seed: int) -> np.ndarray:
    return np.mod(np.atleast_1d(H.xx_longs(ENTRY, seed, side, np.broadcast_to(function, np.shape(at)).copy(), at)).view(np.int64), H.PRIME)


def acyclic(a: list[int], b: list[int]) -> bool:
    """Whether the edges between two sides close no cycle."""
    root: dict[tuple[int, int], tuple[int, int]] = {}

    def find(x: tuple[int, int]) -> tuple[int, int]:
        while (up := root.get(x, x)) != x:
            root[x] = x = root.get(up, up)
        return x

    for x, y in zip(a, b):
        p, q = find((0, x)), find((1, y))
        if p == q:
            return False
        root[p] = q
    return True


def solve(plan: Plan, rows: int, parts: list[S.Part]) -> list[tuple]:
    """(slots, try, pair, status, solution) of each chunk."""
    out: list = [None] * len(parts)
    pair: dict[int, int] = {}
    where: dict[int, list[np.ndarray]] = {}
    for i, (d1, d2, _) in enumerate(parts):
        for p in range(PAIRS):
            found = np_addresses(d1, d2, p, rows)
            if acyclic(*(x.tolist() for x in found)):
                pair[i], where[i] = p, found
                break
    size = {i: S.least_slots(plan.k, len(parts[i][0]), math.ceil((1 + plan.slack) * len(parts[i][0]))) for i in pair}
    for t in range(plan.tries):
        live = sorted((i for i in size if out[i] is None), key=size.get)
        while live:
            some, live = S._batch(live, size, parts)
            counts, sizes = np.array([len(parts[i][0]) for i in some]), [size[i] for i in some]
            block = np.repeat(np.arange(len(some)), counts)
            row = np.arange(len(block)) - np.repeat(np.cumsum(counts) - counts, counts)
            h = [np.concatenate([where[i][side] for i in some]) for side in (0, 1)]
            m = np.array(sizes)[block]
            raw = np.stack([np.mod((np_entry(0, t * plan.k + i, h[0], plan.seed) + np_entry(1, t * plan.k + i, h[1], plan.seed)) % H.PRIME, np.maximum(m - i, 1)) for i in range(plan.k)], 1)
            cells = H.skip_taken(raw).ravel()
            key = np.repeat(np.arange(len(block)), plan.k)
            for i, x in zip(some, S.solve_systems(block, row, key, cells, np.concatenate([parts[i][2] for i in some]), counts, sizes)):
                if x:
                    out[i] = size[i], t, pair[i], S.GOOD, x[0]
    return [(0, 0, 0, S.OVER, []) if x is None else x for x in out]


def _pass(plan: Plan, rows: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names, i, l = [x.split(" ")[0] for x in SEGMENTS.split(", ")], pa.int32(), pa.int64()
    out = []
    for block, n, (m, t, pair, status, slots) in S.solved(functools.partial(solve, plan, rows), batches):
        out.append((block, n, m, t, pair, status, S.pack(slots, plan.width)))
        if len(out) == 512:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), (l, i, i, i, i, i, pa.list_(l)))], names=names)
            out = []
    if out:
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), (l, i, i, i, i, i, pa.list_(l)))], names=names)


def build(df: DataFrame, keys: list[str], value: Column, plan: Plan, on_conflict: str = "error") -> Store:
    rows = S.normalise(df, keys, value, on_conflict).persist()
    n = rows.count()
    chunks, limit = T.chunk_plan(max(n, 1))
    drawn, largest = split(rows, chunks, max(limit, 1), plan.seed)
    size = max(2, math.ceil(2 * n**0.75))
    parts = max(1, min(chunks, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    dealt = rows.withColumn("block", H.poly_hash(F.col("d1"), drawn, chunks))
    segments = dealt.repartition(parts, "block").sortWithinPartitions("block", "d1", "d2").mapInArrow(functools.partial(_pass, plan, size), SEGMENTS).persist()
    out = Store(plan, keys, segments, drawn, chunks, largest, size, n)
    over = dealt.join(segments.filter(F.col("status") == S.OVER).select("block"), "block", "left_semi").drop("block")
    if not over.isEmpty():
        out.overflow = S.overflow_store(over, keys, S.Plan(width=plan.width, seed=plan.seed))
    return out


def tables(store: Store, spark) -> DataFrame:
    """One row with the two shared tables, function after function."""
    at = np.tile(np.arange(store.rows), store.functions)
    function = np.repeat(np.arange(store.functions), store.rows)
    return spark.createDataFrame(pa.table({f"t{side}": pa.array([np_entry(side, function, at, store.plan.seed).astype(np.int32)], pa.list_(pa.int32())) for side in (0, 1)}))


def lookup(df: DataFrame, store: Store, keys: list[str] | None = None, out: str = "value", shared: bool | None = None) -> DataFrame:
    """``df`` with the value of each key.  ``shared``: read stored tables, or compute their entries; by their size where not said."""
    plan, keys = store.plan, keys or store.keys
    shared = 4 * store.table_numbers() <= TABLE_BYTES if shared is None else shared
    rows = H.digests(df.select(F.struct(*[c for c in df.columns if c != out]).alias("__own"), *[F.col(k).alias(f"__k{i}") for i, k in enumerate(keys)]), [f"__k{i}" for i in range(len(keys))])
    rows = rows.withColumn("block", H.poly_hash(F.col("d1"), store.coefficients, store.chunks))
    small = store.n_keys * (1 + plan.slack) * plan.width / 8 + 120 * store.chunks <= S.BROADCAST_BYTES
    rows = rows.join(F.broadcast(store.segments) if small else store.segments, "block", "left")
    h = addresses(F.coalesce("pair", F.lit(0)), store.rows)
    rows = rows.withColumns({"__h0": h[0], "__h1": h[1]})
    function = lambda i: F.coalesce("seed", F.lit(0)).cast("bigint") * plan.k + i
    if shared:
        rows = rows.crossJoin(F.broadcast(tables(store, df.sparkSession)))  # one row
        entry = lambda side, i: F.try_element_at(f"t{side}", (function(i) * store.rows + F.col(f"__h{side}")).cast("int") + 1).cast("bigint")
    else:
        entry = lambda side, i: F.pmod(F.xxhash64(F.lit(ENTRY).cast("bigint"), F.lit(plan.seed).cast("bigint"), F.lit(side).cast("bigint"), function(i), F.col(f"__h{side}")), F.lit(H.PRIME))
    rows = H.slot_columns(rows, plan.k, F.coalesce("n_slots", F.lit(plan.k)), None, prefix="__s", source=lambda i, size: F.pmod(F.pmod(entry(0, i) + entry(1, i), F.lit(H.PRIME)), size.cast("bigint")))
    q, total = 64 // plan.width, F.lit(0).cast("bigint")
    for i in range(plan.k):
        j = F.col(f"__s{i}")
        total = total.bitwiseXOR(F.coalesce(F.call_function("shiftrightunsigned", F.try_element_at("words", F.floor(j / q).cast("int") + 1), (j % q * plan.width).cast("int")).bitwiseAND(F.lit((1 << min(plan.width, 63)) - 1)), F.lit(0).cast("bigint")))
    got = S.once(rows, "__a", F.when(F.col("d1").isNotNull(), total)).select("__own", "d1", "d2", F.col("status").alias("__status"), "__a")
    if store.overflow is not None:
        got = S.lookup_digests(got, store.overflow, "__b").withColumn("__a", F.when(F.col("__status") == S.OVER, F.coalesce("__b", F.lit(0).cast("bigint"))).otherwise(F.col("__a")))
    return got.select("__own.*", F.when(F.col("d1").isNotNull(), store.decode(F.col("__a"))).alias(out))


def bits(store: Store) -> DataFrame:
    """(n, slot_bits, side_bits, table_bits): slots, the size, try and pair of each chunk, and the shared tables."""
    side = math.ceil(math.log2(2 * store.largest + 2)) + math.ceil(math.log2(store.plan.tries + 1)) + math.ceil(math.log2(PAIRS))
    return store.segments.agg(F.sum("n_keys").cast("bigint").alias("n"), (F.sum("n_slots") * store.plan.width).cast("bigint").alias("slot_bits"), (F.lit(store.chunks) * side).cast("bigint").alias("side_bits"), F.lit(31 * store.table_numbers()).cast("bigint").alias("table_bits"))
