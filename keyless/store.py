"""Retrieval stores: keys to r-bit values without the keys.

Keys are dealt to blocks of about ``block`` keys by a hash; a block is a small sparse system over its own slots, solved inside one
task of a clustered pass.  Blocks that are too large or dependent give their keys to an overflow store.  A lookup is a join with the
row of the block and an XOR of k slots, all in generated code.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import krylov
from keyless import linalg as A
from keyless import small

SEGMENTS = "block long, n_keys int, n_slots int, seed int, status int, words array<long>, used array<long>, before array<int>, first long"
EMPTY, GOOD, OVER = 0, 1, 2
#: Bytes of a store that may be broadcast; a larger one is joined by a shuffle of the probes.
BROADCAST_BYTES = 256 << 20


class ConflictError(ValueError):
    """A key has two values."""


class BuildError(RuntimeError):
    """The tries are used up."""


def least_slots(k: int, n: int, m: int) -> int:
    """m, or more where it leaves rows of k slots no choice: two rows of k slots out of k are equal whatever is drawn."""
    return max(k + 2 * (n > 1), m)


@dataclass(frozen=True)
class Plan:
    """How a store is built.

    kind: ``sparse`` rows of k distinct slots; ``square`` as many slots as keys and rows of about 2 log n; ``peel`` rows of k slots
    solved in linear time; ``peel_add`` the same with addition modulo 2^width; ``repeat`` draws with repetition; ``table`` rows of a few
    slots in blocks so small that all their matrices stand in a table; ``field`` sums over the prime field on sets ``kary``, ``two_runs``,
    ``probe_run`` or ``ring``, two runs that wrap around exactly as many cells as keys.  weights: rule of the row weights of ``square``, see
    ``weight_cuts``; with ``whole`` a key whose weight is outside the clip gives any value."""

    width: int = 8
    k: int = 4
    slack: float = 0.06
    block: int = 256
    headroom: float = 0.0
    tries: int = 8
    kind: str = "sparse"
    sets: str = "kary"
    run: int = 8
    combine: str = "flag"
    seed: int = 1
    compressed: bool = False
    equal_segments: bool = False
    prime: int = H.PRIME
    weights: str = "inverse"

    @property
    def cell_bits(self) -> int:
        """Bits of a slot: those of a value, or of an element of the field."""
        return (self.prime - 1).bit_length() if self.kind == "field" else self.width

    def slots_for(self, n: int) -> int:
        if not n:
            return 0
        if self.kind == "square" or self.sets == "ring":
            return n
        base = self.block * (1 + self.headroom) if self.equal_segments else n
        extra = 2 * self.run if self.kind == "field" and self.sets != "kary" else 0
        return least_slots(self.k, n, math.ceil((1 + self.slack) * base)) + extra


@dataclass
class Store:
    plan: Plan
    keys: list[str]
    segments: DataFrame
    blocks: int
    n_keys: int
    overflow: Store | None = None
    decode: Callable[[Column], Column] = field(default=lambda c: c)

    def size_bytes(self) -> int:
        """Bytes of the segments in memory, from above: words, marks and ranks, and what a row takes by itself."""
        slots = self.plan.slots_for(self.plan.block) * self.blocks + self.n_keys * (1 + self.plan.slack)
        each = 64 / (64 // max(self.plan.cell_bits, 1))
        return int(slots * (each + (1.5 if self.plan.compressed else 0)) / 8) + 160 * self.blocks


def normalise(df: DataFrame, keys: list[str], value: Column | None, on_conflict: str = "error") -> DataFrame:
    """(d1, d2, value): null keys dropped, duplicates met once."""
    rows = H.digests(df.withColumn("__value", (F.lit(0) if value is None else value).cast("bigint")), keys).filter("d1 is not null and __value is not null")
    low, high = F.min("__value").alias("value"), F.max("__value").alias("other")
    met = rows.groupBy("d1", "d2").agg(low, high)
    if on_conflict == "error":
        return met.withColumn("value", F.when(F.col("value") == F.col("other"), F.col("value")).otherwise(F.raise_error(F.lit("conflict: a key has two values")).cast("bigint"))).drop("other")
    return met.select("d1", "d2", F.col("value" if on_conflict == "min" else "other").alias("value"))


def entries(plan: Plan, d1: np.ndarray, d2: np.ndarray, n: np.ndarray, m: np.ndarray, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(key, slot) of all ones of the rows of many keys; ``n`` and ``m``: keys and slots of the block of each."""
    if plan.kind != "square":
        cells = H.np_slots(d1, d2, plan.k, m, seed, how="repeat" if plan.kind == "repeat" else "skip")
        return np.repeat(np.arange(len(d1)), plan.k), cells.ravel()
    weight = np.empty(len(d1), np.int64)
    for size in np.unique(n).tolist():
        at = np.flatnonzero(n == size)
        weight[at] = H.np_weights(d1[at], d2[at], max(size, 3), seed, plan.weights)
        if plan.weights == "whole":
            # a key outside the clip has no row, so its block is drawn anew
            least, most = H.clip(max(size, 3))
            weight[at] = np.where((weight[at] < least) | (weight[at] > most), 0, weight[at])
    weight = np.minimum(weight, m)
    keys, cells = [], []
    # keys of one weight are drawn together
    for w in np.unique(weight[weight > 0]).tolist():
        at = np.flatnonzero(weight == w)
        keys.append(np.repeat(at, w))
        cells.append(H.np_slots(d1[at], d2[at], w, m[at], seed).ravel())
    return np.concatenate([np.zeros(0, np.int64), *keys]), np.concatenate([np.zeros(0, np.int64), *cells])


def field_rows(plan: Plan, d1: np.ndarray, d2: np.ndarray, m: int, seed: int) -> list[dict[int, int]]:
    """Maps from slot to coefficient."""
    cells = field_cells(plan, d1, d2, m, seed)
    factors = np.stack([H.np_draw(H.FIELD, seed, j, d1, d2, plan.prime) for j in range(cells.shape[1])], 1).tolist()
    out = []
    for own, given in zip(cells.tolist(), factors):
        row: dict[int, int] = {}
        for c, g in zip(own, given):
            row[c] = (row.get(c, 0) + g) % plan.prime
        out.append(row)
    return out


def field_cells(plan: Plan, d1: np.ndarray, d2: np.ndarray, m: int, seed: int) -> np.ndarray:
    if plan.sets == "kary":
        return H.np_slots(d1, d2, plan.k, m, seed)
    if plan.sets == "ring":
        starts = [H.np_draw(H.RUN, seed, i, d1, d2, m) for i in range(2)]
        return np.concatenate([(s[:, None] + np.arange(plan.run)) % m for s in starts], 1)
    starts = [H.np_draw(H.RUN, seed, i, d1, d2, m - plan.run + 1) for i in range(2 if plan.sets == "two_runs" else 1)]
    return np.concatenate([s[:, None] + np.arange(plan.run) for s in starts], 1)


def pack(slots: list[int], width: int) -> list[int]:
    """Slots in 64-bit words, floor(64 / width) to a word."""
    q = 64 // width
    out = []
    for at in range(0, len(slots), q):
        word = 0
        for j, x in enumerate(slots[at : at + q]):
            word |= x << (j * width)
        out.append(word - (1 << 64) if word >> 63 else word)
    return out


#: Words of the systems that are eliminated together, and keys that are gathered for it.
BATCH_WORDS, BATCH_KEYS = 1 << 17, 1 << 15
#: Keys beyond which a system is eliminated by itself.
ONE_SYSTEM = 2048
Part = tuple[np.ndarray, np.ndarray, np.ndarray]


def solve_blocks(plan: Plan, parts: list[Part]) -> list[tuple[int, int, int, list[int], list[int]]]:
    """(slots, seed, status, solution, pivots) of each block (d1, d2, values)."""
    out: list = [None] * len(parts)
    size = {}
    for i, (d1, _, _) in enumerate(parts):
        m = plan.slots_for(len(d1))
        if plan.headroom and len(d1) > (1 + plan.headroom) * plan.block or m < plan.k and plan.sets != "ring":
            out[i] = (m if plan.equal_segments else 0), 0, OVER, [], []
        else:
            size[i] = m
    for t in range(plan.tries):
        live = sorted((i for i in size if out[i] is None), key=lambda i: (size[i], len(parts[i][0])))
        while live:
            # blocks of like size side by side, so that little is padding
            some, live = _batch(live, size, parts)
            for i, found in zip(some, _solve_some(plan, [parts[i] for i in some], [size[i] for i in some], plan.seed * 1000 + t)):
                if found:
                    out[i] = (size[i], t, GOOD, *found)
    return [(plan.slots_for(len(parts[i][0])) if plan.equal_segments else 0, plan.tries, OVER, [], []) if x is None else x for i, x in enumerate(out)]


def _batch(live: list[int], size: dict[int, int], parts: list[Part]) -> tuple[list[int], list[int]]:
    k, n = 0, 0
    while k < len(live):
        n = max(n, len(parts[live[k]][0]))
        if k and (k + 1) * n * (size[live[k]] // 64 + 2) > BATCH_WORDS:
            break
        k += 1
    return live[:k], live[k:]


def _solve_some(plan: Plan, parts: list[Part], sizes: list[int], seed: int) -> Iterator[tuple[list[int], list[int]] | None]:
    if plan.kind in ("peel", "peel_add"):
        for (d1, d2, values), m in zip(parts, sizes):
            got = A.peel_solve(H.np_slots(d1, d2, plan.k, m, seed).tolist(), values.tolist(), m, "xor" if plan.kind == "peel" else "add", 1 << plan.width)
            yield None if got is None else (got, list(range(m)))
        return
    if plan.kind == "table":
        yield from small.solve(plan, parts, sizes[0], seed)
        return
    if plan.kind == "field":
        for (d1, d2, values), m in zip(parts, sizes):
            yield A.solve_field(field_rows(plan, d1, d2, m, seed), values.tolist(), m, plan.prime)
        return
    if len(parts) == 1 and len(parts[0][0]) > ONE_SYSTEM:
        # one large system is mostly zeros for long; only what is left when its sparse part is used up is a dense system.  The pivots
        # are asked for where slots that are none are not stored
        (d1, d2, values), m = parts[0], sizes[0]
        key, cell = entries(plan, d1, d2, np.full(len(d1), len(d1)), np.full(len(d1), m), seed)
        cuts = np.searchsorted(key[order := np.argsort(key, kind="stable")], np.arange(len(d1) + 1)).tolist()
        cell = cell[order].tolist()
        yield A.solve_lazy([cell[a:b] for a, b in zip(cuts[:-1], cuts[1:])], values.tolist(), m, plan.width, not plan.compressed)
        return
    counts = np.array([len(p[0]) for p in parts])
    block = np.repeat(np.arange(len(parts)), counts)
    row = np.arange(len(block)) - np.repeat(np.cumsum(counts) - counts, counts)
    key, cell = entries(plan, np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]), counts[block], np.array(sizes)[block], seed)
    yield from solve_systems(block, row, key, cell, np.concatenate([p[2] for p in parts]), counts, sizes)


def solve_systems(block: np.ndarray, row: np.ndarray, key: np.ndarray, cell: np.ndarray, values: np.ndarray, counts: np.ndarray, sizes: list[int]) -> Iterator[tuple[list[int], list[int]] | None]:
    """Slots and pivots of each system, or None where its rows are dependent.  ``block`` and ``row``: of each key; ``key`` and ``cell``: of each entry."""
    wide = np.zeros((len(counts), int(counts.max())), np.uint64)
    wide[block, row] = values.astype(np.int64).view(np.uint64)
    slots, pivots = A.solve_batch(A.bit_rows(block[key], row[key], cell, wide, (*wide.shape, max(sizes))), max(sizes))
    for i, m in enumerate(sizes):
        yield (slots[i, :m].tolist(), np.flatnonzero(pivots[i]).tolist()) if pivots[i].sum() == counts[i] else None


def per_block(batches: Iterator[pa.RecordBatch], columns: list[str]) -> Iterator[tuple[int, list[np.ndarray]]]:
    """Whole blocks of clustered batches; a block that two batches share is held back."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        block = batch.column("block").to_numpy()
        last = block[-1]
        cut = int(np.searchsorted(block, last))
        if cut:
            yield from _blocks(pa.Table.from_batches([*held, batch.slice(0, cut)]), columns)
            held = [batch.slice(cut)]
        elif held and held[0].column("block")[0].as_py() != last:
            yield from _blocks(pa.Table.from_batches(held), columns)
            held = [batch]
        else:
            held.append(batch)
    if held:
        yield from _blocks(pa.Table.from_batches(held), columns)


def _blocks(table: pa.Table, columns: list[str]) -> Iterator[tuple[int, list[np.ndarray]]]:
    block = table.column("block").to_numpy()
    data = [table.column(c).to_numpy() for c in columns]
    edges = np.r_[0, np.flatnonzero(np.diff(block)) + 1, len(block)]
    for a, b in zip(edges[:-1], edges[1:]):
        yield int(block[a]), [x[a:b] for x in data]


def clustered(keys: DataFrame, blocks: int, role: int = H.BLOCK, master: int = 1) -> DataFrame:
    parts = max(1, min(blocks, int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    return keys.withColumn("block", H.draw(role, master, 0, blocks)).repartition(parts, "block").sortWithinPartitions("block", "d1", "d2")


def build(df: DataFrame, keys: list[str], value: Column | None, plan: Plan, on_conflict: str = "error", blocks: int | None = None, normalised: bool = False) -> Store:
    """A store of ``value`` (an unsigned number below 2^width) by ``keys``."""
    rows = df if normalised else normalise(df, keys, value, on_conflict)
    rows = rows.persist()  # read by the count, the pass over the blocks and the overflow
    n = rows.count()
    blocks = blocks or max(1, math.ceil(n / plan.block))
    if plan.combine == "compensate":
        return _compensated(rows, keys, plan, blocks, n)
    segments = _one_square(rows, plan) if blocks == 1 and n > ONE_SYSTEM and plan.kind == "square" and plan.width <= 32 else None
    if segments is None:
        segments = clustered(rows, blocks, master=plan.seed).mapInArrow(functools.partial(_pass, plan), SEGMENTS).persist()
    over = rows.withColumn("block", H.draw(H.BLOCK, plan.seed, 0, blocks)).join(segments.filter(F.col("status") == OVER).select("block"), "block", "left_semi").drop("block")
    store = Store(plan, keys, segments, blocks, n)
    if not over.isEmpty():
        store.overflow = overflow_store(over, keys, plan)
    return store


def overflow_store(rows: DataFrame, keys: list[str], plan: Plan) -> Store:
    """A peel store of three slots a key and 1.3 slots for each; wider where that fails."""
    for t in range(6):
        inner = Plan(width=plan.width, k=3, slack=0.3 + 0.05 * t, block=2048, tries=8, kind="peel", seed=plan.seed + 77 + t)
        out = build(rows, keys, None, inner, blocks=max(1, math.ceil(rows.count() / 2048)), normalised=True)
        if out.overflow is None and out.segments.filter(F.col("status") == OVER).isEmpty():
            return out
    raise BuildError("the overflow store did not settle")


def solved(solve: Callable[[list[Part]], list], batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, tuple]]:
    """(block, keys, solution), blocks being solved some at a time."""
    held: list[tuple[int, list]] = []

    def flush() -> Iterator[tuple[int, int, tuple]]:
        for (b, p), x in zip(held, solve([p for _, p in held])):
            yield b, len(p[0]), x
        held.clear()

    n = 0
    for block, part in per_block(batches, ["d1", "d2", "value"]):
        held.append((block, part))
        n += len(part[0])
        if n >= BATCH_KEYS:
            yield from flush()
            n = 0
    yield from flush()


def _pass(plan: Plan, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    out = []
    for block, n_keys, (m, t, status, slots, pivots) in solved(functools.partial(solve_blocks, plan), batches):
        out.append(segment(plan, block, n_keys, m, t, status, slots, pivots))
        if len(out) == 512:
            yield _segment_batch(out)
            out = []
    if out:
        yield _segment_batch(out)


def _one_square(rows: DataFrame, plan: Plan) -> DataFrame:
    """The segment of one large square system.  Most draws have dependent rows, which shows only at the end, so as many are worked out at a time as
    there are cores; the first of those with a solution counts.  Without any the segment is given up."""
    spark = rows.sparkSession
    at_once = max(1, spark.sparkContext.defaultParallelism)
    for t in range(0, plan.tries, at_once):
        tries = spark.range(t, min(t + at_once, plan.tries)).select(F.col("id").alias("block"))
        dealt = rows.select("d1", "d2", "value").crossJoin(F.broadcast(tries)).repartitionById(at_once, (F.col("block") - t).cast("int")).sortWithinPartitions("block", "d1", "d2")
        good = dealt.mapInArrow(functools.partial(_try_square, plan), SEGMENTS).persist()
        first = good.orderBy("seed").limit(1).persist()
        if not first.isEmpty():
            return first
    return spark.createDataFrame([(0, rows.count(), 0, plan.tries, OVER, [], [], [], 0)], SEGMENTS)


def _try_square(plan: Plan, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for t, (d1, d2, values) in per_block(batches, ["d1", "d2", "value"]):
        n = len(d1)
        key, cell = entries(plan, d1, d2, np.full(n, n), np.full(n, n), plan.seed * 1000 + t)
        slots = krylov.solve(key, cell, values, plan.width, t)
        if slots is not None:
            yield _segment_batch([segment(plan, 0, n, n, t, GOOD, slots, list(range(n)))])


def segment(plan: Plan, block: int, n_keys: int, m: int, t: int, status: int, slots: list[int], pivots: list[int]) -> dict:
    used, before = [], []
    if plan.compressed and status == GOOD:
        slots = [slots[p] for p in pivots]
        marks = sum(1 << p for p in pivots)
        used = [(w - (1 << 64) if w >> 63 else w) for w in ((marks >> 64 * i) & (1 << 64) - 1 for i in range(-(-m // 64)))]
        before = np.r_[0, np.cumsum([int(w & (1 << 64) - 1).bit_count() for w in used])[:-1]].astype(int).tolist()
    return {"block": block, "n_keys": n_keys, "n_slots": m, "seed": t, "status": status, "words": pack(slots, plan.cell_bits), "used": used, "before": before, "first": 0}


def _segment_batch(rows: list[dict]) -> pa.RecordBatch:
    i, l = pa.int32(), pa.int64()
    return pa.RecordBatch.from_pylist(rows, pa.schema([("block", l), ("n_keys", i), ("n_slots", i), ("seed", i), ("status", i), ("words", pa.list_(l)), ("used", pa.list_(l)), ("before", pa.list_(i)), ("first", l)]))


def _compensated(rows: DataFrame, keys: list[str], plan: Plan, blocks: int, n: int) -> Store:
    """Good blocks store the value XOR the answer of the overflow store; bad ones are zero, so both are always read."""
    flagged = replace(plan, combine="flag")
    first = build(rows.withColumn("value", F.lit(0).cast("bigint")), keys, None, flagged, blocks=blocks, normalised=True)
    bad = first.segments.filter(F.col("status") == OVER).select("block")
    over = rows.withColumn("block", H.draw(H.BLOCK, plan.seed, 0, blocks)).join(bad, "block", "left_semi").drop("block")
    second = overflow_store(over, keys, plan)
    answered = lookup_digests(rows, second, "second").withColumn("value", F.col("value").bitwiseXOR(F.coalesce("second", F.lit(0)))).select("d1", "d2", "value")
    segments = clustered(answered, blocks, master=plan.seed).mapInArrow(functools.partial(_pass, flagged), SEGMENTS).persist()
    return Store(plan, keys, segments, blocks, n, second)


def once(df: DataFrame, out: str, value: Column) -> DataFrame:
    """``df`` and the value, out of a generator of one row: Catalyst leaves filters and join keys on it above, where they would otherwise be
    rewritten over the draws and repeat them beyond compiled code, and still pushes filters on other columns below."""
    return df.select("*", F.inline(F.array(F.struct(value.alias(out)))))


def read_slots(store: Store, df: DataFrame, out: str) -> DataFrame:
    """Answer of the segment that was joined to each row."""
    plan = store.plan
    bits = plan.cell_bits
    mask = (1 << bits) - 1 if bits < 63 else (1 << 63) - 1

    def cell(j: Column) -> Column:
        if plan.compressed:
            word, bit = F.try_element_at("used", (j / 64).cast("int") + 1), (j % 64).cast("int")
            here = F.call_function("shiftrightunsigned", word, bit).bitwiseAND(F.lit(1)) == 1
            low = word.bitwiseAND(F.bitwise_not(F.call_function("shiftleft", F.lit(-1).cast("bigint"), bit)))
            place = F.try_element_at("before", (j / 64).cast("int") + 1) + F.bit_count(low)
            return F.when(here, packed(place.cast("bigint"))).otherwise(F.lit(0).cast("bigint"))
        return packed(j)

    def packed(j: Column) -> Column:
        q = 64 // bits
        return F.call_function("shiftrightunsigned", F.try_element_at("words", F.floor(j / q).cast("int") + 1), (j % q * bits).cast("int")).bitwiseAND(F.lit(mask))

    seed = F.lit(plan.seed * 1000) + F.col("seed")
    good = (F.col("status") == GOOD) & F.col("d1").isNotNull()
    if plan.kind == "square":
        return _square_lookup(store, df, out, cell, seed, good)
    if plan.kind == "field":
        if plan.sets == "kary":
            df = H.slot_columns(df, plan.k, F.col("n_slots"), seed, prefix="__s")
            cells = [F.col(f"__s{i}") for i in range(plan.k)]
        else:
            ring = plan.sets == "ring"
            size = F.greatest(F.col("n_slots") - (0 if ring else plan.run - 1), F.lit(1))
            starts = [H.draw(H.RUN, seed, i, size) for i in range(1 if plan.sets == "probe_run" else 2)]
            df = df.withColumns({f"__r{i}": s for i, s in enumerate(starts)})
            cells = [F.col(f"__r{i}") + j for i in range(len(starts)) for j in range(plan.run)]
            if ring:
                cells = [F.pmod(c, size.cast("bigint")) for c in cells]
        total = F.lit(0).cast("bigint")
        for i, c in enumerate(cells):
            total = F.pmod(total + H.draw(H.FIELD, seed, i, plan.prime) * packed(c), F.lit(plan.prime))
        return once(df, out, F.when(good, total))
    df = H.slot_columns(df, plan.k, F.col("n_slots"), seed, prefix="__s", how="repeat" if plan.kind == "repeat" else "skip")
    total = None
    for i in range(plan.k):
        x = cell(F.col(f"__s{i}"))
        total = x if total is None else total + x if plan.kind == "peel_add" else total.bitwiseXOR(x)
    if plan.kind == "peel_add":
        total = F.pmod(total, F.lit(1 << plan.width))
    return once(df, out, F.when(good, total))


def _square_lookup(store: Store, df: DataFrame, out: str, cell: Callable, seed: Column, good: Column) -> DataFrame:
    """Rows of a square block have a varying weight, so slots are folded in an array: draws, skip rule, XOR."""
    # the cuts depend on the number of keys of the block, which has few values
    sizes = [r[0] for r in store.segments.select("n_keys").distinct().collect()]  # at most a block's size
    tables = {n: H.weight_cuts(max(n, 3), rule=store.plan.weights) for n in sizes}
    u = H.draw(H.WEIGHT, seed, 0, 2**62)
    spark = df.sparkSession
    cut_rows = spark.createDataFrame([(int(n), int(lo), [int(x) for x in cuts], *H.clip(max(n, 3))) for n, (lo, cuts) in tables.items()], "n_keys int, lo int, cuts array<long>, least int, most int")
    df = df.join(F.broadcast(cut_rows), "n_keys", "left").withColumn("__u", u)
    drawn = F.col("lo") + F.size(F.filter("cuts", lambda c: c <= F.col("__u")))
    df = df.withColumn("__clipped", ~drawn.between(F.col("least"), F.col("most"))).withColumn("__w", F.least(drawn, F.col("n_slots")))
    draws = F.transform(F.sequence(F.lit(0), F.greatest(F.col("__w"), F.lit(1)) - 1), lambda i: F.pmod(F.xxhash64(F.lit(H.SLOT).cast("bigint"), seed.cast("bigint"), i.cast("bigint"), F.col("d1"), F.col("d2")), F.greatest(F.col("n_slots") - i, F.lit(1)).cast("bigint")))
    skip = lambda taken, x: F.aggregate(F.array_sort(taken), x, lambda g, t: g + (t <= g).cast("bigint"))
    slots = F.aggregate(draws, F.array().cast("array<bigint>"), lambda taken, x: F.array_append(taken, skip(taken, x)))
    df = df.withColumn("__slots", F.when(good & ~F.col("__clipped"), slots))
    value = F.aggregate(F.transform("__slots", cell), F.lit(0).cast("bigint"), lambda a, x: a.bitwiseXOR(x))
    # a weight outside the clip is that of no key of the block: any value will do
    return once(df, out, F.when(good, F.coalesce(value, F.lit(0).cast("bigint")))).drop("lo", "cuts", "least", "most")


def lookup_digests(df: DataFrame, store: Store, out: str, mode: str = "auto") -> DataFrame:
    """``df`` (with d1, d2) and the answer of the store; null where there is no good block."""
    keep = [c for c in df.columns if c != out]
    row = df.select(F.struct(*keep).alias("__row"), "d1", "d2").withColumn("block", H.draw(H.BLOCK, store.plan.seed, 0, store.blocks))
    side = store.segments.drop("first")
    if mode == "broadcast" or mode == "auto" and store.size_bytes() <= BROADCAST_BYTES:
        side = F.broadcast(side)
    joined = row.join(side, "block", "left")
    return read_slots(store, joined, out).select("__row.*", out, *(["status"] if "status" not in keep else []))


def lookup(df: DataFrame, store: Store, keys: list[str] | None = None, out: str = "value", mode: str = "auto") -> DataFrame:
    """``df`` with the value of each key.  A key that was not built in gets some value (zero where its block is empty); a null key
    gets null.  All columns and the multiplicity of rows stay."""
    columns = [c for c in df.columns if c != out]
    rows = H.digests(df.select(F.struct(*columns).alias("__own"), *[F.col(k).alias(f"__k{i}") for i, k in enumerate(keys or store.keys)]), [f"__k{i}" for i in range(len(keys or store.keys))])
    got = lookup_digests(rows, store, "__a", mode)
    if store.overflow is not None:
        got = lookup_digests(got.withColumnRenamed("status", "__status"), store.overflow, "__b", mode).drop("status")
        zero = F.lit(0).cast("bigint")
        if store.plan.combine == "compensate":
            value = F.coalesce("__a", zero).bitwiseXOR(F.coalesce("__b", zero))
        else:
            value = F.when(F.col("__status") == OVER, F.coalesce("__b", zero)).otherwise(F.coalesce("__a", zero))
    else:
        value = F.coalesce("__a", F.lit(0).cast("bigint"))
    return got.select("__own.*", F.when(F.col("d1").isNotNull(), store.decode(value)).alias(out))


def long_form(store: Store) -> DataFrame:
    """(block, slot, val): one row for each slot of the segments."""
    q, w = 64 // store.plan.width, store.plan.width
    word = store.segments.select("block", "n_slots", F.posexplode("words").alias("i", "word"))
    cell = word.select("block", "n_slots", "i", "word", F.explode(F.sequence(F.lit(0), F.lit(q - 1))).alias("j"))
    return cell.select("block", (F.col("i") * q + F.col("j")).cast("bigint").alias("slot"), F.call_function("shiftrightunsigned", F.col("word"), F.col("j") * w).bitwiseAND(F.lit((1 << w) - 1)).alias("val"), "n_slots").filter("slot < n_slots").drop("n_slots")


def lookup_long(df: DataFrame, store: Store, key: str, out: str = "value") -> DataFrame:
    """(key, value) of the distinct keys by relations only: k rows a key meet the long form and are summed by XOR.  A key whose block is
    empty gets zero, one whose block was given up the answer of the overflow store; null keys give no row."""
    if store.plan.kind not in ("sparse", "peel", "repeat") or store.plan.compressed:
        raise ValueError(f"no long form of {store.plan.kind} segments")
    keys = H.digests(df.select(F.col(key).alias("__key")).filter(F.col(key).isNotNull()).distinct(), ["__key"])
    got = _long(keys, store)
    if store.overflow is not None:
        second = _long(keys if store.plan.combine == "compensate" else got.filter(F.col("status") == OVER).select("__key", "d1", "d2"), store.overflow).select("__key", F.col("value").alias("second"))
        got = got.join(second, "__key", "left").withColumn("value", F.coalesce("value", F.lit(0).cast("bigint")).bitwiseXOR(F.coalesce("second", F.lit(0).cast("bigint"))))
    return got.select(F.col("__key").alias(key), F.coalesce("value", F.lit(0).cast("bigint")).alias(out))


def _long(keys: DataFrame, store: Store) -> DataFrame:
    """(__key, d1, d2, status, value); no value where there is no good block."""
    here = keys.withColumn("block", H.draw(H.BLOCK, store.plan.seed, 0, store.blocks)).join(store.segments.select("block", "status", "n_slots", "seed"), "block", "left")
    rows = H.slot_columns(here.filter(F.col("status") == GOOD), store.plan.k, F.col("n_slots"), F.lit(store.plan.seed * 1000) + F.col("seed"), prefix="__s", how="repeat" if store.plan.kind == "repeat" else "skip")
    cells = rows.select("__key", "block", F.explode(F.array(*[F.col(f"__s{i}") for i in range(store.plan.k)])).alias("slot"))
    found = cells.join(long_form(store), ["block", "slot"]).groupBy("__key").agg(F.bit_xor("val").alias("value"))
    return here.select("__key", "d1", "d2", "status").join(found, "__key", "left")


def flatten(store: Store) -> DataFrame:
    """(pos, val): the slots of the segments and of the overflow store behind one another, as one array.  Segments have one size."""
    width = store.plan.slots_for(store.plan.block)
    own = long_form(store).select((F.col("block") * width + F.col("slot")).alias("pos"), "val")
    if store.overflow is None:
        return own
    second = long_form(store.overflow).join(F.broadcast(_firsts(store)), "block").select((F.col("at") + F.col("slot")).alias("pos"), "val")
    return own.unionAll(second)


def _firsts(store: Store) -> DataFrame:
    """(block, n_slots, seed, at): where the segments of the overflow store begin in the one array; a row for each of its blocks."""
    from pyspark.sql import Window

    before = F.sum("n_slots").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1))
    return store.overflow.segments.select("block", "n_slots", "seed", (F.lit(store.blocks * store.plan.slots_for(store.plan.block)) + F.coalesce(before, F.lit(0))).cast("bigint").alias("at"))


def flat_slots(keys: DataFrame, store: Store) -> DataFrame:
    """``keys`` (with d1, d2) and the places of the array that their sum reads: slots of a segment and of the overflow store."""
    columns = [c for c in keys.columns if c not in ("d1", "d2")]
    width, out = store.plan.slots_for(store.plan.block), None
    starts = store.segments.select("block", "n_slots", "seed", (F.col("block") * width).alias("at"))
    for st, first in ((store, starts), *(((store.overflow, _firsts(store)),) if store.overflow is not None else ())):
        rows = keys.withColumn("block", H.draw(H.BLOCK, st.plan.seed, 0, st.blocks)).join(first.filter("n_slots > 0"), "block")
        rows = H.slot_columns(rows, st.plan.k, F.col("n_slots"), F.lit(st.plan.seed * 1000) + F.col("seed"), prefix="__s")
        some = rows.select(*columns, F.explode(F.array(*[F.col("at") + F.col(f"__s{i}") for i in range(st.plan.k)])).alias("pos"))
        out = some if out is None else out.unionAll(some)
    return out


def verify(store: Store, df: DataFrame, value: Column) -> DataFrame:
    """(n, errors) over the rows with a key."""
    got = lookup(df.withColumn("__want", value.cast("bigint")), store, out="__got").filter(F.col("__got").isNotNull())
    return got.agg(F.count("*").alias("n"), F.count_if(F.col("__got") != F.col("__want")).cast("bigint").alias("errors"))


def logical_bits(store: Store) -> DataFrame:
    """Bits of slots, seeds, sizes and rank tables, by the definition of the measure; those of the overflow store count too.

    A segment's size and seed take what their ranges need, a status bit is there where there is an overflow store, and a rank table
    takes a bit a slot and, for each 64 of them, a number up to the slots."""
    p = store.plan
    rank = F.size("used") * (64 + F.ceil(F.log2(F.col("n_slots") + 1)))
    slots = F.when(F.size("used") > 0, F.col("n_keys") * p.width + rank).otherwise(F.col("n_slots") * p.cell_bits)
    side = math.ceil(math.log2(p.slots_for(2 * p.block) + 2)) + math.ceil(math.log2(p.tries + 1)) + (store.overflow is not None and p.combine == "flag")
    kept = F.when((F.col("status") == GOOD) | F.lit(p.equal_segments), slots).otherwise(0)
    own = store.segments.agg(F.coalesce(F.sum(kept), F.lit(0)).cast("bigint").alias("slot_bits"), (F.count("*") * side).cast("bigint").alias("side_bits"), F.coalesce(F.sum("n_keys"), F.lit(0)).cast("bigint").alias("n"))
    if store.overflow is None:
        return own
    second = logical_bits(store.overflow).select("slot_bits", "side_bits", F.lit(0).cast("bigint").alias("n"))
    return own.unionAll(second).agg(*[F.sum(c).cast("bigint").alias(c) for c in ("slot_bits", "side_bits", "n")])


def stored_bits(store: Store) -> int:
    """Bits of the segments as they stand in memory: whole words, marks, 32-bit ranks, and the columns of a row."""
    one = store.segments.agg(F.sum(64 * F.size("words") + 64 * F.size("used") + 32 * F.size("before") + 64 + 4 * 32)).first()[0] or 0
    return int(one) + (stored_bits(store.overflow) if store.overflow is not None else 0)


def reads(store: Store) -> tuple[int, bool]:
    """(slots read by a lookup at most, whether they depend on what was read before)."""
    p = store.plan
    own = {"square": min(p.slots_for(2 * p.block), int(4 * math.log(max(p.block, 3)))), "field": p.k if p.sets == "kary" else p.run * (1 if p.sets == "probe_run" else 2)}.get(p.kind, p.k)
    second = store.overflow.plan.k if store.overflow is not None else 0
    return own + second, p.compressed or bool(second) and p.combine == "flag"
