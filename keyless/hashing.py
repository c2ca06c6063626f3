"""Hash draws as Catalyst expressions and their numpy twins.

A key becomes two 64-bit digests once; every later draw hashes (role, seed, draw, d1, d2), all bigint, so that both sides agree."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: One constant for each use of a hash, so that uses are independent.
BLOCK, SLOT, OVERFLOW, SIGNATURE, WEIGHT, FIELD, RUN, CHUNK = range(101, 109)
PRIME = 2**31 - 1
#: Fixed values of the public 64-bit xx hash.
P1, P2, P3, P4, P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def normal(df: DataFrame, key: str) -> Column:
    kind = dict(df.dtypes)[key]
    if kind in ("tinyint", "smallint", "int", "bigint", "boolean"):
        return F.col(key).cast("bigint")
    if kind == "date":
        return F.unix_date(key).cast("bigint")
    if kind.startswith("timestamp"):
        return F.unix_micros(F.col(key).cast("timestamp"))
    if kind in ("float", "double") or kind.startswith("map"):
        raise TypeError(f"{key}: {kind} is no key type")
    return F.col(key)


def digests(df: DataFrame, keys: list[str]) -> DataFrame:
    """``df`` with d1 and d2; both null where a key column is null."""
    parts = [normal(df, k) for k in keys]
    known = F.lit(True)
    for k in keys:
        known = known & F.col(k).isNotNull()
    return df.withColumns({f"d{i}": F.when(known, F.xxhash64(F.lit(i).cast("bigint"), *parts)) for i in (1, 2)})


def draw(role: int, seed, number: int, m) -> Column:
    """A number below m, by role, seed and draw."""
    seed = seed if isinstance(seed, Column) else F.lit(seed)
    m = m if isinstance(m, Column) else F.lit(m)
    return F.pmod(F.xxhash64(F.lit(role).cast("bigint"), seed.cast("bigint"), F.lit(number).cast("bigint"), F.col("d1"), F.col("d2")), m.cast("bigint"))


def slot_columns(df: DataFrame, k: int, m, seed, role: int = SLOT, prefix: str = "s", how: str = "skip", source=None) -> DataFrame:
    """k slots below m.  ``skip``: distinct, each draw from those left; ``repeat``: with repetition.  ``source``: another way to draw the
    i-th number below a range."""
    source = source or (lambda i, size: draw(role, seed, i, size))
    m = m if isinstance(m, Column) else F.lit(m)
    # a block smaller than k is never looked up by its slots; its range only has to be legal
    taken: list[Column] = []
    for i in range(k):
        name = f"{prefix}{i}"
        df = df.withColumn(name, source(i, F.greatest(m - (i if how == "skip" else 0), F.lit(1))))
        if how == "skip" and taken:
            c = F.col(name)
            for t in taken:
                c = c + (c >= t).cast("bigint")
            df = df.withColumn(name, c)
            # the taken slots in ascending order, for the next draw
            ordered, carry = [], F.col(name)
            for j, t in enumerate(taken):
                df = df.withColumns({f"__{prefix}{i}_{j}": F.least(t, carry), f"__{prefix}{i}_{j}c": F.greatest(t, carry)})
                ordered.append(F.col(f"__{prefix}{i}_{j}"))
                carry = F.col(f"__{prefix}{i}_{j}c")
            taken = [*ordered, carry]
        else:
            taken = [F.col(name)]
    return df


def _rotl(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def xx_longs(*values) -> np.ndarray:
    """Spark's xxhash64 of bigint arguments."""
    h = np.uint64(42)
    with np.errstate(over="ignore"):
        for v in values:
            v = np.asarray(v, np.int64).view(np.uint64) if np.ndim(v) else np.uint64(int(v) & (1 << 64) - 1)
            x = h + P5 + np.uint64(8)
            x = x ^ (_rotl(v * P2, 31) * P1)
            x = _rotl(x, 27) * P1 + P4
            x = (x ^ (x >> np.uint64(33))) * P2
            x = (x ^ (x >> np.uint64(29))) * P3
            h = x ^ (x >> np.uint64(32))
    return h


def np_draw(role: int, seed: int, number: int, d1: np.ndarray, d2: np.ndarray, m: int) -> np.ndarray:
    return np.mod(np.atleast_1d(xx_longs(role, seed, number, d1, d2)).view(np.int64), m)


def np_slots(d1: np.ndarray, d2: np.ndarray, k: int, m: int | np.ndarray, seed: int, role: int = SLOT, how: str = "skip") -> np.ndarray:
    """(n, k) slots below m, one for all keys or one for each; ``swap`` (one m) gives the law of ``skip`` by swaps on an array that holds only what was touched."""
    if how == "repeat":
        return np.stack([np_draw(role, seed, i, d1, d2, m) for i in range(k)], 1)
    raw = np.stack([np_draw(role, seed, i, d1, d2, np.maximum(m - i, 1)) for i in range(k)], 1)
    if how == "swap":
        out = np.empty_like(raw)
        for row, r in zip(out, raw.tolist()):
            moved: dict[int, int] = {}
            for i, x in enumerate(r):
                row[i] = moved.get(x, x)
                moved[x] = moved.get(m - 1 - i, m - 1 - i)
        return out
    return skip_taken(raw)


def skip_taken(raw: np.ndarray) -> np.ndarray:
    """Draws from ever smaller ranges as slots: each is a place among the slots that are not yet taken."""
    for i in range(1, raw.shape[1]):
        taken = np.sort(raw[:, :i], axis=1)
        for j in range(i):
            raw[:, i] += raw[:, i] >= taken[:, j]
    return raw


def poly_hash(column, coefficients: list[int], m: int) -> Column:
    """c-wise independent family: a polynomial over the prime 2^31-1, then the remainder by m."""
    x = F.pmod(column.cast("bigint"), F.lit(PRIME))
    out = F.lit(coefficients[0]).cast("bigint")
    for c in coefficients[1:]:
        out = F.pmod(out * x + F.lit(c), F.lit(PRIME))
    return F.pmod(out, F.lit(m).cast("bigint"))


def portable_digest(column) -> Column:
    """The first 60 bits of md5, which any SQL engine can compute."""
    return F.conv(F.substring(F.md5(column), 1, 15), 16, 10).cast("bigint")


def clip(n: int, log=np.log) -> tuple[int, int]:
    """Least and largest weight of a row of a square system of n keys."""
    return max(1, int(np.ceil(0.5 * log(n)))), min(n, int(4 * log(n)))


def weight_cuts(n: int, log=np.log, rule: str = "inverse") -> tuple[int, np.ndarray]:
    """(least weight, cuts of the clipped binomial with chance 2 log n / n on 2^62): the weight of a draw is the least plus the
    number of cuts at or below it.  ``midpoint`` moves each cut half a step down; ``whole`` does not clip."""
    from math import lgamma, log as ln, log1p

    p = min(0.5, 2 * float(log(n)) / n)
    lo, hi = clip(n, log) if rule != "whole" else (0, min(n, 2 * clip(n, log)[1]))
    mass = [np.exp(lgamma(n + 1) - lgamma(w + 1) - lgamma(n - w + 1) + w * ln(p) + (n - w) * log1p(-p)) for w in range(lo, hi + 1)]
    dist = np.cumsum(mass) / np.sum(mass)
    if rule == "midpoint":
        dist = (np.concatenate([[0], dist[:-1]]) + dist) / 2
    return lo, (dist[:-1] * 2**62).astype(np.int64)


def np_weights(d1: np.ndarray, d2: np.ndarray, n: int, seed: int, rule: str = "inverse") -> np.ndarray:
    lo, cuts = weight_cuts(n, rule=rule)
    return lo + np.searchsorted(cuts, np_draw(WEIGHT, seed, 0, d1, d2, 2**62), side="right")
