"""Approximate membership from retrieval: a key is accepted where the store gives back its own signature."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import store as S


def _signature(s: int, seed: int) -> Column:
    return H.draw(H.SIGNATURE, seed, 0, 1 << s)


def build_filter(df: DataFrame, keys: list[str], s: int, plan: S.Plan = S.Plan()) -> S.Store:
    """No key is missed; any other is accepted with chance 2^-s.  The base is any kind of store."""
    rows = S.normalise(df.select(*keys), keys, None, "min").withColumn("value", _signature(s, plan.seed))
    return S.build(rows, keys, None, replace(plan, width=s), normalised=True)


def maybe(df: DataFrame, flt: S.Store, keys: list[str] | None = None, out: str = "maybe", mode: str = "auto") -> DataFrame:
    """``df`` with a boolean; null keys get false, and so does every key where the set is empty."""
    keys = keys or flt.keys
    if not flt.n_keys:
        return df.withColumn(out, F.lit(False))
    got = S.lookup(df, flt, keys, "__sig", mode)
    d = H.digests(got.withColumnsRenamed({c: f"__o_{c}" for c in got.columns}), [f"__o_{k}" for k in keys])
    ok = F.coalesce(F.col("__o___sig") == _signature(flt.plan.width, flt.plan.seed), F.lit(False))
    return d.select(*[F.col(f"__o_{c}").alias(c) for c in df.columns if c != out], ok.alias(out))


def build_guarded(df: DataFrame, keys: list[str], value: Column, r: int, s: int, plan: S.Plan = S.Plan()) -> S.Store:
    """r value bits beside s guard bits: other keys get null but for a chance of 2^-s."""
    rows = S.normalise(df, keys, value).withColumn("value", F.call_function("shiftleft", F.col("value"), F.lit(s)).bitwiseOR(_signature(s, plan.seed)))
    out = S.build(rows, keys, None, replace(plan, width=r + s), normalised=True)
    out.guard = s
    return out


def guarded(df: DataFrame, store: S.Store, keys: list[str] | None = None, out: str = "value") -> DataFrame:
    keys = keys or store.keys
    got = S.lookup(df, replace(store, decode=lambda c: c), keys, "__both")
    d = H.digests(got.withColumnsRenamed({c: f"__o_{c}" for c in got.columns}), [f"__o_{k}" for k in keys])
    s = store.guard
    both = F.col("__o___both")
    value = F.when(both.bitwiseAND(F.lit((1 << s) - 1)) == _signature(s, store.plan.seed), F.call_function("shiftright", both, F.lit(s)))
    return d.select(*[F.col(f"__o_{c}").alias(c) for c in df.columns if c != out], store.decode(value).alias(out))


def prefilter_join(fact: DataFrame, dim: DataFrame, on: str, flt: S.Store, how: str = "inner") -> DataFrame:
    """The ordinary join behind the filter: always exact, cheaper where few rows have a partner."""
    return maybe(fact, flt, [on]).filter("maybe").drop("maybe").join(dim, on, how)


def split_by_filter(df: DataFrame, flt: S.Store, on: str) -> tuple[DataFrame, DataFrame]:
    """(rows that may be members, rows that are not)."""
    both = maybe(df, flt, [on])
    return both.filter("maybe").drop("maybe"), both.filter("not maybe").drop("maybe")


def within_bound(hits: Column, n: Column, s: int) -> Column:
    """Five standard deviations around the expected number of false positives."""
    p = 2.0**-s
    return F.abs(hits - n * p) <= 5 * F.sqrt(n * p * (1 - p)) + 1
