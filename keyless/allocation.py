"""Slot placement: every key in a cell of its own among few allowed ones, and its link with ranks over large fields."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyless import hashing as H
from keyless import linalg as A
from keyless import store as S

ROWS = "block long, d1 long, cell long, m int, allowed boolean, rank_ok boolean"


def place(df: DataFrame, keys: list[str], how: str = "kary", k: int = 3, load: float = 0.9, run: int = 4, block: int = 128, tries: int = 50, rank: bool = False, seed: int = 5) -> DataFrame:
    """(block, d1, cell, m, allowed, rank_ok).  how: ``kary``, ``two_runs`` or ``probe``; ``rank`` also tests that random
    coefficients on the allowed cells have full rank over a large prime field, and that a placement follows from the pivots.  A block that
    is placed is not drawn anew for its rank: rank_ok is false where the rank is short, by chance at most keys / prime."""
    rows = S.normalise(df.select(*keys), keys, None, "min")
    n = rows.count()
    blocks = max(1, -(-n // block))

    def run_block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, (d1, d2) in S.per_block(batches, ["d1", "d2"]):
            m = max(k, run, int(np.ceil(len(d1) / load)))
            cells = ok = None
            for t in range(tries):
                s = seed * 1000 + t
                if how == "probe":
                    homes = H.np_draw(H.RUN, s, 0, d1, d2, m).tolist()
                    cells, choices = A.place_probing(homes, m), None
                    break
                choices = H.np_slots(d1, d2, k, m, s).tolist() if how == "kary" else [sorted({*range(a, a + run), *range(c, c + run)}) for a, c in zip(H.np_draw(H.RUN, s, 0, d1, d2, m - run + 1).tolist(), H.np_draw(H.RUN, s, 1, d1, d2, m - run + 1).tolist())]
                cells = A.match(choices)
                if cells is None:
                    continue
                if rank:
                    coded = [{c: int(g) for c, g in zip(r, (H.np_draw(H.FIELD, s, j, d1[i : i + 1], d2[i : i + 1], H.PRIME - 1)[0] + 1 for j in range(len(r))))} for i, r in enumerate(choices)]
                    ok = rank_and_pivots(choices, coded, m)
                break
            if cells is None:
                raise S.BuildError(f"block {b}: no placement at load {load}")
            allowed = [True] * len(cells) if choices is None else [c in r for c, r in zip(cells, choices)]
            yield pa.RecordBatch.from_arrays([pa.array([b] * len(cells), pa.int64()), pa.array(d1), pa.array(cells, pa.int64()), pa.array([m] * len(cells), pa.int32()), pa.array(allowed), pa.array([ok] * len(cells), pa.bool_())], names=["block", "d1", "cell", "m", "allowed", "rank_ok"])

    return S.clustered(rows, blocks, master=seed).mapInArrow(run_block, ROWS)


def rank_and_pivots(choices: list[list[int]], coded: list[dict[int, int]], m: int) -> bool:
    """Whether the coded rows have full rank and a placement follows from the pivots."""
    found = A.solve_field(coded, [0] * len(coded), m, H.PRIME)
    if found is None:
        return False
    pivots = set(found[1])
    return A.match([[c for c in r if c in pivots] for r in choices]) is not None


def longest_run(df: DataFrame, region: str, home: str, key: str) -> DataFrame:
    """(region, longest_shift, cells_used) under linear probing without a ring, by sorting homes: the cell of the i-th key in order of
    homes is i plus the running maximum of home minus rank.  Regions are placed apart, so none needs more than one task."""
    w = Window.partitionBy(region).orderBy(home, key)
    placed = df.withColumn("__i", F.row_number().over(w)).withColumn("__cell", F.max(F.col(home) - F.col("__i")).over(w.rowsBetween(Window.unboundedPreceding, 0)) + F.col("__i"))
    return placed.groupBy(region).agg(F.max(F.col("__cell") - F.col(home)).cast("bigint").alias("longest_shift"), F.count_distinct("__cell").alias("cells_used"))
