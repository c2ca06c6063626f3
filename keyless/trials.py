"""Random systems out of the keys of the orders: chances are counted over draws of given keys, by seed.

All keys are read; a trial's system has as many rows as its claim says, those of the keys with the least digests, drawn by its own seed."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyless import hashing as H


def key_rows(d1: np.ndarray, d2: np.ndarray, m: int, k: int, kind: str, seed: int, run: int = 8) -> list[list[int]]:
    """Slots of the rows of the keys, ``distinct``, ``repeat`` or ``two_runs`` (each place of two runs with chance a half)."""
    if kind != "two_runs":
        return H.np_slots(d1, d2, k, m, seed, how="repeat" if kind == "repeat" else "skip").tolist()
    starts = [H.np_draw(H.RUN, seed, i, d1, d2, m - run + 1).tolist() for i in range(2)]
    out = []
    for a, b, x in zip(*starts, H.np_draw(H.FIELD, seed, 0, d1, d2, 1 << 2 * run).tolist()):
        cells = {a + i for i in range(run) if x >> i & 1} ^ {b + i for i in range(run) if x >> run + i & 1}
        out.append(sorted(cells or {a}))
    return out


def simulate(orders: DataFrame, keys: int, grid: list[tuple], schema: str, run, out: str) -> DataFrame:
    """One row of the grid to a task; ``run(d1, d2, *row)`` gives the values of the columns ``out`` for the digests of ``keys`` orders."""
    names = [x.split(" ")[0] for x in f"{schema}, {out}".split(", ")]

    def each(batches):
        for batch in batches:
            rows = []
            for *row, own in zip(*[batch.column(i).to_pylist() for i in range(batch.num_columns)]):
                d1, d2 = (np.array([x[c] for x in own], np.int64) for c in ("d1", "d2"))
                rows.append((*row, *run(d1, d2, *row)))
            if rows:
                yield pa.RecordBatch.from_pylist([dict(zip(names, r)) for r in rows])

    least = H.digests(orders, ["o_orderkey"]).filter("d1 is not null").select("d1", "d2").orderBy("d1", "d2").limit(keys)
    whole = least.agg(F.array_sort(F.collect_list(F.struct("d1", "d2"))).alias("own"))  # one row of ``keys`` pairs
    rows = orders.sparkSession.createDataFrame(grid, schema).repartition(len(grid)).crossJoin(F.broadcast(whole))
    return rows.mapInArrow(each, f"{schema}, {out}")
