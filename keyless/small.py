"""Blocks so small that all their matrices are solved before: a table gives for each whether its rows are independent and, if so, which
values are summed for each slot; a second table gives those sums for some bits of the values at once.  Building is then lookups only."""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np

from keyless import hashing as H
from keyless import linalg as A

#: Bits of a value that the table of sums takes at once.
PIECE = 4
#: Entries of the larger table, from above.
ENTRIES = 1 << 16


@functools.lru_cache(maxsize=8)
def inverses(n: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(mask of rows for each slot, independent) of every matrix of n rows and m slots, numbered by its bits, the first row lowest."""
    if n * m > ENTRIES.bit_length() - 1:
        raise ValueError(f"{n} rows of {m} slots are too many for a table")
    number = np.arange(1 << (n * m))
    block, row, cell = (x.ravel() for x in np.meshgrid(number, np.arange(n), np.arange(m), indexing="ij"))
    one = (block >> (row * m + cell)) & 1 == 1
    # with unit values, the solution of a slot is the set of rows that it sums
    units = np.broadcast_to(np.uint64(1) << np.arange(n, dtype=np.uint64), (len(number), n))
    masks, pivots = A.solve_batch(A.bit_rows(block[one], row[one], cell[one], units, (len(number), n, m)), m)
    return masks.astype(np.uint8), pivots.sum(1) == n


@functools.lru_cache(maxsize=8)
def sums(n: int) -> np.ndarray:
    """The sum of the values in a mask, for every mask and every n values of PIECE bits."""
    mask, *values = np.meshgrid(np.arange(1 << n), *[np.arange(1 << PIECE)] * n, indexing="ij")
    out = np.zeros(mask.shape, np.uint8)
    for i, v in enumerate(values):
        out ^= np.where(mask >> i & 1, v, 0).astype(np.uint8)
    return out


def solve(plan, parts: list, m: int, seed: int) -> Iterator[tuple[list[int], list[int]] | None]:
    """Slots and their numbers for each block (d1, d2, values), or None where its rows are dependent."""
    out: list = [None] * len(parts)
    counts = np.array([len(p[0]) for p in parts])
    for n in np.unique(counts).tolist():
        own = np.flatnonzero(counts == n)
        d1, d2, values = (np.concatenate([parts[i][c] for i in own]) for c in range(3))
        cells = H.np_slots(d1, d2, plan.k, m, seed)
        rows = np.bitwise_xor.reduce(1 << cells, axis=1).reshape(-1, n)
        number = (rows << (m * np.arange(n))).sum(1)
        masks, independent = inverses(n, m)
        mask, values, table = masks[number], values.reshape(-1, n), sums(n)
        slots = np.zeros(mask.shape, np.int64)
        for at in range(0, plan.width, PIECE):
            pieces = (values >> at) & ((1 << PIECE) - 1)
            slots |= table[(mask, *[pieces[:, i : i + 1] for i in range(n)])].astype(np.int64) << at
        for i, ok, s in zip(own.tolist(), independent[number].tolist(), slots.tolist()):
            out[i] = (s, list(range(m))) if ok else None
    yield from out
