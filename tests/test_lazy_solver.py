"""One large sparse system."""

import time

import numpy as np
import pytest

from keyless import linalg as A


def holds(rows, values, slots, pivots, m):
    for r, v in zip(rows, values):
        for c in r:
            v ^= slots[c]
        assert v == 0
    assert len(set(pivots)) == len(rows) and not any(slots[c] for c in set(range(m)) - set(pivots))


def test_lazy_solver_solves_what_the_plain_one_solves():
    for n, m, k, kind in ((1, 3, 3, "distinct"), (60, 60, 9, "distinct"), (200, 206, 4, "distinct"), (300, 420, 3, "distinct"), (90, 100, 3, "repeat"), (64, 64, 12, "distinct")):
        for seed in range(12):
            rows = A.random_rows(n, m, k, seed, kind)
            values = [(i * 37 + seed) % 32 for i in range(n)]
            got = A.solve_lazy(rows, values, m, 5)
            assert (got is None) == (A.solve2(rows, values, m, 5) is None)
            if got:
                holds(rows, values, *got, m)


def test_large_system_is_not_cubic_in_its_keys():
    n, m = 30_000, 31_800
    rows, values = A.random_rows(n, m, 4, 3), [i % 32 for i in range(n)]
    began = time.monotonic()
    got = A.solve_lazy(rows, values, m, 5)
    assert time.monotonic() - began < 30
    holds(rows, values, *got, m)


def test_sums_of_written_slots_are_taken_in_stripes():
    rng, m, n = np.random.default_rng(2), 200, 300
    written = [sorted(rng.choice(m + j, min(m + j, int(rng.integers(0, 7))), replace=False).tolist()) for j in range(n)]
    dense = [sorted(rng.choice(m + n, 9, replace=False).tolist()) for _ in range(40)]
    given, wanted = rng.integers(0, 1 << 60, n).tolist(), rng.integers(0, 1 << 60, 40).tolist()
    plain = [(1 << j, 0) for j in range(m)]

    def total(cells, value):
        bits = 0
        for x in cells:
            bits, value = bits ^ plain[x][0], value ^ plain[x][1]
        return bits, value

    for cells, v in zip(written, given):
        plain.append(total(cells, v))
    for stripe in (1, 3, 64):
        with pytest.MonkeyPatch.context() as patch:
            patch.setattr(A, "STRIPE", stripe)
            got = A._in_terms_of(m, written, dense, given, wanted).tolist()
        assert [(sum(w << 64 * i for i, w in enumerate(r[:-1])), r[-1]) for r in got] == [total(c, v) for c, v in zip(dense, wanted)]
