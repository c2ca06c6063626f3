"""One large sparse system with slots to spare, solved by products without its dense part."""

import numpy as np
import pytest

from keyless import hashing as H
from keyless import krylov as K
from keyless import linalg as A
from keyless import store as S


def part(n, seed):
    rng = np.random.default_rng(seed)
    d1, d2 = (rng.integers(-(2**63), 2**63 - 1, n) for _ in range(2))
    return d1, d2, rng.integers(0, 32, n)


def never(*args):
    raise AssertionError("a dense system was made")


def test_large_system_is_never_made_dense():
    n = 60_000
    d1, d2, values = part(n, 1)
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(A, "_in_terms_of", never)
        patch.setattr(A, "echelon", never)
        m, t, status, slots, _ = S.solve_blocks(S.Plan(width=5, block=n, tries=2), [(d1, d2, values)])[0]
    assert (status, m, len(slots)) == (S.GOOD, 63_600, 63_600)
    cells = H.np_slots(d1, d2, 4, np.full(n, m), 1000 + t)
    assert (np.bitwise_xor.reduce(np.array(slots)[cells], axis=1) == values).all()


def test_compressed_store_still_has_its_pivots():
    n = 5000
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(A, "DENSE", 100)
        m, _, status, slots, pivots = S.solve_blocks(S.Plan(width=5, block=n, compressed=True), [part(n, 2)])[0]
    assert status == S.GOOD and len(pivots) == n
    assert not any(slots[c] for c in set(range(m)) - set(pivots))


@pytest.mark.parametrize("width", [1, 5, 20, 32])
def test_systems_are_solved_by_products(width):
    solved = 0
    for n, m, k, kind in ((1500, 1590, 4, "distinct"), (1200, 1500, 3, "repeat"), (900, 1000, 9, "distinct"), (900, 900, 12, "distinct")):
        for seed in range(4):
            rows = A.random_rows(n, m, k, seed, kind)
            values = np.random.default_rng(seed).integers(0, 1 << width, n).tolist()
            with pytest.MonkeyPatch.context() as patch:
                patch.setattr(A, "DENSE", 64)
                got = A.solve_lazy(rows, values, m, width, True)
            # dependent rows may still agree with their values
            assert got is not None or m == n or A.solve_lazy(rows, values, m, width) is None
            if got:
                solved += 1
                for r, v in zip(rows, values):
                    for c in r:
                        v ^= got[0][c]
                    assert v == 0
    assert solved >= 10


def test_values_that_are_all_alike():
    rows = A.random_rows(1500, 1590, 4, 5)
    for values in ([0] * 1500, [31] * 1500):
        with pytest.MonkeyPatch.context() as patch:
            patch.setattr(A, "DENSE", 64)
            slots, _ = A.solve_lazy(rows, values, 1590, 5, True)
        assert (np.bitwise_xor.reduce(np.array(slots)[np.array(rows)], axis=1) == values).all()


def test_rows_that_contradict_one_another_have_no_solution():
    rows = A.random_rows(1500, 1590, 4, 5)
    rows.append(rows[0])
    values = [i % 32 for i in range(1500)]
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(A, "DENSE", 64)
        assert A.solve_lazy(rows, [*values, values[0] ^ 1], 1590, 5, True) is None


def test_product_is_that_of_the_sums_written_out():
    rng, m, n = np.random.default_rng(2), 200, 300
    written = [sorted(rng.choice(m + j, min(m + j, int(rng.integers(0, 7))), replace=False).tolist()) for j in range(n)]
    rows = [sorted(rng.choice(m + n, int(rng.integers(0, 9)), replace=False).tolist()) for _ in range(90)]
    system = K.Written(m, written, rows, A._depths(m, written))
    given = rng.integers(0, 1 << 60, n).astype(np.uint64)
    for dtype in (np.uint64, np.uint8, np.uint64):
        x = rng.integers(0, 255, m).astype(dtype)
        for add in (None, given.astype(dtype)):
            plain = x.tolist()
            for j, cells in enumerate(written):
                plain.append(0 if add is None else int(add[j]))
                for c in cells:
                    plain[m + j] ^= plain[c]
            want = [int(np.bitwise_xor.reduce([0, *(plain[c] for c in cells)])) for cells in rows]
            assert system.product(x, add).tolist() == [want[i] for i in system.row]
