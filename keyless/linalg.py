"""Solvers for sparse systems.  Rows over two elements are Python integers, so a row operation is one machine-level XOR."""

from __future__ import annotations

import random
from array import array
from collections import deque
from collections.abc import Iterator

import numpy as np

from keyless import krylov


def eliminate(rows: list[list[int]], values: list[int] | None = None) -> tuple[dict[int, tuple[int, int]], bool]:
    """Echelon form by least column: pivot column to (row, value).  False where the rows are dependent."""
    pivots: dict[int, tuple[int, int]] = {}
    for i, cells in enumerate(rows):
        row, value = 0, values[i] if values else 0
        for c in cells:
            row ^= 1 << c
        while row:
            low = (row & -row).bit_length() - 1
            held = pivots.get(low)
            if held is None:
                pivots[low] = (row, value)
                break
            row ^= held[0]
            value ^= held[1]
        if not row:
            return pivots, False
    return pivots, True


def row_sums(rows: list[list[int]]) -> int:
    """Sums of two rows that the elimination takes; each costs a word for every 64 slots."""
    pivots: dict[int, int] = {}
    sums = 0
    for cells in rows:
        row = 0
        for c in cells:
            row ^= 1 << c
        while row:
            low = (row & -row).bit_length() - 1
            if low not in pivots:
                pivots[low] = row
                break
            row ^= pivots[low]
            sums += 1
    return sums


def rank2(rows: list[list[int]]) -> int:
    pivots: dict[int, int] = {}
    for cells in rows:
        row = 0
        for c in cells:
            row ^= 1 << c
        while row:
            low = (row & -row).bit_length() - 1
            if low not in pivots:
                pivots[low] = row
                break
            row ^= pivots[low]
    return len(pivots)


def solve2(rows: list[list[int]], values: list[int], m: int, width: int) -> tuple[list[int], list[int]] | None:
    """(slots, pivot columns) with all free slots zero, or None.  The pivots do not depend on the order of the rows, so neither
    does the solution; all value bits are carried at once and read back by parities."""
    pivots, ok = eliminate(rows, values)
    if not ok:
        return None
    planes = [0] * width
    for p in sorted(pivots, reverse=True):
        row, value = pivots[p]
        for b in range(width):
            if (value >> b & 1) ^ ((row & planes[b]).bit_count() & 1):
                planes[b] |= 1 << p
    return [sum((planes[b] >> j & 1) << b for b in range(width)) for j in range(m)], sorted(pivots)


def bit_rows(block: np.ndarray, row: np.ndarray, cell: np.ndarray, values: np.ndarray, shape: tuple[int, int, int]) -> np.ndarray:
    """Systems of one shape (blocks, rows, slots) as words: bit ``cell`` of row ``row`` of block ``block`` is flipped for each entry,
    and the value of a row stands in its last word.  ``values``: (blocks, rows)."""
    b, n, m = shape
    out = np.zeros((b, n, -(-m // 64) + 1), np.uint64)
    np.bitwise_xor.at(out, (block, row, cell >> 6), np.uint64(1) << (cell & 63).astype(np.uint64))
    out[:, :, -1] = values
    return out


def solve_batch(words: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(slots, which slots are pivots) of all systems at once, columns in ascending order, free slots zero; the rows of a system are
    independent where it has as many pivots as rows.  Rows without entries are no rows.  ``words`` is used up."""
    at = np.arange(len(words))
    used = np.zeros(words.shape[:2], bool)
    row = np.full((len(words), m), -1)
    for c in range(m):
        bit = (words[:, :, c >> 6] >> np.uint64(c & 63)) & np.uint64(1)
        free = (bit != 0) & ~used
        first = free.argmax(1)
        has = free[at, first]
        if not has.any():
            continue
        used[at[has], first[has]] = True
        row[has, c] = first[has]
        bit[at, first] = 0
        bit[~has] = 0
        words ^= words[at, first][:, None, :] * bit[:, :, None]
    pivots = row >= 0
    return np.where(pivots, words[at[:, None], row, -1], np.uint64(0)), pivots


def peel_order(rows: list[list[int]], m: int) -> list[tuple[int, int]] | None:
    """(row, its own slot) from the last to be set to the first, or None where a core is left."""
    degree, mixed = [0] * m, [0] * m
    for i, cells in enumerate(rows):
        for c in cells:
            degree[c] += 1
            mixed[c] ^= i
    queue = [c for c in range(m) if degree[c] == 1]
    out: list[tuple[int, int]] = []
    while queue:
        c = queue.pop()
        if degree[c] != 1:
            continue
        i = mixed[c]
        out.append((i, c))
        for x in rows[i]:
            degree[x] -= 1
            mixed[x] ^= i
            if degree[x] == 1:
                queue.append(x)
    return out if len(out) == len(rows) else None


def peel_solve(rows: list[list[int]], values: list[int], m: int, op: str = "xor", modulus: int = 0) -> list[int] | None:
    order = peel_order(rows, m)
    if order is None:
        return None
    slots = [0] * m
    for i, c in reversed(order):
        if op == "xor":
            x = values[i]
            for j in rows[i]:
                if j != c:
                    x ^= slots[j]
        else:
            x = (values[i] - sum(slots[j] for j in rows[i] if j != c)) % modulus
        slots[c] = x
    return slots


def solve_field(rows: list[dict[int, int]], values: list[int], m: int, p: int) -> tuple[list[int], list[int]] | None:
    """The same over the prime field of p elements; rows map a slot to its coefficient."""
    pivots: dict[int, tuple[dict[int, int], int]] = {}
    for cells, v in zip(rows, values):
        row = {c: g % p for c, g in cells.items() if g % p}
        while row:
            low = min(row)
            if low not in pivots:
                inv = pow(row[low], -1, p)
                pivots[low] = ({c: g * inv % p for c, g in row.items()}, v * inv % p)
                break
            f, (held, hv) = row[low], pivots[low]
            for c, g in held.items():
                x = (row.get(c, 0) - f * g) % p
                if x:
                    row[c] = x
                else:
                    row.pop(c, None)
            v = (v - f * hv) % p
        if not row:
            return None
    slots = [0] * m
    for c in sorted(pivots, reverse=True):
        row, v = pivots[c]
        slots[c] = (v - sum(g * slots[j] for j, g in row.items() if j != c)) % p
    return slots, sorted(pivots)


def match(choices: list[list[int]]) -> list[int] | None:
    """One slot of its own for each row, by augmenting paths without recursion; None where there is no such choice."""
    owner: dict[int, int] = {}
    mine = [-1] * len(choices)
    for start in range(len(choices)):
        came: dict[int, int] = {}
        queue, end = [start], None
        while queue and end is None:
            i = queue.pop(0)
            for c in choices[i]:
                if c in came:
                    continue
                came[c] = i
                if c not in owner:
                    end = c
                    break
                queue.append(owner[c])
        if end is None:
            return None
        while end is not None:
            i = came[end]
            last = mine[i] if mine[i] >= 0 else None
            owner[end], mine[i] = i, end
            end = last if i != start else None
    return mine


def place_probing(homes: list[int], m: int) -> list[int]:
    """Linear probing on a ring of m cells, in the order given."""
    used, out = set(), []
    for h in homes:
        while h in used:
            h = (h + 1) % m
        used.add(h)
        out.append(h)
    return out


def random_rows(n: int, m: int, k: int, seed: int, kind: str = "distinct", run: int = 0) -> list[list[int]]:
    rng = random.Random(seed)
    if kind == "repeat":
        return [[rng.randrange(m) for _ in range(k)] for _ in range(n)]
    if kind == "two_runs":
        out = []
        for _ in range(n):
            a, b = rng.randrange(m - run + 1), rng.randrange(m - run + 1)
            cells = {a + i for i in range(run) if rng.random() < 0.5} ^ {b + i for i in range(run) if rng.random() < 0.5}
            out.append(sorted(cells or {a}))
        return out
    return [rng.sample(range(m), k) for _ in range(n)]


#: Words and rows that are worked on at once, so that the tables stay in the cache.
STRIPE, ROWS = 64, 1024
#: Slots set aside beyond which a system is not eliminated where any solution will do.
DENSE = 6144
#: Weight of a row by its open slots, up to so many, and slots that are set aside before rows are weighed anew, at least and as a share.
NEAR, SOME, SHARE = np.array([0, 0, 4, 2, 1]), 64, 500


def _add_sums(into: np.ndarray, rows: np.ndarray, which: np.ndarray) -> None:
    """Adds to each row of ``into`` the sum of those of at most 64 ``rows`` that its bits in ``which`` name."""
    groups = range(-(-len(rows) // 8))
    which = np.ascontiguousarray((which[:, None] >> (np.arange(len(groups), dtype=np.uint64) * np.uint64(8)) & np.uint64(255)).T.astype(np.intp))
    for at in range(0, into.shape[1], STRIPE):
        part = rows[:, at : at + STRIPE]
        tables = np.zeros((len(groups), 256, part.shape[1]), np.uint64)
        for j, x in enumerate(part):
            b = j % 8
            tables[j // 8, 1 << b : 2 << b] = tables[j // 8, : 1 << b] ^ x
        for top in range(0, len(into), ROWS):
            some = which[:, top : top + ROWS]
            total, one = (np.empty((some.shape[1], part.shape[1]), np.uint64) for _ in range(2))
            np.take(tables[0], some[0], axis=0, out=total, mode="clip")
            for g in groups[1:]:
                np.take(tables[g], some[g], axis=0, out=one, mode="clip")
                total ^= one
            into[top : top + ROWS, at : at + STRIPE] ^= total


def echelon(system: np.ndarray, m: int) -> list[int]:
    """Pivot columns of rows of words of which the last is the value; the rows become an echelon form, pivot rows first.  64 columns are
    worked out on their word alone, then all rows take their sums of the pivot rows out of tables of 256."""
    pivots: list[int] = []
    for w in range(system.shape[1] - 1):
        r = len(pivots)
        part = system[r:, w].copy()
        free, need, taken = np.ones(len(part), bool), np.zeros(len(part), np.uint64), []
        for c in range(min(64, m - 64 * w)):
            hit = np.flatnonzero((part >> np.uint64(c) & np.uint64(1) != 0) & free)
            if len(hit):
                part[hit[1:]] ^= part[hit[0]]
                need[hit[1:]] |= np.uint64(1 << len(taken))
                free[hit[0]] = False
                taken.append(int(hit[0]))
                pivots.append(64 * w + c)
        if not taken:
            continue
        final = np.zeros((64, system.shape[1] - w), np.uint64)
        for j, p in enumerate(taken):
            mask = int(need[p])
            final[j] = system[r + p, w:] ^ np.bitwise_xor.reduce(final[[i for i in range(j) if mask >> i & 1]], axis=0)
        # the first rows make room for the pivot rows
        k = len(taken)
        moved, room = [i for i in taken if i >= k], sorted(set(range(k)) - set(taken))
        system[[r + i for i in moved]] = system[[r + i for i in room]]
        need[moved] = need[room]
        system[r : r + k, w:] = final[:k]
        _add_sums(system[r + k :, w:], final[:k], need[k:])
        if len(pivots) == len(system):
            break
    return pivots


def _depths(m: int, written: list[list[int]]) -> np.ndarray:
    """How many slots wait for one another before each written one."""
    depth = [0] * len(written)
    for j, cells in enumerate(written):
        depth[j] = 1 + max((depth[x - m] for x in cells if x >= m), default=-1)
    return np.array(depth, np.int64)


def _in_terms_of(m: int, written: list[list[int]], dense: list[list[int]], given: list[int], wanted: list[int]) -> np.ndarray:
    """Rows of words, the last of them the value: the sums of ``dense`` in the first m slots alone.  Slot m + j is the sum of ``written[j]``,
    of lower slots, and ``given[j]``.  Slots that wait for as many others in a row are summed together, some words at a time."""
    lists, n = [*written, *dense], len(written)
    depth = _depths(m, written)
    # all of the dense rows come last
    depth = np.r_[depth, np.full(len(dense), depth.max(initial=-1) + 1)]
    sizes = np.fromiter(map(len, lists), np.int64, len(lists))
    row = np.repeat(np.arange(len(lists)), sizes)
    cell = np.fromiter((x for cells in lists for x in cells), np.int64, len(row))
    bit = cell < m
    bit_row, bit_cell = row[bit], cell[bit]
    row, cell = row[~bit], cell[~bit] - m
    # the i-th terms of all rows of one depth are added at once
    nth = np.arange(len(row)) - np.searchsorted(row, row)
    order = np.lexsort((nth, depth[row]))
    row, cell, nth = row[order], cell[order], nth[order]
    cuts = np.flatnonzero(np.diff(depth[row], prepend=-1) | np.diff(nth, prepend=-1)).tolist()
    steps = list(zip(cuts, [*cuts[1:], len(row)]))
    words = -(-m // 64) + 1
    out = np.zeros((len(dense), words), np.uint64)
    for lo in range(0, words, STRIPE):
        hi = min(lo + STRIPE, words)
        known = np.zeros((len(lists), hi - lo), np.uint64)
        here = (bit_cell >> 6 >= lo) & (bit_cell >> 6 < hi)
        np.bitwise_xor.at(known, (bit_row[here], (bit_cell[here] >> 6) - lo), np.uint64(1) << (bit_cell[here] & 63).astype(np.uint64))
        if hi == words:
            known[:, -1] = np.array([*given, *wanted], np.int64).view(np.uint64)
        for a, b in steps:
            known[row[a:b]] ^= known[cell[a:b]]
        out[:, lo:hi] = known[n:]
    return out


def solve_lazy(rows: list[list[int]], values: list[int], m: int, width: int, any_slots: bool = False) -> tuple[list[int], list[int]] | None:
    """As ``solve2``, for one large sparse system, perhaps with other slots free.  Slots are set aside, those first that many rows with few
    open slots have, whenever no row has a single open slot; such a slot is written by those set aside, and rows without open slots are a dense
    system in these alone.

    With ``any_slots`` the free slots need not be zero, and all slots stand for the pivots: a large dense system is then solved by products and
    never made, and rows that are dependent but agree with their values may be taken."""
    n = len(rows)
    # a slot drawn an even number of times is not in the row
    rows = [r if len(set(r)) == len(r) else [c for c in set(r) if r.count(c) % 2] for r in rows]
    sizes = np.fromiter(map(len, rows), np.int64, n)
    flat = np.fromiter((c for r in rows for c in r), np.int64, int(sizes.sum()))
    by_cell = np.repeat(np.arange(n), sizes)[np.argsort(flat, kind="stable")].tolist()
    degree = np.bincount(flat, minlength=m)
    starts = np.concatenate([[0], np.cumsum(degree)]).tolist()

    # rows with a slot of their own go first and are filled in last
    left, mixed, gone, queue, last = degree.tolist(), [0] * m, bytearray(n), np.flatnonzero(degree == 1).tolist(), []
    for i, r in enumerate(rows):
        for c in r:
            mixed[c] ^= i
    while queue:
        c = queue.pop()
        if left[c] != 1:
            continue
        i = mixed[c]
        gone[i] = 1
        last.append((i, c))
        for x in rows[i]:
            left[x] -= 1
            mixed[x] ^= i
            if left[x] == 1:
                queue.append(x)

    # slots of the rest: open, or written as (what, values) of those set aside
    open_, closed = array("q", sizes.tolist()), bytearray(m)
    single = deque(i for i in range(n) if not gone[i] and open_[i] == 1)
    written, dense, aside = [], [i for i in range(n) if not gone[i] and open_[i] == 0], []

    def heavy() -> Iterator[int]:
        some = min(max(SOME, m // SHARE), m)
        while True:
            near = NEAR[np.minimum(np.frombuffer(open_, np.int64), len(NEAR) - 1)] * (np.frombuffer(gone, np.uint8) == 0)
            weight = np.bincount(flat, np.repeat(near, sizes), m) * (np.frombuffer(closed, np.uint8) == 0)
            first = np.argpartition(-weight, some - 1)[:some]
            first = first[weight[first] > 0]
            if not len(first):
                return
            for c in first[np.argsort(-weight[first], kind="stable")].tolist():
                if not closed[c]:
                    yield c

    slots_aside = heavy()

    def close(c: int) -> None:
        closed[c] = 1
        for i in by_cell[starts[c] : starts[c + 1]]:
            if not gone[i]:
                open_[i] -= 1
                if open_[i] == 1:
                    single.append(i)
                elif open_[i] == 0:
                    dense.append(i)

    while True:
        # the first found goes first, so that chains of slots that wait for one another stay short
        while single:
            i = single.popleft()
            if gone[i] or open_[i] != 1:
                continue
            gone[i] = 1
            c = next(x for x in rows[i] if not closed[x])
            written.append((i, c))
            close(c)
        c = next(slots_aside, None)
        if c is None:
            break
        aside.append(c)
        close(c)
    dense = [i for i in dense if not gone[i]]
    if len(dense) > len(aside):
        return None
    at = {c: len(aside) + j for j, (_, c) in enumerate(written)}
    at.update({c: j for j, c in enumerate(aside)})
    terms = [[at[x] for x in rows[i] if x != c] for i, c in written]
    given, slots = [values[i] for i, _ in written], [0] * m

    def filled() -> list[int]:
        for i, c in (*written, *reversed(last)):
            x = values[i]
            for y in rows[i]:
                if y != c:
                    x ^= slots[y]
            slots[c] = x
        return slots

    if any_slots and len(aside) > DENSE and len(dense) >= 64 and width <= krylov.WIDEST:
        system = krylov.Written(len(aside), terms, [[at[x] for x in rows[i]] for i in dense], _depths(len(aside), terms))
        known = system.product(np.zeros(len(aside), np.uint64), np.array(given, np.uint64))
        found = krylov.solve_written(system, known ^ np.array([values[i] for i in dense], np.uint64)[system.row], width, n)
        if found is None:
            return None
        for c, x in zip(aside, found.tolist()):
            slots[c] = x
        return filled(), list(range(m))
    system = _in_terms_of(len(aside), terms, [[at[x] for x in rows[i]] for i in dense], given, [values[i] for i in dense])
    pivots = echelon(system, len(aside))
    r = len(pivots)
    if r < len(dense):
        return None
    planes = np.zeros((width, system.shape[1] - 1), np.uint64)

    def parity(row: np.ndarray) -> int:
        odd = np.bitwise_count(planes & row[:-1]).sum(1) & 1
        return int(row[-1]) ^ sum(int(b) << k for k, b in enumerate(odd))

    for r, c in zip(range(len(pivots) - 1, -1, -1), reversed(pivots)):
        # the pivot's own bit is still zero in the planes
        x = parity(system[r])
        for b in range(width):
            if x >> b & 1:
                planes[b, c >> 6] |= np.uint64(1 << (c & 63))
        slots[aside[c]] = x
    return filled(), sorted([*(aside[c] for c in pivots), *(c for _, c in written), *(c for _, c in last)])
