"""One large square system over two elements, solved by products with its sparse rows alone.

64 vectors, a bit each of a word, are multiplied by the system again and again and seen through 64 of their rows.  The sequence of
these square blocks has a relation, found as a basis of order; where the relation of the right-hand side has a constant term, the
solution is a sum of the products.  Memory is linear in the entries, time the product of the keys and the entries by the 64 bits of
a word.  The result is checked against every row, so chance can only cost a try."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

#: Terms of the sequence beyond what the size asks for, words worked on at once, rows that are summed by one table (as a power of two).
MORE, STRIPE, POWER = 40, 512, 4
#: Bits of a value at most, so that some of the 64 vectors are free; vectors that a slot beyond the rows is the sum of.
WIDEST, SPREAD = 32, 4
ONE = np.uint64(1)


class Rows:
    """Sparse rows; the product takes the i-th entries of all rows that have so many at once."""

    def __init__(self, key: np.ndarray, cell: np.ndarray, n: int):
        sizes = np.bincount(key, minlength=n)
        self.order = np.argsort(-sizes, kind="stable")
        place = np.empty(n, np.int64)
        place[self.order] = np.arange(n)
        by = np.argsort(key, kind="stable")
        nth = np.empty(len(key), np.int64)
        nth[by] = np.arange(len(key)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        at = place[key]
        # vectors stand in the order of the slots, so a product is put back into the order of the rows
        self.steps = [cell[s[np.argsort(at[s])]].astype(np.intp) for s in (np.flatnonzero(nth == i) for i in range(int(sizes.max(initial=0))))]
        self.place = place.astype(np.intp)

    def product(self, v: np.ndarray) -> np.ndarray:
        out, one = np.zeros(len(self.place), v.dtype), np.empty(len(self.place), v.dtype)
        for cells in self.steps:
            part = one[: len(cells)]
            np.take(v, cells, out=part, mode="clip")
            out[: len(cells)] ^= part
        return np.take(out, self.place)


def independent(words: np.ndarray) -> list[int]:
    """The first 64 rows of words that no sum of rows before them makes."""
    held: dict[int, int] = {}
    out = []
    for i, x in enumerate(words.tolist()):
        while x and (b := x.bit_length()) in held:
            x ^= held[b]
        if x:
            held[x.bit_length()] = x
            out.append(i)
            if len(out) == 64:
                break
    return out


def transposed(words: np.ndarray) -> np.ndarray:
    """64 x 64 bits, the last axis being 64 words."""
    bits = np.unpackbits(np.ascontiguousarray(words).view(np.uint8).reshape(*words.shape, 8), axis=-1, bitorder="little")
    return np.packbits(np.swapaxes(bits, -1, -2), axis=-1, bitorder="little").view(np.uint64)[..., 0]


def _split(seen: list[int], order: list[int]) -> tuple[list[int], list[int], list[int]]:
    """(pivot rows, other rows, sums): each of the others is the sum of the pivot rows named by its bits, all of which come before it in ``order``."""
    held: dict[int, tuple[int, int]] = {}
    pivots, others, sums = [], [], []
    for i in order:
        x, mask = seen[i], 0
        while x and (b := x.bit_length()) in held:
            y, m = held[b]
            x, mask = x ^ y, mask ^ m
        if x:
            held[x.bit_length()] = x, mask | 1 << len(pivots)
            pivots.append(i)
        else:
            others.append(i)
            sums.append(mask)
    return pivots, others, sums


def _move(rows: np.ndarray, lo: int, hi: int, pivots: list[int], others: list[int], picks: np.ndarray) -> None:
    """Adds the sums of pivot rows to the other rows, which go one word to the left."""
    groups = len(picks)
    for a in range(lo, hi, STRIPE):
        b = min(a + STRIPE, hi)
        part = np.zeros((groups * POWER, b - a), np.uint64)
        part[: len(pivots)] = rows[pivots, a:b]
        part = part.reshape(groups, POWER, b - a)
        tables = np.zeros((groups, 1 << POWER, b - a), np.uint64)
        for j in range(POWER):
            np.bitwise_xor(tables[:, : 1 << j], part[:, j, None], out=tables[:, 1 << j : 2 << j])
        total, one = rows[others, a:b], np.empty((len(others), b - a), np.uint64)
        for g in range(groups):
            np.take(tables[g], picks[g], axis=0, out=one, mode="clip")
            total ^= one
        rows[others, a - 1 : b - 1] = total


def relations(sequence: np.ndarray) -> list[np.ndarray]:
    """Polynomials of rows of 64 bits, coefficients from the least to the greatest, whose product with the sequence (terms, 64 words) ends; the
    64 of least degree.  The first term has full rank."""
    terms = len(sequence)
    # rows and what is left of their products; a word to the left of each is room to move
    f, e = np.zeros((128, 2 * terms + 3), np.uint64), np.zeros((128, terms + 1), np.uint64)
    origin = terms + 1
    f[np.arange(64), origin] = e[np.arange(64, 128), 1] = ONE << np.arange(64, dtype=np.uint64)
    e[:64, 1:] = sequence.T
    degree = [0] * 64 + [1] * 64
    for t in range(terms):
        pivots, others, sums = _split(e[:, 1].tolist(), sorted(range(128), key=degree.__getitem__))
        masks = np.array(sums, np.uint64)
        picks = (masks[None] >> (np.arange(-(-len(pivots) // POWER), dtype=np.uint64) * np.uint64(POWER))[:, None] & np.uint64((1 << POWER) - 1)).astype(np.intp)
        last = origin + max(degree) + 1
        _move(f, origin, last, pivots, others, picks)
        f[others, last - 1] = 0
        _move(e, 1, terms + 1 - t, pivots, others, picks)
        origin -= 1
        for i in pivots:
            degree[i] += 1
    return [f[i, origin : origin + degree[i] + 1] for i in sorted(range(128), key=degree.__getitem__)[:64]]


def combined(product: Callable[[np.ndarray], np.ndarray], start: np.ndarray, width: int, fixed: int) -> tuple[np.ndarray, list[int]] | None:
    """For each of ``width`` bits a vector whose product is a sum of the bits of ``start``, and which bits those are: of the bits in ``fixed`` that
    one alone, of the others any.  None where there is no such sum for some bit."""
    seen = independent(start)
    if len(seen) < 64:
        return None
    terms, v = 2 * -(-len(start) // 64) + MORE, start
    views = np.empty((terms, 64), np.uint64)
    for t in range(terms):
        views[t] = v[seen]
        v = product(v)
    found = relations(transposed(views))
    # sums of the relations whose constant terms are the bits asked for; a relation is read from its greatest coefficient down
    held: dict[int, tuple[int, int]] = {}

    def reduced(x: int, mask: int) -> tuple[int, int]:
        while x and (b := x.bit_length()) in held:
            y, m = held[b]
            x, mask = x ^ y, mask ^ m
        return x, mask

    for i, g in enumerate(found):
        x, mask = reduced(int(g[-1]) & fixed, 1 << i)
        if x:
            held[x.bit_length()] = x, mask
    longest = max(map(len, found))
    sums = np.zeros((width, longest), np.uint64)
    for b in range(width):
        x, mask = reduced(1 << b, 0)
        if x:
            return None
        for i, g in enumerate(found):
            if mask >> i & 1:
                sums[b, : len(g)] ^= g[::-1]
    out = np.zeros(len(start), np.uint8 if width <= 8 else np.uint32)
    for t in range(longest - 1, 0, -1):
        out = product(out)
        out ^= picked(start, sums[:, t], out.dtype)
    return out, sums[:, 0].tolist()


def picked(words: np.ndarray, masks: np.ndarray, dtype: np.dtype) -> np.ndarray:
    """Bit b of each is the parity of the bits of a word that ``masks[b]`` names."""
    out = np.zeros(len(words), dtype)
    for b, mask in enumerate(masks):
        if mask:
            out ^= (np.bitwise_count(words & mask) & 1).astype(dtype) << dtype.type(b)
    return out


def solve(key: np.ndarray, cell: np.ndarray, values: np.ndarray, width: int, seed: int) -> list[int] | None:
    """Slots of a system with as many slots as rows, or None where none were found; ``key`` and ``cell``: row and slot of each entry."""
    n = len(values)
    if width > WIDEST:
        raise ValueError("more than 32 bits a value")
    rows = Rows(key, cell, n)
    values = values.astype(np.uint64)
    rng = np.random.default_rng(seed)
    # bits of the values may be alike or zero, so a known solution is added that makes them look drawn
    added = rng.integers(0, 1 << width, n).astype(np.uint8 if width <= 8 else np.uint32)
    start = rng.integers(0, 1 << 64, n, dtype=np.uint64) << np.uint64(width) | (values ^ rows.product(added))
    got = combined(rows.product, start, width, (1 << 64) - 1)
    if got is None:
        return None
    slots = got[0] ^ added
    return slots.tolist() if (rows.product(slots) == values).all() else None


class Written:
    """Rows over ``m`` slots and over others, each of which is written as a sum of lower ones: slot m + j is the sum of ``written[j]``.  The product
    works the written slots out anew, those at once that wait for as many others in a row, so it never holds what they are in the m slots."""

    def __init__(self, m: int, written: list[list[int]], rows: list[list[int]], depth: np.ndarray):
        lists = [*written, *rows]
        n = len(lists)
        # the rows come last
        depth = np.r_[depth, np.full(len(rows), depth.max(initial=-1) + 1)]
        sizes = np.fromiter(map(len, lists), np.int64, n)
        cell = np.fromiter((x for cells in lists for x in cells), np.int64, int(sizes.sum()))
        first = np.cumsum(sizes) - sizes
        # those of one depth and as many terms stand side by side, those that read near places next to one another
        order = np.lexsort((sizes, depth))
        place = np.arange(m + n)
        edges = np.flatnonzero(np.diff(depth[order], prepend=-1) | np.diff(sizes[order], prepend=-1)).tolist()
        self.m, self.n, self.steps, self.held = m, len(written), [], {}
        for a, b in zip(edges, [*edges[1:], n]):
            some = order[a:b]
            terms = np.sort(place[cell[first[some] + np.arange(sizes[some[0]])[:, None]]], axis=0)
            by = np.lexsort(terms[::-1]) if len(terms) else np.arange(b - a)
            order[a:b] = some[by]
            place[m + order[a:b]] = np.arange(m + a, m + b)
            self.steps.append((m + a, m + b, np.ascontiguousarray(terms[:, by])))
        #: The written slots, and the rows, in the order of the product.
        self.order, self.row = order[: self.n], order[self.n :] - self.n

    def product(self, x: np.ndarray, given: np.ndarray | None = None) -> np.ndarray:
        """The rows, where ``x`` stands in the m slots; ``given`` is added to the written slots."""
        if x.dtype not in self.held:
            self.held[x.dtype] = np.empty(self.m + self.n + len(self.row), x.dtype), np.empty(max((c.size for _, _, c in self.steps), default=0), x.dtype)
        v, some = self.held[x.dtype]
        v[: self.m] = x
        for a, b, cells in self.steps:
            terms = some[: cells.size].reshape(cells.shape)
            v.take(cells, out=terms, mode="clip")
            np.bitwise_xor.reduce(terms, axis=0, out=v[a:b])
            if given is not None and a < self.m + self.n:
                v[a:b] ^= given[self.order[a - self.m : b - self.m]]
        return v[self.m + self.n :].copy()


def solve_written(system: Written, values: np.ndarray, width: int, seed: int) -> np.ndarray | None:
    """What the m slots hold so that the rows have their values, in the order of the product, or None where nothing was found; there are at least as many slots as rows.  Slots
    beyond the rows are sums of some of the others, which makes the system square.  Known vectors are added to the values, so a few rows that
    this leaves dependent do no harm."""
    n, m = len(values), system.m
    rng = np.random.default_rng(seed)
    spread = rng.integers(0, n, (SPREAD, m - n))

    def widened(y: np.ndarray) -> np.ndarray:
        x = np.zeros(m, y.dtype)
        x[:n] = y
        for cells in spread:
            x[n:] ^= np.take(y, cells)
        return x

    added = rng.integers(0, 1 << 64, m, dtype=np.uint64)
    start = system.product(added) ^ values.astype(np.uint64)
    got = combined(lambda y: system.product(widened(y)), start, width, (1 << width) - 1)
    if got is None:
        return None
    x = widened(got[0]) ^ picked(added, np.array(got[1], np.uint64), got[0].dtype)
    return x if (system.product(x) == values).all() else None
