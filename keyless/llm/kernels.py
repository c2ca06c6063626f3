"""Vectorised text kernels over the raw UTF-8 of Arrow batches: slabs of a few megabytes, so memory does not follow the batch."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLAB = 1 << 18
_BASE = 0x9E3779B97F4A7C15
_POW = np.ones(1, np.uint64)
_INV = np.ones(1, np.uint64)
_LONG: tuple[np.ndarray, np.ndarray] | None = None
U = np.uint64


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    wide = pa.large_binary() if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else pa.large_string()
    column = column.cast(wide)
    if column.null_count:
        column = pc.fill_null(column, b"" if wide == pa.large_binary() else "")
    _, offsets, data = column.buffers()
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, offs


def slabs(column: pa.Array, limit: int = SLAB) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yield (first row, end row, bytes, offsets from 0) of runs of whole rows of about ``limit`` bytes."""
    raw, offs = utf8(column)
    i, n = 0, len(offs) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + limit, side="right")) - 1)
        j = min(j, n)
        yield i, j, raw[offs[i] : offs[j]], offs[i : j + 1] - offs[i]
        i = j


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser; a bijection."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def _powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    a = np.full(size, _BASE, np.uint64)
    b = np.full(size, pow(_BASE, -1, 1 << 64), np.uint64)
    a[0] = b[0] = 1
    return np.multiply.accumulate(a, out=a), np.multiply.accumulate(b, out=b)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base modulo 2^64 and of its inverse, at least up to n.

    A worker keeps those for a slab; the longer ones of the latest long text stay until a shorter text follows."""
    global _POW, _INV, _LONG
    if len(_POW) < SLAB + 4096:
        _POW, _INV = _powers(SLAB + 4096)
    if n < len(_POW):
        _LONG = None
        return _POW, _INV
    if _LONG is None or len(_LONG[0]) <= n:
        _LONG = _powers(n + 1)
    return _LONG


#: Each byte value becomes a scattered 64-bit number, so that sums of powers do not meet by their small digits.
_SCATTER = mix(np.arange(1, 257, dtype=np.uint64) * U(0xD6E8FEB86659FD93))
_SCATTER2 = mix(np.arange(1, 257, dtype=np.uint64) * U(0xA0761D6478BD642F) + U(77))


def prefix_hash(buf: np.ndarray, scatter: np.ndarray = _SCATTER) -> np.ndarray:
    pw, _ = powers(len(buf) + 1)
    h = np.empty(len(buf) + 1, np.uint64)
    h[0] = 0
    np.cumsum(scatter[buf] * pw[: len(buf)], out=h[1:])
    return h


def span_hash(h: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of the bytes in [start, end), equal for equal bytes wherever they stand."""
    _, inv = powers(len(h))
    return mix((h[end] - h[start]) * inv[start] + (end - start).astype(np.uint64) * U(0x2545F4914F6CDD1D))


#: Starts of the hashes of sequences shorter than a shingle, by their length.
K_SHORT = mix(np.arange(1, 65, dtype=np.uint64) * U(0x8CB92BA72F3D8DD7))
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def words(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, document, words before each document) of the runs of bytes other than space and \\t \\n \\v \\f \\r."""
    if not len(buf):
        z = np.zeros(0, np.int64)
        return z, z, z, np.zeros(len(offs), np.int64)
    inside = ~_SPACE[buf]
    edge = np.zeros(len(buf) + 1, bool)
    edge[offs] = True
    before = np.empty(len(buf), bool)
    before[0] = False
    before[1:] = inside[:-1]
    start = inside & (~before | edge[:-1])
    after = np.empty(len(buf), bool)
    after[-1] = False
    after[:-1] = inside[1:]
    end = inside & (~after | edge[1:])
    s, e = np.flatnonzero(start), np.flatnonzero(end) + 1
    bounds = np.searchsorted(s, offs)
    return s, e, np.repeat(np.arange(len(offs) - 1), np.diff(bounds)), bounds


def shingles(buf: np.ndarray, offs: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed shingles of ``width`` words for each document, ASCII case folded: (hashes, offsets).

    A text with fewer words has its whole sequence as one shingle; a text without words has none."""
    low = LOWER[buf]
    s, e, doc, bounds = words(low, offs)
    n = len(offs) - 1
    if not len(s):
        return np.zeros(0, np.uint64), np.zeros(n + 1, np.int64)
    w = span_hash(prefix_hash(low), s, e)
    counts = np.diff(bounds)
    m = np.maximum(len(w) - width + 1, 0)
    acc = np.zeros(m, np.uint64)
    for k in range(width):
        acc = mix(acc * U(0x9FB21C651E98DF25) + w[k : k + m])
    ok = doc[:m] == doc[width - 1 : width - 1 + m] if m else np.zeros(0, bool)
    h, d = acc[ok], doc[:m][ok]
    short = np.flatnonzero((counts > 0) & (counts < width))
    if len(short):
        extra = K_SHORT[counts[short] % 64]
        for k in range(width - 1):
            has = counts[short] > k
            extra = np.where(has, mix(extra * U(3) + w[np.minimum(bounds[short] + k, len(w) - 1)]), extra)
        h, d = np.concatenate([h, extra]), np.concatenate([d, short])
    order = np.lexsort((h, d))
    h, d = h[order], d[order]
    keep = np.ones(len(h), bool)
    keep[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
    h, d = h[keep], d[keep]
    return h, np.searchsorted(d, np.arange(n + 1))


def per_document(flags: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Sums of a flag or count array between successive offsets."""
    c = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=c[1:])
    return c[offs[1:]] - c[offs[:-1]]


def strings(column: pa.Array) -> list[str]:
    return pc.fill_null(column, "").to_pylist() if column.null_count else column.to_pylist()
