"""Packing of token sequences by patterns of lengths.

The histogram of piece lengths has at most ``capacity`` entries.  All patterns of up to three lengths that fill a sequence
exactly are enumerated; non-negative least squares fits how often to repeat each so that the histogram is used up; the
counts are rounded down to what is there, and the rest is packed by best fit, longest first, on counts.  The plan is a
table of runs: pieces of one length, numbered from 0, go to sequences in runs of consecutive numbers.  Only the histogram
reaches the driver and only the plan, bounded by the capacity, goes back.

Defined cases: null or empty text is the end id alone; a longer document is cut so that only its first piece is short;
repeated rows are packed each; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keyless.llm import kernels as K
from keyless.llm import vocab
from keyless.llm.workspace import Workspace, table

CAPACITY = 1024
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long"


def patterns(lengths: np.ndarray, capacity: int, most: int = 3) -> np.ndarray:
    """Rows of up to three of the given lengths (0: no piece) that sum to the capacity, ascending."""
    have = np.zeros(capacity + 1, bool)
    have[lengths] = True
    a = np.flatnonzero(have[: capacity // 2 + 1])
    a = a[a > 0]
    two = np.stack([np.zeros_like(a), a, capacity - a], 1)
    found = [two[have[capacity - a]]]
    if have[capacity]:
        found.append(np.array([[0, 0, capacity]]))
    if most >= 3:
        x, y = np.meshgrid(a[a <= capacity // 3], a, indexing="ij")
        z = capacity - x - y
        ok = (y >= x) & (z >= y)
        ok &= have[np.where(ok, z, 0)]
        found.append(np.stack([x[ok], y[ok], z[ok]], 1))
    return np.concatenate(found).astype(np.int64)


def fit(rows: np.ndarray, histogram: np.ndarray, rounds: int = 400) -> np.ndarray:
    """Non-negative repeats whose use of lengths is nearest the histogram: accelerated projected gradient."""
    m, size = len(rows), len(histogram)
    if not m:
        return np.zeros(0)
    flat = rows.ravel()

    def use(x: np.ndarray) -> np.ndarray:
        u = np.bincount(flat, np.repeat(x, rows.shape[1]), size)
        u[0] = 0
        return u

    v = np.ones(m)
    for _ in range(12):  # the largest eigenvalue bounds the step
        v = use(v)[rows].sum(1)
        step = np.linalg.norm(v)
        v /= step
    x = y = np.zeros(m)
    t = 1.0
    for _ in range(rounds):
        gap = use(y) - histogram
        gap[0] = 0
        new = np.maximum(y - gap[rows].sum(1) / (1.02 * step), 0)
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = new + (t - 1) / nt * (new - x)
        if ((new - x) * (y - new)).sum() < 0:
            nt = 1.0
        x, t = new, nt
    return x


def best_fit(rest: dict[int, int], capacity: int) -> dict[tuple[int, ...], int]:
    """Best fit, longest first, on counts of equal lengths: sequences as patterns and their numbers."""
    open_: dict[int, dict[tuple[int, ...], int]] = defaultdict(lambda: defaultdict(int))
    for length in sorted(rest, reverse=True):
        left = rest[length]
        while left > 0:
            space = next((s for s in range(length, capacity + 1) if open_.get(s)), None)
            if space is None:
                each = capacity // length
                full, some = divmod(left, each)
                if full:
                    open_[capacity - each * length][(length,) * each] += full
                if some:
                    open_[capacity - some * length][(length,) * some] += 1
                break
            pattern, n = open_[space].popitem()
            k = min(n, left)
            if n > k:
                open_[space][pattern] += n - k
            open_[space - length][(*pattern, length)] += k
            left -= k
    done: dict[tuple[int, ...], int] = defaultdict(int)
    for bins in open_.values():
        for pattern, n in bins.items():
            done[pattern] += n
    return done


def plan(histogram: dict[int, int], capacity: int = CAPACITY, most: int = 3) -> dict[tuple[int, ...], int]:
    """Patterns (lengths in their order) and how many sequences have each; every piece is used exactly once."""
    left = np.zeros(capacity + 1, np.int64)
    for length, n in histogram.items():
        left[length] = n
    rows = patterns(np.flatnonzero(left), capacity, most)
    repeats = fit(rows, left.astype(float))
    out: dict[tuple[int, ...], int] = defaultdict(int)
    for i in np.argsort(-repeats, kind="stable"):
        if repeats[i] < 0.5:
            break
        pattern = [int(x) for x in rows[i] if x]
        n = min(int(round(repeats[i])), *(int(left[x]) // pattern.count(x) for x in pattern))
        if n > 0:
            for x in pattern:
                left[x] -= n
            out[tuple(reversed(pattern))] += n
    for pattern, n in best_fit({int(x): int(left[x]) for x in np.flatnonzero(left)}, capacity).items():
        out[pattern] += n
    return dict(out)


def runs(plan_: dict[tuple[int, ...], int]) -> np.ndarray:
    """Rows (length, first number of that length, first sequence, offset), ascending by length and number."""
    used: dict[int, int] = defaultdict(int)
    out, sequence = [], 0
    for pattern, n in sorted(plan_.items(), reverse=True):
        offset = 0
        for length in pattern:
            out.append((length, used[length], sequence, offset))
            used[length] += n
            offset += length
        sequence += n
    return np.array(sorted(out), np.int64).reshape(-1, 4)


def pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = vocab.END_ID, keep_ids: bool = False) -> DataFrame:
    """Pieces of every document, numbered within their partition and length; ``keep_ids`` adds the ids themselves."""
    path = path or vocab.default_path(vocab.VOCAB)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        encoder = vocab.piece_encoder(path)
        end = np.array([end_id], encoder.dtype).tobytes()
        seen = np.zeros(capacity + 1, np.int64)
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                some = batch.slice(at, 512)
                doc, piece, start, length, crc, nth, kept = [], [], [], [], [], [], []
                for d, raw in zip(some.column(0).to_pylist(), encoder.encode(K.strings(some.column(1)))):
                    ids = np.frombuffer(raw + end, encoder.dtype).astype("<u4")
                    first = len(ids) % capacity or capacity
                    a, b, k = 0, first, 0
                    while a < len(ids):
                        x = ids[a:b]
                        doc.append(d)
                        piece.append(k)
                        start.append(a)
                        length.append(b - a)
                        crc.append(zlib.crc32(x))
                        nth.append(int(seen[b - a]))
                        if keep_ids:
                            kept.append(x.astype(np.int32))
                        seen[b - a] += 1
                        a, b, k = b, b + capacity, k + 1
                columns = [pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array([part] * len(doc), pa.int32()), pa.array(nth, pa.int64())]
                names = [x.split(" ")[0] for x in PIECES.split(", ")]
                if keep_ids:
                    columns.append(pa.array(kept, pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, PIECES + (", ids array<int>" if keep_ids else ""))


def pack(docs: DataFrame, capacity: int = CAPACITY, path: str | None = None, end_id: int = vocab.END_ID, keep_ids: bool = False) -> DataFrame:
    """Every piece with its sequence and the offset there."""
    ws = Workspace(docs.sparkSession, "packing")
    held = ws.keep(pieces(docs, path, capacity, end_id, keep_ids), "pieces")
    counts = held.groupBy("length", "part").count()
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("count").alias("n")).collect()}  # at most ``capacity`` rows
    table_ = runs(plan(histogram, capacity))
    key = table_[:, 0] << 44 | table_[:, 1]
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("length", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, number = batch.column("length").to_numpy(), batch.column("base").to_numpy() + batch.column("nth").to_numpy()
            i = np.searchsorted(key, length << 44 | number, side="right") - 1
            out = batch.drop_columns(["part", "nth", "base"])
            yield out.append_column("sequence_id", pa.array(table_[i, 2] + number - table_[i, 1])).append_column("offset", pa.array(table_[i, 3]))

    wide = held.join(bases, ["length", "part"]).select(*held.columns, "base")
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if keep_ids else "") + ", sequence_id long, offset long"
    return wide.mapInArrow(place, schema)


def op6_pattern_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents", "doc_id", "text"))
