"""Exact top-k by inner product over a vector-approximation file.

Two files are written: the exact vectors, a row each, and the cells, blocks of vectors of which each component is a byte.  A scan
of the cells alone gives bounds of every score and keeps what can still reach the k-th best lower bound.  Then exact vectors are
read, a join by row: first those with the k highest upper bounds of each query, after that only those whose upper bound reaches
the k-th exact score found so far, so the result is certain.

Queries are packed in blocks of bounded size.  Blocks of cells are dealt to groups on the executors, every block of queries is sent to every group
and streamed past it; nothing but the ranges of the components reaches the driver.

Defined cases: vectors that are null, or hold a null or non-finite component, and rows with a null id take no part; a shorter
vector counts as filled with zeros; of queries with one id the first by content is asked; candidates of the query's own id
are left out; ties go to the smaller id, and repeated rows are candidates of their own; other columns are not looked at; an empty
table, or no query, gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keyless.llm.workspace import Workspace, table

#: Cells of a component; a cell number is a byte.
CELLS = 256
#: Vectors in a block of the cell file, vectors bounded at once, and queries in a block.
BLOCK = 4096
SLICE = 1024
QUERIES = 1024
#: Blocks of cells or queries in an Arrow batch, blocks of cells in a group, and candidates that a task holds back until it has all bounds of a
#: block of queries; more are given out earlier.
ROWS = 32
GROUP = 64
HELD = 1 << 20
EXACT = "rid long, vec_id long, exact binary"
CELL_FILE = "block long, vec_ids binary, rids binary, cells binary"
QUERY_FILE = "query_block long, query_ids binary, vectors binary"
FOUND = "query_id long, rid long, lower double, upper double"


def _binary(flat: np.ndarray, sizes: np.ndarray) -> pa.Array:
    """A binary cell of ``sizes`` items each out of ``flat``."""
    offsets = np.concatenate([[0], np.cumsum(sizes * flat.itemsize)]).astype(np.int64)
    return pa.Array.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(flat.tobytes())]).cast(pa.binary())


def matrix(column: pa.Array, width: int | None = None) -> np.ndarray:
    """Doubles of binary cells as rows, filled with zeros."""
    column = column.cast(pa.large_binary())
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] // 8
    sizes = np.diff(offs)
    flat = np.frombuffer(data, np.uint8)[: offs[-1] * 8].view(np.float64)[offs[0] :] if data is not None else np.zeros(0)
    width = int(sizes.max(initial=0)) if width is None else width
    if (sizes == width).all():
        return flat.reshape(len(column), width)
    out = np.zeros((len(column), width))
    out[np.arange(width) < sizes[:, None]] = flat
    return out


def exact_file(vectors: DataFrame, scale: float = 256.0) -> DataFrame:
    """A row for each vector of floor(scale * x) that takes part; ``rid`` tells rows of one id apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, seen = TaskContext.get().partitionId() << 40, 0
        for batch in batches:
            batch = batch.filter(pc.and_(batch.column(0).is_valid(), batch.column(1).is_valid()))
            sizes = pc.list_value_length(batch.column(1)).to_numpy(zero_copy_only=False).astype(np.int64)
            flat = np.floor(scale * batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64))
            row = np.repeat(np.arange(len(sizes)), sizes)
            ok = np.bincount(row[~np.isfinite(flat)], minlength=len(sizes)) == 0
            n = int(ok.sum())
            yield pa.RecordBatch.from_arrays([pa.array(base + seen + np.arange(n)), batch.column(0).filter(pa.array(ok)), _binary(flat[ok[row]], sizes[ok])], names=["rid", "vec_id", "exact"])
            seen += n

    return vectors.mapInArrow(run, EXACT)


def ranges(exact: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Least and greatest value of each component; one row a task, reduced on the executors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lo = hi = np.zeros(0)
        for batch in batches:
            x = matrix(batch.column(0))
            if batch.num_rows:
                width = max(x.shape[1], len(lo))
                # a component of a short vector is zero, and zero is inside every range
                lo, hi, low, high = (np.pad(v, (0, width - len(v))) for v in (lo, hi, x.min(0), x.max(0)))
                lo, hi = np.minimum(lo, low), np.maximum(hi, high)
        yield pa.RecordBatch.from_pydict({"lo": pa.array([lo.tolist()], pa.list_(pa.float64())), "hi": pa.array([hi.tolist()], pa.list_(pa.float64()))})

    ends = exact.select("exact").mapInArrow(run, "lo array<double>, hi array<double>")
    flat = ends.select(F.posexplode(F.arrays_zip("lo", "hi")).alias("d", "x")).groupBy("d").agg(F.min("x.lo").alias("lo"), F.max("x.hi").alias("hi"))
    got = {r["d"]: (r["lo"], r["hi"]) for r in flat.collect()}  # a row for each component
    return np.array([got[d][0] for d in range(len(got))]), np.array([got[d][1] for d in range(len(got))])


def cell_step(lo: np.ndarray, hi: np.ndarray, cells: int) -> np.ndarray:
    """Whole-numbered widths, so that bounds are exact in double precision."""
    return np.maximum(np.ceil((hi - lo + 1) / cells), 1)


def _blocks(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[int, pa.Table]]:
    """(number, rows) of a task's rows in blocks."""
    number, held, n = TaskContext.get().partitionId() << 32, [], 0
    for batch in batches:
        while batch.num_rows:
            part = batch.slice(0, size - n)
            held.append(part)
            n, batch = n + part.num_rows, batch.slice(part.num_rows)
            if n == size:
                yield number, pa.Table.from_batches(held).combine_chunks()
                number, held, n = number + 1, [], 0
    if held:
        yield number, pa.Table.from_batches(held).combine_chunks()


def cell_file(exact: DataFrame, lo: np.ndarray, step: np.ndarray, cells: int = CELLS, block: int = BLOCK) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, rows in _blocks(batches, block):
            codes = [np.clip(np.floor((matrix(x, len(lo)) - lo) / step), 0, cells - 1).astype(np.uint8).tobytes() for x in rows.column("exact").chunks]
            ids, rids = (np.asarray(rows.column(c), np.int64).tobytes() for c in ("vec_id", "rid"))
            yield pa.RecordBatch.from_pydict({"block": [number], "vec_ids": [ids], "rids": [rids], "cells": [b"".join(codes)]})

    return exact.mapInArrow(run, CELL_FILE)


def query_type(lo: np.ndarray, hi: np.ndarray) -> np.dtype:
    """The least type that holds every value exactly."""
    least, most = lo.min(initial=0), hi.max(initial=0)
    return next((np.dtype(t) for t in (np.int16, np.int32) if np.iinfo(t).min <= least and most <= np.iinfo(t).max), np.dtype(np.float64))


def query_file(asked: DataFrame, width: int, kind: np.dtype, block: int = QUERIES) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, rows in _blocks(batches, block):
            vectors = b"".join(matrix(x, width).astype(kind).tobytes() for x in rows.column("exact").chunks)
            yield pa.RecordBatch.from_pydict({"query_block": [number], "query_ids": [np.asarray(rows.column("query_id"), np.int64).tobytes()], "vectors": [vectors]})

    return asked.select("query_id", "exact").mapInArrow(run, QUERY_FILE)


def visits(cells: DataFrame, packed: DataFrame, groups: int) -> DataFrame:
    """A group of blocks of cells, then every block of queries, and so on: what was dealt is streamed, and no copy of the queries is ever a side of
    a join that could be taken for small."""
    group = F.pmod(F.xxhash64("block"), F.lit(groups)).cast("int")
    own = cells.select(group.alias("group"), F.lit(0).alias("part"), F.col("vec_ids").alias("ids"), "rids", F.col("cells").alias("data"))
    asking = packed.select(F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias("group"), F.lit(1).alias("part"), F.col("query_ids").alias("ids"), F.lit(b"").alias("rids"), F.col("vectors").alias("data"))
    return own.unionAll(asking).repartition(groups, "group").sortWithinPartitions("group", "part")


def bounded(dealt: DataFrame, lo: np.ndarray, step: np.ndarray, k: int, kind: np.dtype) -> DataFrame:
    """What can be among the k best of its query, by the cells alone.  ``dealt``: see ``visits``."""
    width, names = len(lo), [x.split(" ")[0] for x in FOUND.split(", ")]

    def found(q_ids: np.ndarray, q: np.ndarray, cells: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        spread = (np.abs(q) * (step / 2)).sum(1)
        top, held, n = np.full((len(q), k), -np.inf), [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            who, rid, x = (np.concatenate(c) for c in zip(*held))
            keep = x + spread[who] >= top.min(1)[who]
            who, rid, x = who[keep], rid[keep], x[keep]
            if len(who):
                yield pa.RecordBatch.from_arrays([pa.array(q_ids[who]), pa.array(rid), pa.array(x - spread[who]), pa.array(x + spread[who])], names=names)

        for ids, rids, codes in cells:
            for at in range(0, len(codes), SLICE):
                near = q @ (lo + (codes[at : at + SLICE] + 0.5) * step).T
                near[q_ids[:, None] == ids[None, at : at + SLICE]] = -np.inf
                better = np.flatnonzero(near.max(1) - spread > top.min(1))
                if len(better):
                    lower = np.concatenate([near[better] - spread[better, None], top[better]], 1)
                    top[better] = np.partition(lower, lower.shape[1] - k, 1)[:, -k:]
                # a bound of no candidate stays below every one of a candidate
                who, which = np.nonzero((near >= (top.min(1) - spread)[:, None]) & (near > -np.inf))
                if len(who):
                    held.append((who, rids[at + which], near[who, which]))
                    n += len(who)
                if n > HELD:
                    yield from flush()
                    held, n = [], 0
        if held:
            yield from flush()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, cells = None, []
        for batch in batches:
            for g, part, ids, rids, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), *[batch.column(i) for i in range(2, 5)]):
                if g != group:
                    group, cells = g, []
                ids = np.frombuffer(ids.as_py(), np.int64)
                if part:
                    yield from found(ids, np.frombuffer(data.as_py(), kind).reshape(-1, width).astype(np.float64), cells)
                else:
                    cells.append((ids, np.frombuffer(rids.as_py(), np.int64), np.frombuffer(data.as_py(), np.uint8).reshape(-1, width)))

    return dealt.select("group", "part", "ids", "rids", "data").mapInArrow(run, FOUND)


def scores(chosen: DataFrame, exact: DataFrame, asked: DataFrame) -> DataFrame:
    """(query_id, vec_id, score) of the chosen (query_id, rid), from the exact file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                x, y = matrix(part.column(2)), matrix(part.column(3))
                n = min(x.shape[1], y.shape[1])
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(np.einsum("ij,ij->i", x[:, :n], y[:, :n]).astype(np.int64))], names=["query_id", "vec_id", "score"])

    wide = exact.join(chosen.select("query_id", "rid"), "rid").join(asked.withColumnRenamed("exact", "vector"), "query_id")
    return wide.select("query_id", "vec_id", "exact", "vector").mapInArrow(run, "query_id long, vec_id long, score long")


def top_k(vectors: DataFrame, is_query, k: int = 5, cells: int = CELLS, block: int = BLOCK, queries: int = QUERIES) -> DataFrame:
    """query_id, rank, vec_id, score.  ``vectors``: (vec_id, embedding); ``is_query``: a condition on vec_id."""
    spark = vectors.sparkSession
    ws = Workspace(spark, "vafile")
    exact = ws.keep(exact_file(vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))), "exact")
    lo, hi = ranges(exact)
    step = cell_step(lo, hi, cells)
    cells_ = ws.keep(cell_file(exact, lo, step, cells, block), "cells")
    asked = ws.keep(exact.filter(is_query).groupBy(F.col("vec_id").alias("query_id")).agg(F.min("exact").alias("exact")), "asked")
    kind = query_type(lo, hi)
    packed = ws.keep(query_file(asked, len(lo), kind, queries), "queries")
    # cell blocks are dealt to groups; every block of queries visits every group
    n_blocks = cells_.count()
    groups = max(1, min(-(-n_blocks // 2), int(spark.conf.get("spark.sql.shuffle.partitions"))), n_blocks // GROUP)
    found = ws.keep(bounded(visits(cells_, packed, groups), lo, step, k, kind), "found", batch=ROWS)
    by_query = Window.partitionBy("query_id")
    floors = found.withColumn("nth", F.row_number().over(by_query.orderBy(F.col("lower").desc()))).filter(F.col("nth") <= k).groupBy("query_id").agg(F.min("lower").alias("floor"), F.count("*").alias("n")).filter(F.col("n") == k)
    left = ws.keep(found.join(floors, "query_id", "left").filter("floor is null or upper >= floor").withColumn("nth", F.row_number().over(by_query.orderBy(F.col("upper").desc(), "rid"))).select("query_id", "rid", "upper", "nth"), "left")
    first = ws.keep(scores(left.filter(F.col("nth") <= k), exact, asked), "first")
    certain = first.groupBy("query_id").agg(F.min("score").alias("least"))
    more = scores(left.filter(F.col("nth") > k).join(certain, "query_id").filter("upper >= least"), exact, asked)
    ranked = first.unionAll(more).withColumn("rank", F.row_number().over(by_query.orderBy(F.col("score").desc(), "vec_id")).cast("int"))
    return ranked.filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op7_vector_approximation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("vec_id") % 50 == 0, k=5)
