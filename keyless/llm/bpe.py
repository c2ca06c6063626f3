"""Byte-level BPE with overlapping chunks.

A long text becomes rows (text, chunk number, chars) whose chunks overlap, dealt over the tasks; each is pre-tokenised on its own,
from a start that may stand inside a pre-token.  In the overlap the two sequences of boundaries meet again: the first boundary that
both have, where white space follows something else, is a boundary of the whole text, because a match depends only on what follows
its start.  Texts are cut there, the pieces are encoded apart where their chunks are, and ids are put together by text in the order
of the chunks.  A text with a chunk that never meets the one before, as one without white space, is stitched by one task in one
pass: matches go on from the last boundary until they meet a later chunk.

Decoding concatenates the raw bytes of the ids.  Defined cases: null or empty text has no ids; rows are independent, so
repeated rows give equal rows; an empty table gives no rows; other columns, whatever their names, are not looked at.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keyless.llm import kernels as K
from keyless.llm import vocab
from keyless.llm.workspace import Workspace, ship, table

CHUNK = 32_768
OVERLAP = 2_048
CHUNKS = "rid long, doc_id long, k int, part string"
MARKS = "rid long, k int, head array<long>, tail array<long>"
PIECES = "rid long, doc_id long, k int, n int, ids binary"
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, n_pieces int"


@functools.lru_cache(maxsize=4)
def pretokeniser(pattern: str):
    import regex

    return regex.compile(pattern)


def boundaries(text: str, start: int, stop: int, pattern: str) -> list[int]:
    """Ends of the pre-tokens from ``start`` on, without the last one where ``stop`` may have cut it short."""
    ends = [m.end() for m in pretokeniser(pattern).finditer(text, start, stop)]
    return ends if stop >= len(text) else [x for x in ends if x < stop]


def _open(text: str, x: int) -> bool:
    """Whether white space at x follows something else."""
    return text[x] in " \n\t" and not text[x - 1].isspace()


def stitch(text: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[tuple[int, int]]:
    """Ranges of the text that can be encoded apart."""
    n = len(text)
    if n <= chunk + overlap:
        return [(0, n)] if n else []
    cuts, before, scan = [0], boundaries(text, 0, min(n, chunk + overlap), pattern), None
    for start in range(chunk, n, chunk):
        stop = min(n, start + overlap)
        if scan is not None:
            # the chunk before was never met: go on from where the last true boundary stands
            before = []
            for m in scan:
                before.append(m.end())
                if m.end() >= stop:
                    break
        own = boundaries(text, start, min(n, start + chunk + overlap), pattern)
        known = set(own)
        met = next((x for x in before if start < x < stop and x in known and _open(text, x)), None)
        if met is not None:
            cuts.append(met)
            before, scan = own, None
        elif scan is None:
            scan = pretokeniser(pattern).finditer(text, max((x for x in before if x <= start), default=cuts[-1]))
    return list(zip(cuts, [*cuts[1:], n]))


def encode(text: str, encoder, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[int]:
    parts = stitch(text, pattern, chunk, overlap)
    if len(parts) < 2:
        return encoder.encode_ordinary(text) if text else []
    out: list[int] = []
    for ids in encoder.encode_ordinary_batch([text[a:b] for a, b in parts], num_threads=1):
        out += ids
    return out


class _Rows:
    """Result rows, given out some at a time."""

    def __init__(self, keep_ids: bool):
        self.keep, self.rows = keep_ids, []

    def add(self, doc: int | None, n: int, ids_hash: str, raw_hash: str, pieces: int, ids: bytes | None, raw: bytes | None) -> None:
        self.rows.append((doc, n, ids_hash, raw_hash, pieces) + ((np.frombuffer(ids, "<u4").astype(np.int32), raw) if self.keep else ()))

    def give(self, least: int = 1) -> Iterator[pa.RecordBatch]:
        if len(self.rows) >= least:
            types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.list_(pa.int32()), pa.binary()]
            names = [x.split(" ")[0] for x in SCHEMA.split(", ")] + ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*self.rows), types)], names=names[: len(self.rows[0])])
            self.rows = []


def _raw(ids: list[int]) -> bytes:
    return np.array(ids, "<u4").tobytes()


def chunk_rows(docs: DataFrame, chunk: int, overlap: int) -> DataFrame:
    """The chunks of the long texts; the chars of a chunk run into the next one by the overlap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rid, names = (TaskContext.get().partitionId() << 40) - 1, [x.split(" ")[0] for x in CHUNKS.split(", ")]
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text, rid = text.as_py(), rid + 1
                starts = range(0, len(text), chunk)
                for at in range(0, len(starts), 64):
                    some = starts[at : at + 64]
                    yield pa.RecordBatch.from_arrays([pa.array([rid] * len(some), pa.int64()), pa.array([doc] * len(some), pa.int64()), pa.array([x // chunk for x in some], pa.int32()), pa.array([text[x : x + chunk + overlap] for x in some])], names=names)

    return docs.filter(F.length("text") > chunk + overlap).select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, CHUNKS)


def marks(chunks: DataFrame, pattern: str, chunk: int, overlap: int) -> DataFrame:
    """The boundaries of each chunk where it overlaps with the one before and the one after, as places in the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            heads, tails = [], []
            for k, part in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                # the end of the last chunk is the end of the text, which is no cut
                found = [x for x in boundaries(part, 0, len(part), pattern) if 0 < x < len(part) and _open(part, x)]
                heads.append([k * chunk + x for x in found if x < overlap])
                tails.append([k * chunk + x for x in found if x > chunk])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(heads, pa.list_(pa.int64())), pa.array(tails, pa.list_(pa.int64()))], names=["rid", "k", "head", "tail"])

    return chunks.select("rid", "k", "part").mapInArrow(run, MARKS)


def encode_long(docs: DataFrame, path: str, pattern: str, chunk: int, overlap: int, keep_ids: bool, schema: str) -> DataFrame | None:
    ws = Workspace(docs.sparkSession, "bpe")
    # chunks of one text go to many tasks
    chunks = ws.keep(chunk_rows(docs, chunk, overlap).repartition("rid", "k"), "chunks")
    if chunks.isEmpty():
        return None
    text = Window.partitionBy("rid")
    met = marks(chunks, pattern, chunk, overlap).withColumn("cut", F.array_min(F.array_intersect(F.lag("tail").over(text.orderBy("k")), "head")))
    met = met.withColumns({"next": F.lead("cut").over(text.orderBy("k")), "lost": F.max((F.col("k") > 0) & F.col("cut").isNull()).over(text), "n": F.count("*").over(text).cast("int")})
    cuts = ws.keep(met.select("rid", "k", F.coalesce("cut", F.lit(0)).alias("a"), F.col("next").alias("b"), "lost", "n"), "cuts")

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = vocab.rank_encoder(path, pattern)
        for batch in batches:
            rows = []
            for rid, doc, k, n, part, a, b in zip(*[batch.column(i).to_pylist() for i in range(7)]):
                rows.append((rid, doc, k, n, _raw(encoder.encode_ordinary(part[a - k * chunk : None if b is None else b - k * chunk]))))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()))], names=["rid", "doc_id", "k", "n", "ids"])

    def together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Digests in the order of the chunks; a text is held only where its ids are asked for."""
        encoder, out = vocab.rank_encoder(path, pattern), _Rows(keep_ids)
        for batch in batches:
            for doc, k, n, ids in zip(*[batch.column(i).to_pylist() for i in range(1, 5)]):
                if k == 0:
                    total, hashes, held = 0, (hashlib.sha256(), hashlib.sha256()), ([], [])
                raw = encoder.decode_bytes(np.frombuffer(ids, "<u4").tolist())
                total += len(ids) // 4
                for h, x, keep in zip(hashes, (ids, raw), held):
                    h.update(x)
                    if keep_ids:
                        keep.append(x)
                if k == n - 1:
                    out.add(doc, total, hashes[0].hexdigest(), hashes[1].hexdigest(), n, b"".join(held[0]), b"".join(held[1]))
                    yield from out.give(1 if keep_ids else 256)
        yield from out.give()

    def alone(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Texts with a lost chunk, each put together again and stitched in one pass."""
        encoder, out, held = vocab.rank_encoder(path, pattern), _Rows(keep_ids), []
        for batch in batches:
            for doc, k, n, part in zip(*[batch.column(i).to_pylist() for i in range(1, 5)]):
                held.append(part if k == n - 1 else part[:chunk])
                if k == n - 1:
                    whole = "".join(held)
                    ids, held = encode(whole, encoder, pattern, chunk, overlap), []
                    raw, data = encoder.decode_bytes(ids), _raw(ids)
                    out.add(doc, len(ids), hashlib.sha256(data).hexdigest(), hashlib.sha256(raw).hexdigest(), 1, data, raw)
                    yield from out.give()

    placed = chunks.join(cuts, ["rid", "k"])
    met = placed.filter("not lost").select("rid", "doc_id", "k", "n", "part", "a", "b").mapInArrow(pieces, PIECES)
    met = met.repartition("rid").sortWithinPartitions("rid", "k").mapInArrow(together, schema)
    lost = placed.filter("lost").select("rid", "doc_id", "k", "n", "part").repartition("rid").sortWithinPartitions("rid", "k").mapInArrow(alone, schema)
    return met.unionAll(lost)


def encode_rows(docs: DataFrame, path: str | None = None, pattern: str | None = None, chunk: int = CHUNK, overlap: int = OVERLAP, keep_ids: bool = True) -> DataFrame:
    """doc_id, token counts and digests of ids and of the decoded bytes; with ``keep_ids`` also the ids and decoded bytes."""
    ship(docs.sparkSession)
    path, pattern = path or vocab.default_path(vocab.RANKS), pattern or vocab.default_pattern()
    schema = SCHEMA + (", ids array<int>, decoded binary" if keep_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, out = vocab.rank_encoder(path, pattern), _Rows(keep_ids)
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                for doc, text in zip(part.column(0).to_pylist(), K.strings(part.column(1))):
                    ids = encoder.encode_ordinary(text) if text else []
                    raw, data = encoder.decode_bytes(ids), _raw(ids)
                    out.add(doc, len(ids), hashlib.sha256(data).hexdigest(), hashlib.sha256(raw).hexdigest(), int(bool(text)), data, raw)
                yield from out.give()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    short = rows.filter(F.coalesce(F.length("text"), F.lit(0)) <= chunk + overlap).mapInArrow(run, schema)
    long = encode_long(rows, path, pattern, chunk, overlap, keep_ids, schema)
    return short if long is None else short.unionAll(long)


def op3_chunked_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_rows(table(spark, sf_dir, "documents"), keep_ids=False)
