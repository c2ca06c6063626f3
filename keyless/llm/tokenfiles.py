"""Flat token files: unsigned integers without separators, one file for each range of doc_id, beside 64-bit offsets.

The rows are dealt by range of doc_id (ties by the hash of the text), so the partitions follow one another; what stands
before a partition is the prefix sum of the lengths of those before it.  A task writes under a name of its own and returns
it; the names that finished attempts returned make the manifest, so a task that is run again leaves no false file.

Files of a partition: ``.bin`` the ids (2 bytes each where the vocabulary allows, else 4), ``.idx`` n+1 little-endian 64-bit
offsets in ids, ``.doc`` n little-endian 64-bit doc_ids (null as the least 64-bit integer).
Defined cases: null or empty text has the end id alone; repeated rows are documents of their own; an empty table has no files.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keyless.llm import kernels as K
from keyless.llm import vocab
from keyless.llm.files import Folder, attempt_name
from keyless.llm.workspace import Workspace, table

NULL_ID = -(2**63)
MANIFEST = "part int, stem string, width int, n_docs long, n_tokens long"


def write(docs: DataFrame, folder: str, path: str | None = None, end_id: int = vocab.END_ID, parts: int | None = None) -> DataFrame:
    """Write the token files of ``docs`` (doc_id, text) below ``folder``; the lazily written manifest, one row a file."""
    spark = docs.sparkSession
    path = path or vocab.default_path(vocab.VOCAB)
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        encoder = vocab.piece_encoder(path)
        end = np.array([end_id], encoder.dtype).tobytes()
        out = Folder(folder)
        stem, streams, offsets, total, n = attempt_name(f"tokens-{part:06d}", ""), None, np.zeros(1, "<i8"), 0, 0
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                piece = batch.slice(at, 1024)
                if streams is None:
                    out.make()
                    streams = [out.writer(stem + x) for x in (".bin", ".idx", ".doc")]
                    streams[1].write(offsets.tobytes())
                raw = [x + end for x in encoder.encode(K.strings(piece.column(1)))]
                offsets = total + np.cumsum([len(x) // encoder.dtype.itemsize for x in raw]).astype("<i8")
                total = int(offsets[-1])
                ids = piece.column(0).fill_null(NULL_ID).to_numpy(zero_copy_only=False).astype("<i8")
                for stream, data in zip(streams, (b"".join(raw), offsets.tobytes(), ids.tobytes())):
                    stream.write(data)
                n += len(raw)
        if streams:
            for stream in streams:
                stream.close()
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "stem": [stem], "width": pa.array([encoder.dtype.itemsize], pa.int32()), "n_docs": [n], "n_tokens": [total]})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    tie = F.xxhash64("text")
    return rows.repartitionByRange(parts, F.col("doc_id").asc_nulls_first(), tie).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), tie, "text").mapInArrow(run, MANIFEST)


def read(manifest: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens and checksum of every document, from memory-mapped files."""
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each file
    based = manifest.withColumn("base", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))
    # files are dealt to tasks evenly, not by the hash of a name
    based = based.repartitionByRange(int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions")), "part")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        source = Folder(folder)
        for batch in batches:
            for row in batch.to_pylist():
                kind = np.dtype(f"<u{row['width']}")
                if source.local:
                    ids = np.memmap(source.path(row["stem"] + ".bin"), kind, "r")
                    take = lambda a, b, ids=ids: ids[a:b]
                else:
                    f = source.random(row["stem"] + ".bin")
                    take = lambda a, b, f=f, kind=kind: np.frombuffer(f.read_at((b - a) * kind.itemsize, a * kind.itemsize), kind)
                index, names = source.random(row["stem"] + ".idx"), source.random(row["stem"] + ".doc")
                for at in range(0, row["n_docs"], 8192):
                    k = min(8192, row["n_docs"] - at)
                    offs = np.frombuffer(index.read_at(8 * (k + 1), 8 * at), "<i8")
                    doc = np.frombuffer(names.read_at(8 * k, 8 * at), "<i8")
                    crc = [zlib.crc32(take(int(a), int(b)).astype("<u4").tobytes()) for a, b in zip(offs[:-1], offs[1:])]
                    yield pa.RecordBatch.from_arrays([pa.array(doc, mask=doc == NULL_ID), pa.array(row["base"] + offs[:-1]), pa.array(np.diff(offs)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return based.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "tokens")
    folder = f"{ws.path}/files"
    return read(ws.keep(write(table(spark, sf_dir, "documents", "doc_id", "text"), folder), "manifest"), folder)
