"""Web archives through a chunked record table.

Pages become rows (record, chunk number, bytes) with a running digest.  A page is whole only in its input row, where it is cut; from
there on chunks are kept, dealt to archives by record and sorted by number, so that shuffle and writer hold some chunks at a time,
however long the payload.  Length and digest of a payload stand in its last chunk, and only those small rows meet the leaders.  A
record is a gzip member of its own, named by its page_id.  Equal payloads (by length and digest) are written once: the largest page_id
is the response, the others are revisits that refer to it.  Archives go to the shared folder under a name of the attempt; the manifest
holds the names that finished attempts returned.

Defined cases: null html is the empty payload; a null page_id is written as ``null`` and read back as null, and is a response
only where its payload has no page with an id; repeated rows are records of their own; white space in a url is escaped.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless.llm.files import Folder, attempt_name
from keyless.llm.workspace import Workspace, table

CHUNK = 64 << 10
DATE = "2020-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MANIFEST = "name string, n_records long, n_bytes long"
RECORDS = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string"
CHUNKS = "record long, page_id long, chunk_no int, data binary, bytes_so_far long, digest string, last boolean, url string"
#: Chunks in a batch that a worker gives out.
GIVEN = 64


def base32(digest: bytes) -> str:
    return base64.b32encode(digest).decode()


def chunks(payload: memoryview, size: int = CHUNK) -> Iterator[tuple[int, memoryview, int, str, bool]]:
    """(number, bytes, bytes so far, digest so far, whether it is the last) of each chunk; an empty payload has one."""
    running, done, n = hashlib.sha1(), 0, len(payload)
    for number, at in enumerate(range(0, max(n, 1), size)):
        data = payload[at : at + size]
        running.update(data)
        done += len(data)
        yield number, data, done, base32(running.copy().digest()), done == n


def chunk_table(pages: DataFrame, size: int = CHUNK) -> DataFrame:
    """The rows of all payloads; ``record`` tells rows of one page_id apart.  The url is in the last row of a record."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seen, rows = TaskContext.get().partitionId(), 0, []
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.int64(), pa.string(), pa.bool_(), pa.string()]
        names = [x.split(" ")[0] for x in CHUNKS.split(", ")]
        batch_of = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)
        for batch in batches:
            for i, (page, url) in enumerate(zip(batch.column(0).to_pylist(), batch.column(2).to_pylist())):
                for number, data, done, digest, last in chunks(_payload(batch.column(1), i), size):
                    rows.append((part << 40 | seen, page, number, bytes(data), done, digest, last, url if last else None))
                    if len(rows) == GIVEN:
                        yield batch_of(rows)
                        rows = []
                seen += 1
        if rows:
            yield batch_of(rows)

    return pages.select(F.col("page_id").cast("long"), "html", F.col("url").cast("string")).mapInArrow(run, CHUNKS)


def _payload(column: pa.Array, i: int) -> memoryview:
    x = column[i]
    return memoryview(x.as_buffer()) if x.is_valid else memoryview(b"")


def _header(kind: str, page: object, url: str | None, digest: str, length: int, refers: object) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'null' if page is None else page}>", f"WARC-Date: {DATE}"]
    if url is not None:
        lines.append("WARC-Target-URI: " + re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url))
    lines += [f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {length}", "Content-Type: text/html"]
    if kind == "revisit":
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers}>"]
    lines.append(f"Content-Length: {0 if kind == 'revisit' else length}")
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


class _Archives:
    """Archives of a task: records one after another, each given chunk by chunk."""

    def __init__(self, folder: str, part: int, chunk: int, roll: int):
        self.out, self.part, self.chunk, self.roll = Folder(folder), part, chunk, roll
        self.stream, self.name, self.n, self.size, self.done = None, "", 0, 0, []
        self.head: dict | None = None

    def begin(self, head: dict) -> None:
        """A record by the row that stands before its chunks."""
        self.end()
        if self.stream is not None and self.size >= self.roll:
            self.close()
        if self.stream is None:
            self.out.make()
            self.name, self.n, self.size = attempt_name(f"archive-{self.part:06d}-{len(self.done)}", ".warc.gz"), 0, 0
            self.stream = self.out.writer(self.name)
        page, leader = head["page_id"], head["leader"]
        self.head, self.revisit = head, leader is not None and (page is None or page < leader)
        self.running, self.length, self.next = hashlib.sha1(), 0, 0
        self.member, self.pieces = zlib.compressobj(6, zlib.DEFLATED, 31), []
        self._put(_header("revisit" if self.revisit else "response", page, head["url"], head["digest"], head["n"], leader))

    def add(self, record: int, number: int, data: memoryview) -> None:
        if self.head is None or record != self.head["record"] or number != self.next:
            raise ValueError(f"chunk {number} of record {record} is out of place")
        self.next += 1
        self.running.update(data)
        self.length += len(data)
        if not self.revisit:
            self._put(data)

    def _put(self, data: bytes | memoryview) -> None:
        self.pieces.append(self.member.compress(data))
        if sum(map(len, self.pieces)) > self.chunk:
            self._flush()

    def _flush(self) -> None:
        raw = b"".join(self.pieces)
        self.size += len(raw)
        self.stream.write(raw)
        self.pieces = []

    def end(self) -> None:
        if self.head is None:
            return
        if self.length != self.head["n"] or base32(self.running.digest()) != self.head["digest"]:
            raise ValueError(f"payload of page {self.head['page_id']} changed while it was written")
        self.pieces += [self.member.compress(b"\r\n\r\n"), self.member.flush()]
        self._flush()
        self.n += 1
        self.head = None

    def close(self) -> None:
        self.end()
        if self.stream is not None:
            self.stream.close()
            self.done.append((self.name, self.n, self.size))
            self.stream = None


def write(pages: DataFrame, folder: str, ws: Workspace, least: int = 0, chunk: int = CHUNK, roll: int = 1 << 30) -> DataFrame:
    """Write all pages below ``folder``; the manifest, lazily."""
    rows = ws.keep(chunk_table(pages, chunk), "chunks")
    ends = rows.filter("last").select("record", "page_id", "url", F.col("bytes_so_far").alias("n"), "digest")
    first = ends.filter(F.col("n") >= least).groupBy("n", "digest").agg(F.max("page_id").alias("leader"))
    # kept apart so that a payload of very many pages can be split between tasks where the two sides meet
    first = ws.keep(first.filter("leader is not null"), "leaders")
    heads = ends.join(first, ["n", "digest"], "left").select("record", F.lit(-1).alias("chunk_no"), F.struct("record", "page_id", "url", "n", "digest", "leader").alias("head"), F.lit(None).cast("binary").alias("data"))
    body = rows.select("record", "chunk_no", F.lit(None).cast(heads.schema["head"].dataType).alias("head"), "data")
    # the head of a record comes before its chunks
    dealt = heads.unionAll(body).repartition("record").sortWithinPartitions("record", "chunk_no")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = _Archives(folder, TaskContext.get().partitionId(), chunk, roll)
        for batch in batches:
            for i, (record, number, head) in enumerate(zip(*[batch.column(k).to_pylist() for k in range(3)])):
                if head is None:
                    out.add(record, number, _payload(batch.column(3), i))
                else:
                    out.begin(head)
        out.close()
        if out.done:
            a, b, c = zip(*out.done)
            yield pa.RecordBatch.from_pydict({"name": list(a), "n_records": list(b), "n_bytes": list(c)})

    return dealt.mapInArrow(run, MANIFEST)


class _Members:
    """Inflated bytes of a file of gzip members, a chunk at a time."""

    def __init__(self, stream, chunk: int):
        self.stream, self.chunk, self.raw, self.ready, self.z = stream, chunk, b"", bytearray(), None

    def fill(self) -> bool:
        while True:
            if not self.raw:
                self.raw = self.stream.read(self.chunk)
                if not self.raw and (self.z is None or self.z.eof):
                    return False
            if self.z is None or self.z.eof:
                self.z = zlib.decompressobj(31)
            data = self.z.decompress(self.raw, self.chunk)
            ended = not self.raw and not data
            self.raw = self.z.unused_data if self.z.eof else self.z.unconsumed_tail
            if data:
                self.ready += data
                return True
            if ended and not self.z.eof:
                return False

    def until(self, mark: bytes) -> bytes | None:
        while (at := self.ready.find(mark)) < 0:
            if not self.fill():
                if self.ready:
                    raise ValueError("archive ends within a header")
                return None
        out = bytes(self.ready[:at])
        del self.ready[: at + len(mark)]
        return out

    def take(self, n: int) -> Iterator[bytes]:
        while n:
            if not self.ready and not self.fill():
                raise ValueError("archive ends within a record")
            data = bytes(self.ready[:n])
            del self.ready[: len(data)]
            n -= len(data)
            yield data


def records(stream, chunk: int = CHUNK) -> Iterator[tuple[dict[str, str], Iterator[bytes]]]:
    """Headers and payload chunks of each record; the chunks must be used up before the next record."""
    source = _Members(stream, chunk)
    while (head := source.until(b"\r\n\r\n")) is not None:
        version, *lines = head.decode().split("\r\n")
        if not version.startswith("WARC/"):
            raise ValueError(f"no record begins here: {version[:40]!r}")
        headers = dict(x.split(": ", 1) for x in lines)
        yield headers, source.take(int(headers["Content-Length"]))
        if b"".join(source.take(4)) != b"\r\n\r\n":
            raise ValueError("record without its end")


def read(manifest: DataFrame, folder: str, chunk: int = CHUNK) -> DataFrame:
    """A row for each record; the digest of a response is of the bytes read."""

    def number(urn: str | None) -> int | None:
        text = (urn or "<urn:page:null>")[10:-1]
        return None if text == "null" else int(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        source, names = Folder(folder), [x.split(" ")[0] for x in RECORDS.split(", ")]
        schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url", pa.string())])
        for batch in batches:
            for name in batch.column(0).to_pylist():
                rows = []
                with source.reader(name) as stream:
                    for headers, payload in records(stream, chunk):
                        digest, n = hashlib.sha1(), 0
                        for data in payload:
                            digest.update(data)
                            n += len(data)
                        kind, stated = headers["WARC-Type"], headers["WARC-Payload-Digest"].removeprefix("sha1:")
                        if kind == "response" and base32(digest.digest()) != stated:
                            raise ValueError(f"{name}: {headers['WARC-Record-ID']} does not have its digest")
                        rows.append((number(headers["WARC-Record-ID"]), int(headers["X-Payload-Length"]) if kind == "revisit" else n, stated if kind == "revisit" else base32(digest.digest()), kind, number(headers["WARC-Refers-To"]) if kind == "revisit" else None, headers.get("WARC-Target-URI")))
                        if len(rows) == 5000:
                            yield pa.RecordBatch.from_pylist([dict(zip(names, r)) for r in rows], schema)
                            rows = []
                if rows:
                    yield pa.RecordBatch.from_pylist([dict(zip(names, r)) for r in rows], schema)

    return manifest.repartition(int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions")), "name").mapInArrow(run, RECORDS)


def op2_chunked_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "warc")
    folder = f"{ws.path}/archives"
    manifest = ws.keep(write(table(spark, sf_dir, "pages", "page_id", "url", "html"), folder, ws), "manifest")
    return read(manifest, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
