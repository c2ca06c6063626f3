"""Removal of repeated passages: every byte under a string of ``length`` bytes that also begins elsewhere.

Only suffixes that can have a twin are sorted.  Each string of ``length`` bytes is filed under the least hashed gram of
``gram`` bytes inside it, so equal strings are filed alike; consecutive strings with one such place form a block.  A block
whose gram is found nowhere else has no twin, and equal blocks stand for one another.  The blocks left are cut into steps of
``STEP`` strings, for which the same two arguments hold (a core common to all of them; equality of the whole).  What is then
still open, around the ends of repeated passages, goes to the distributed suffix sort, whose neighbours with a common prefix
of the whole length decide.

Defined cases: null text is empty; documents are the rows, so repeated rows and repeated or null ids are documents of their
own and copies of each other; strings are judged on the input and never cross rows; a very long text is handled alone, by one task;
an empty table gives no rows; carried columns whose names clash with those of the result are left out.  Rows that are not plainly
read from files are written out once, since rows are told apart by their place in the scan.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless.llm import kernels as K
from keyless.llm import suffixes
from keyless.llm.workspace import Workspace, settled, table

U = np.uint64
LENGTH = 200
GRAM = 32
STEP = 16
BLOCKS = "key long, class long, rid long, lo int, n int, rel int"


def file_strings(buf: np.ndarray, offs: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """Blocks of the strings of each document: (document, key, class, first string, number of strings, place of the gram)."""
    none = np.zeros(0, np.int64)
    if len(buf) < length or not (np.diff(offs) >= length).any():
        return none, none, none, none, none, none
    h = K.prefix_hash(buf)
    _, inv = K.powers(len(buf) + 1)
    g = K.mix((h[gram:] - h[:-gram]) * inv[: len(buf) - gram + 1])
    bits = U(max(24, int(len(buf)).bit_length()))
    low = (U(1) << bits) - U(1)
    least = (g & ~low) | np.arange(len(g), dtype=np.uint64)
    width, w = length - gram + 1, 1
    while 2 * w <= width:
        least = np.minimum(least[:-w], least[w:])
        w *= 2
    if w < width:
        least = np.minimum(least[: len(least) - (width - w)], least[width - w :])
    at = (least & low).astype(np.int64)
    sizes = np.diff(offs)
    doc = np.repeat(np.arange(len(offs) - 1), np.maximum(sizes - length + 1, 0))
    p = np.arange(len(doc)) - np.repeat(np.cumsum(np.maximum(sizes - length + 1, 0)) - np.maximum(sizes - length + 1, 0), np.maximum(sizes - length + 1, 0)) + offs[doc]
    a = at[p]
    new = np.ones(len(p), bool)
    new[1:] = (a[1:] != a[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    n = np.diff(np.r_[first, len(p)])
    lo, a, doc = p[first], a[first], doc[first]
    rel = a - lo
    kind = K.mix(K.span_hash(h, lo, lo + n + length - 1) + rel.astype(np.uint64) * U(0x9E6C63D0876A9A47))
    return doc, g[a].view(np.int64), kind.view(np.int64), lo - offs[doc], n, rel


def steps(s: np.ndarray, offs: np.ndarray, n: np.ndarray, rel: np.ndarray, key: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """Steps of blocks: (block, core, whole, first string, number of strings); hashes of core and whole include key and step."""
    h = K.prefix_hash(s)
    far, near = rel, rel - n + 1  # distances of the gram from the strings of the block, from the first to the last
    j0, j1 = near // STEP, far // STEP
    count = j1 - j0 + 1
    block = np.repeat(np.arange(len(n)), count)
    j = np.arange(len(block)) - np.repeat(np.cumsum(count) - count, count) + j0[block]
    least, most = np.maximum(near[block], j * STEP), np.minimum(far[block], j * STEP + STEP - 1)
    i1, i2 = rel[block] - most, rel[block] - least
    base = offs[block] + rel[block] - j * STEP
    salt = K.mix(key[block].view(np.uint64) + (j + 1).astype(np.uint64) * U(0xC2B2AE3D27D4EB4F))
    core = K.mix(K.span_hash(h, base, base + length - STEP + 1) ^ salt)
    whole = K.mix(K.span_hash(h, offs[block] + i1, offs[block] + i2 + length) + salt * U(3) + (least - j * STEP).astype(np.uint64))
    return block, core.view(np.int64), whole.view(np.int64), i1, i2 - i1 + 1


def repeated_spans(docs: DataFrame, ws: Workspace, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(rid, places) for each row with repeats: places is an array of (lo, array of (a, b)), strings from lo+a to lo+b.

    ``docs``: (rid, text)."""

    def blocks_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rid = batch.column(0).to_numpy()
            for i, _, buf, offs in K.slabs(batch.column(1)):
                doc, key, kind, lo, n, rel = file_strings(buf, offs, length, gram)
                if len(doc):
                    yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(kind), pa.array(rid[i + doc]), *[pa.array(x.astype(np.int32)) for x in (lo, n, rel)]], names=["key", "class", "rid", "lo", "n", "rel"])

    blocks = ws.keep(docs.mapInArrow(blocks_of, BLOCKS), "blocks")
    classes = ws.keep(blocks.groupBy("key", "class").agg(F.count("*").alias("copies"), F.min("rid").alias("rid"), F.min_by("lo", "rid").alias("lo"), F.min("n").alias("n"), F.min("rel").alias("rel")), "classes")
    mixed = ws.keep(classes.groupBy("key").count().filter("count > 1").select("key"), "mixed")
    # a member of each class whose gram other classes share, with its bytes
    asked = classes.join(mixed, "key", "left_semi").groupBy("rid").agg(F.collect_list(F.struct("key", "class", "copies", "lo", "n", "rel")).alias("want"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["key", "class", "copies", "n", "rel", "data"]
        for batch in batches:
            raw, offs = K.utf8(batch.column(0))
            rows = []
            for i, want in enumerate(batch.column(1).to_pylist()):
                for w in want:
                    at = offs[i] + w["lo"]
                    rows.append((w["key"], w["class"], w["copies"], w["n"], w["rel"], raw[at : at + w["n"] + length - 1].tobytes()))
            if rows:
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)

    members = ws.keep(docs.join(asked, "rid").select("text", "want").mapInArrow(cut, "key long, class long, copies long, n int, rel int, data binary"), "members")

    def stepped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                key, kind, copies, n, rel = [part.column(k).to_numpy() for k in range(5)]
                raw, offs = K.utf8(part.column(5))
                block, core, whole, first, count = steps(raw[offs[0] : offs[-1]], offs - offs[0], n.astype(np.int64), rel.astype(np.int64), key, length)
                yield pa.RecordBatch.from_arrays([pa.array(core), pa.array(whole), pa.array(kind[block]), pa.array(copies[block]), pa.array(first.astype(np.int32)), pa.array(count.astype(np.int32))], names=["core", "whole", "class", "copies", "first", "count"])

    stepped_ = ws.keep(members.mapInArrow(stepped, "core long, whole long, class long, copies long, first int, count int"), "steps")
    kinds = ws.keep(stepped_.groupBy("core", "whole").agg(F.sum("copies").alias("copies"), F.min("class").alias("class"), F.min_by("first", "class").alias("first"), F.min("count").alias("count")), "kinds")
    open_cores = ws.keep(kinds.groupBy("core").count().filter("count > 1").select("core"), "cores")
    # every kind of an open core is a partner; its bytes come from one of its members
    partners = kinds.join(open_cores, "core", "left_semi")
    data = F.substring("data", F.col("first") + 1, F.col("count") + length - 1)
    undecided = ws.keep(partners.select("whole", "class", "first", "count").join(members.select("class", "data"), "class").select(F.col("whole").alias("id"), data.alias("data")), "undecided")
    sorted_ = suffixes.twins(undecided, length, ws)
    masks = sorted_.groupBy("id").agg(F.expr("bit_or(shiftleft(1, place))").alias("mask"))
    # a kind with several members has all its strings repeated
    all_ = kinds.filter("copies > 1").select(F.col("whole").alias("id"), F.lit((1 << STEP) - 1).alias("mask"))
    decided = ws.keep(masks.unionAll(all_).groupBy("id").agg(F.expr("bit_or(mask)").alias("mask")), "decided")
    inner = stepped_.filter("copies = 1").join(decided, stepped_["whole"] == decided["id"]).select("class", F.col("first").alias("a"), "count", "mask")
    bit = F.explode(F.filter(F.transform(F.sequence(F.lit(0), F.lit(STEP - 1)), lambda k: F.when((k < F.col("count")) & (F.expr("1").bitwiseAND(F.call_function("shiftright", F.col("mask"), k)) == 1), k)), lambda k: k.isNotNull()))
    full = F.call_function("shiftleft", F.lit(1), F.col("count")) - 1
    whole_steps = inner.filter(F.col("mask").bitwiseAND(full) == full).select("class", F.col("a"), (F.col("a") + F.col("count") - 1).alias("b"))
    some_steps = inner.filter(F.col("mask").bitwiseAND(full) != full).select("class", "a", bit.alias("k"), "count", "mask").select("class", (F.col("a") + F.col("k")).alias("a"), (F.col("a") + F.col("k")).alias("b"))
    partial = whole_steps.unionAll(some_steps).groupBy("class").agg(F.collect_list(F.struct("a", "b")).alias("spans"))
    complete = classes.filter("copies > 1").select("class", F.array(F.struct(F.lit(0).alias("a"), (F.col("n") - 1).alias("b"))).alias("spans"))
    spans = ws.keep(complete.unionAll(partial), "spans")
    for name in ("classes", "mixed", "members", "steps", "kinds", "cores", "undecided", "sort-runs", "decided"):
        ws.drop(name)
    return blocks.select("class", "rid", "lo").join(spans, "class").groupBy("rid").agg(F.collect_list(F.struct("lo", "spans")).alias("places"))


def removed(places: list[dict] | None, n: int, length: int) -> list[tuple[int, int]]:
    """Maximal runs of bytes under the repeated strings."""
    if not places:
        return []
    depth = np.zeros(n + 1, np.int32)
    lo = np.array([p["lo"] + s["a"] for p in places for s in p["spans"]], np.int64)
    hi = np.array([p["lo"] + s["b"] for p in places for s in p["spans"]], np.int64) + length
    np.add.at(depth, lo, 1)
    np.add.at(depth, hi, -1)
    under = np.concatenate([[False], np.cumsum(depth[:-1]) > 0, [False]])
    edge = np.flatnonzero(under[1:] != under[:-1])
    return list(zip(edge[::2].tolist(), edge[1::2].tolist()))


def whole_characters(data: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The spans without characters that they cut."""
    out = []
    for a, b in spans:
        while a < b and data[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(data) and data[b] & 0xC0 == 0x80:
            b -= 1
        if a < b:
            out.append((a, b))
    return out


def drop_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, keep_text: bool = True, carry: list[str] | None = None) -> DataFrame:
    """(n_bytes, n_removed, n_spans, kept_sha256) and, with ``keep_text``, kept_text (whole characters) and spans, after the
    columns in ``carry`` (all but the clashing ones)."""
    ws = Workspace(docs.sparkSession, "dedup")
    own = ["n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text", "spans"]
    carry = [c for c in (docs.columns if carry is None else carry) if c.lower() not in own]
    rows = settled(docs, ws).select(F.monotonically_increasing_id().alias("rid"), "text", F.struct(*carry).alias("row"))
    places = repeated_spans(rows.select("rid", "text"), ws, length, gram)

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                raw, offs = K.utf8(part.column(0))
                out = []
                for i, where in enumerate(part.column(2).to_pylist()):
                    data = raw[offs[i] : offs[i + 1]].tobytes()
                    spans = removed(where, len(data), length)
                    left, last = [], 0
                    for a, b in [*spans, (len(data), len(data))]:
                        left.append(data[last:a])
                        last = b
                    row = [len(data), sum(b - a for a, b in spans), len(spans), hashlib.sha256(b"".join(left)).hexdigest()]
                    if keep_text:
                        left, last = [], 0
                        for a, b in [*whole_characters(data, spans), (len(data), len(data))]:
                            left.append(data[last:a])
                            last = b
                        row += [b"".join(left).decode(), [{"start": a, "end": b} for a, b in spans]]
                    out.append(row)
                types = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))]
                yield pa.RecordBatch.from_arrays([part.column(1), *[pa.array(c, t) for c, t in zip(zip(*out), types)]], names=["row", *own[: len(out[0])]])

    joined = rows.join(places, "rid", "left").select("text", "row", "places")
    schema = f"row {rows.schema['row'].dataType.simpleString()}, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept_text string, spans array<struct<start:bigint,end:bigint>>" if keep_text else "")
    return joined.mapInArrow(apply, schema).select("row.*", *own[: 6 if keep_text else 4])


def op1_suffix_merge_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drop_repeats(table(spark, sf_dir, "documents", "doc_id", "text"), keep_text=False, carry=["doc_id"])
