"""Common-prefix-aware distributed merge sort of suffixes.

A task sorts its suffixes into runs and front-codes them: of each suffix only the length of the prefix shared with the one
before and the bytes after it are sent.  The runs are dealt by ranges of whole strings.  Each range is merged by a loser tree
that keeps, for every waiting run, the prefix its head shares with the last winner: two heads with different shared prefixes
are decided by those numbers alone, and equal ones are compared only behind what is known to be equal.  A suffix has a twin
where its shared prefix with a neighbour is the whole length.

Suffixes are cut at ``length`` bytes, which is what the caller asks about.  Equal suffixes of one run travel once.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyless.llm.workspace import Workspace

RUN = 30_000
RUNS = "dest int, run long, shared binary, tails binary, ids binary, places binary, twins binary"


def front_code(sorted_: list[bytes], length: int) -> tuple[np.ndarray, bytes]:
    """(shared prefix lengths, concatenated tails) of distinct ascending strings of one length."""
    shared = np.zeros(len(sorted_), np.uint16)
    for at in range(1, len(sorted_), 4096):
        m = np.frombuffer(b"".join(sorted_[at - 1 : at + 4096]), np.uint8).reshape(-1, length)
        shared[at : at + len(m) - 1] = (m[1:] != m[:-1]).argmax(1)
    return shared, b"".join([s[k:] for s, k in zip(sorted_, shared.tolist())])


def decode(shared: np.ndarray, tails: bytes, length: int) -> Iterator[tuple[int, bytes]]:
    """The strings again, one at a time, each with the prefix it shares with the one before."""
    at, last = 0, b""
    for k in shared.tolist():
        n = length - k
        last = last[:k] + tails[at : at + n]
        at += n
        yield k, last


class LoserTree:
    """Merge of front-coded runs; ``next`` gives (shared prefix with the previous output, run, number in the run)."""

    def __init__(self, runs: list[Iterator[tuple[int, bytes]]], length: int):
        self.runs, self.length = runs, length
        size = 1
        while size < len(runs):
            size *= 2
        self.size = size
        self.head: list[bytes | None] = [None] * size
        self.shared = [0] * size
        self.number = [-1] * size
        self.compared = 0
        for r in range(len(runs)):
            self._advance(r)
            self.shared[r] = 0
        self.losers = [0] * size
        winners = list(range(size))
        while len(winners) > 1:
            half = len(winners) // 2
            nxt = []
            for i in range(half):
                win, lose = self._play(winners[2 * i], winners[2 * i + 1])
                self.losers[half + i] = lose
                nxt.append(win)
            winners = nxt
        self.winner = winners[0]

    def _advance(self, r: int) -> None:
        got = next(self.runs[r], None)
        self.number[r] += 1
        if got is None:
            self.head[r] = None
        else:
            self.shared[r], self.head[r] = got

    def _play(self, a: int, b: int) -> tuple[int, int]:
        x, y = self.head[a], self.head[b]
        if x is None or y is None:
            return (b, a) if x is None else (a, b)
        p, q = self.shared[a], self.shared[b]
        if p != q:
            return (a, b) if p > q else (b, a)
        self.compared += 1
        differ = int.from_bytes(x[p:]) ^ int.from_bytes(y[p:])
        if not differ:
            self.shared[b] = self.length
            return a, b
        at = self.length - (differ.bit_length() + 7) // 8
        if x[at] < y[at]:
            self.shared[b] = at
            return a, b
        self.shared[a] = at
        return b, a

    def next(self) -> tuple[int, int, int] | None:
        r = self.winner
        if self.head[r] is None:
            return None
        out = (self.shared[r], r, self.number[r])
        self._advance(r)
        node = (self.size + r) // 2
        while node:
            r, self.losers[node] = self._play(r, self.losers[node])
            node //= 2
        self.winner = r
        return out


def twins(blocks: DataFrame, length: int, ws: Workspace, name: str = "sort", per_range: int = 400_000) -> DataFrame:
    """(id, place) of every suffix that has a twin.

    ``blocks``: (id long, data binary); the suffixes of a block begin at each place from 0 to len(data) - length."""
    total = blocks.agg(F.sum(F.octet_length("data") - length + 1)).collect()[0][0] or 0
    ranges = max(1, -(-total // per_range), int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions")) if total > per_range else 1)
    # splitters: about 40 strings for each range, drawn by hash
    keep = min(1.0, 40 * ranges / max(total, 1))
    drawn = blocks.withColumn("place", F.explode(F.sequence(F.lit(0), F.octet_length("data") - length))).filter(F.pmod(F.xxhash64("id", "place", F.lit(3)), F.lit(1_000_000)) <= int(1_000_000 * keep)).select(F.substring("data", F.col("place") + 1, F.lit(length)).alias("s"))
    sample = sorted(bytes(r[0]) for r in drawn.collect()) if ranges > 1 else []
    splitters = sorted({sample[len(sample) * k // ranges] for k in range(1, ranges)}) if sample else []

    def sort(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split(" ")[0] for x in RUNS.split(", ")]

        def flush(held: list[tuple[bytes, int]]) -> Iterator[pa.RecordBatch]:
            held.sort()
            strings, owners, twin, last = [], [], [], None
            for s, owner in held:
                if s == last:
                    if owners[-1] is not None:
                        twin.append(owners[-1])
                        owners[-1] = None
                    twin.append(owner)
                else:
                    strings.append(s)
                    owners.append(owner)
                    last = s
            pack = lambda xs: (np.array([x >> 12 for x in xs], np.int64).tobytes(), np.array([x & 4095 for x in xs], np.int16).tobytes())
            rows = []
            for at in range(0, len(twin), 50_000):
                a, b = pack(map_ids(twin[at : at + 50_000]))
                rows.append((-1, 0, b"", b"", a, b, b""))
            run = zlib.crc32(strings[0]) << 20 | len(strings)
            at = 0
            while at < len(strings):
                dest = bisect_right(splitters, strings[at])
                stop = len(strings) if dest == len(splitters) else bisect_left(strings, splitters[dest], at)
                shared, tails = front_code(strings[at:stop], length)
                own = owners[at:stop]
                a, b = pack(map_ids([0 if x is None else x for x in own]))
                rows.append((dest, run, shared.tobytes(), tails, a, b, bytes(x is None for x in own)))
                at = stop
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.int64(), *[pa.binary()] * 5))], names=names)

        def map_ids(xs: list[int]) -> list[int]:
            return [(ids[x >> 12] << 12) | (x & 4095) if x else (ids[0] << 12) for x in xs]

        held: list[tuple[bytes, int]] = []
        ids: list[int] = []
        for batch in batches:
            for i, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                slot = len(ids) << 12
                ids.append(i)
                held += [(data[k : k + length], slot | k) for k in range(len(data) - length + 1)]
                if len(held) >= RUN:
                    yield from flush(held)
                    held, ids = [], []
        if held:
            yield from flush(held)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(group: list[tuple]) -> Iterator[pa.RecordBatch]:
            tree = LoserTree([decode(np.frombuffer(g[0], np.uint16), g[1], length) for g in group], length)
            ids = [np.frombuffer(g[2], np.int64) for g in group]
            places = [np.frombuffer(g[3], np.int16) for g in group]
            many = [g[4] for g in group]
            out_i, out_p, last = [], [], None
            while (got := tree.next()) is not None:
                shared, r, n = got
                if shared == length and last is not None:
                    if last != -1:
                        out_i.append(last[0])
                        out_p.append(last[1])
                        last = -1
                    if not many[r][n]:
                        out_i.append(ids[r][n])
                        out_p.append(places[r][n])
                else:
                    last = -1 if many[r][n] else (ids[r][n], places[r][n])
                if len(out_i) >= 50_000:
                    yield pa.RecordBatch.from_arrays([pa.array(out_i, pa.int64()), pa.array(out_p, pa.int32())], names=["id", "place"])
                    out_i, out_p = [], []
            if out_i:
                yield pa.RecordBatch.from_arrays([pa.array(out_i, pa.int64()), pa.array(out_p, pa.int32())], names=["id", "place"])

        dest, group = None, []
        for batch in batches:
            for row in zip(*[batch.column(k).to_pylist() for k in (0, 2, 3, 4, 5, 6)]):
                if row[0] != dest and group:
                    yield from done(group)
                    group = []
                dest = row[0]
                group.append(row[1:])
        if group:
            yield from done(group)

    def inside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(a, np.int64)), pa.array(np.frombuffer(b, np.int16).astype(np.int32))], names=["id", "place"])

    runs = ws.keep(blocks.select("id", "data").mapInArrow(sort, RUNS), f"{name}-runs")
    own = runs.filter("dest = -1").select("ids", "places").mapInArrow(inside, "id long, place int")
    parts = min(ranges, 4 * int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    met = runs.filter("dest >= 0").repartition(parts, "dest").sortWithinPartitions("dest", "run").mapInArrow(merge, "id long, place int")
    return own.unionAll(met)
