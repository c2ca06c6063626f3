"""Exact Jaccard self-join on word shingles with adaptive multi-match prefixes, down to connected groups.

A text is its set of hashed shingles; texts with one set are one node.  Shingles are ordered from rare to frequent by a table of
counters of fixed size over the whole corpus (any one order is right, a good one is fast).  Two sets that reach the threshold
share at least l of their first n - o + l shingles, where o is the least overlap that a set of n can have with a partner.
Every node takes the l, and with it the prefix, for which the estimated cost of its lists and of the candidates that share l
shingles is least; a pair is a candidate where it shares the smaller l of the two.

Links are looked for twice.  First every list is compared with two of its nodes only, which joins groups of copies at a cost that
follows the lists.  These two have the fewest shingles rarer than that of the list: a text with few words of its own, as the one
that the others were made from, is near to most.  Then pairs of different components, and only those, meet in the lists that still
hold more than one component.  Two sets that link share one of their first n - o + 1 shingles too, with o for the sizes of both, so only those
entries are joined; the join compares parity bitmaps, whose distance is never above that of the sets, and gives out no pair that
the bitmaps rule out.  Both ways end in a count of the shared shingles of the prefixes, and every candidate is verified on the
whole sets.

Defined cases: null or empty texts, and texts without words, have no shingles and link with nothing; repeated rows are copies;
null ids are never the smallest; a very long text is handled alone, by one task; an empty table gives no rows; columns other than
doc_id and text stay as they are, whatever their names.  Rows that are not plainly read from files are written out once, since rows
are told apart by their place in the scan.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless.llm import kernels as K
from keyless.llm.components import connected
from keyless.llm.workspace import Workspace, settled, table

U = np.uint64
BUCKETS = 1 << 20
SHARDS = 64
#: Numbers of shared shingles that a prefix can be made for.
MATCHES = (1, 2, 4, 8, 16, 32, 64)
#: Chance that a shingle that looks rare stands in another text too, through a passage that both have.
PASSAGE = 0.3
#: Words of 64 bits in a parity bitmap.
WORDS = 16
BITS = [f"w{k}" for k in range(WORDS)]
#: Row numbers that may be broadcast, 8 bytes each.
BROADCAST_ROWS = 100_000


def node_ids(h: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """A number for each set: sums over its hashes and its size."""
    c = np.zeros((2, len(h) + 1), np.uint64)
    np.cumsum(K.mix(h ^ U(0x51ED270B7A1F39C1)), out=c[0, 1:])
    np.cumsum(K.mix(h + U(0x7F4A7C159E3779B9)), out=c[1, 1:])
    s = c[:, offs[1:]] - c[:, offs[:-1]]
    return K.mix(s[0] ^ K.mix(s[1] + np.diff(offs).astype(np.uint64))).view(np.int64)


def parities(h: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Parity bitmaps of sets, a row for each: bit b tells if an odd number of hashes fall in bucket b."""
    size = 64 * WORDS
    doc = np.repeat(np.arange(len(at) - 1), np.diff(at))
    odd = np.bincount(doc * size + (h >> U(40)).astype(np.int64) % size, minlength=(len(at) - 1) * size) & 1
    return np.packbits(odd.astype(np.uint8).reshape(-1, size), axis=1).view(np.int64)


def profile(docs: DataFrame, width: int) -> DataFrame:
    """(rid, doc_id, n, node, bitmap) for each row and, with rid null, the counters of a task in SHARDS parts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(BUCKETS, np.int32)
        names = ["rid", "doc_id", "n", "node", "counts", *BITS]
        for batch in batches:
            for i, j, buf, offs in K.slabs(batch.column(2)):
                h, at = K.shingles(buf, offs, width)
                np.add.at(counts, (h & U(BUCKETS - 1)).astype(np.int64), 1)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), pa.array(np.diff(at)), pa.array(node_ids(h, at)), pa.nulls(j - i, pa.binary()), *map(pa.array, parities(h, at).T.copy())], names=names)
        if counts.any():
            parts = counts.reshape(SHARDS, -1)
            yield pa.RecordBatch.from_arrays([pa.nulls(SHARDS, pa.int64()), pa.nulls(SHARDS, pa.int64()), pa.array(np.arange(SHARDS)), pa.nulls(SHARDS, pa.int64()), pa.array([p.tobytes() for p in parts], pa.binary()), *[pa.nulls(SHARDS, pa.int64())] * WORDS], names=names)

    return docs.select("rid", F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, ", ".join(["rid long, doc_id long, n long, node long, counts binary", *[f"{c} long" for c in BITS]]))


def counters(rows: DataFrame) -> np.ndarray:
    """The counters of all tasks, summed on the executors; their number does not depend on the corpus."""

    def add(batches: Iterator[pa.RecordBatch], kind: type = np.int64) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                total[k] = total.get(k, 0) + np.frombuffer(raw, kind).astype(np.int64)
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([x.tobytes() for x in total.values()], pa.binary())], names=["n", "counts"])

    out = np.zeros((SHARDS, BUCKETS // SHARDS), np.int64)
    # one partial sum in each task before the parts meet
    for r in rows.filter("rid is null").select("n", "counts").mapInArrow(lambda x: add(x, np.int32), "n long, counts binary").repartition(SHARDS, "n").mapInArrow(add, "n long, counts binary").collect():
        out[r["n"]] = np.frombuffer(r["counts"], np.int64)
    return out.ravel()


def choose(n: np.ndarray, at: np.ndarray, estimate: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """(l, prefix length) of each set.  ``estimate``: expected lengths of the lists of its shingles, rare ones first.

    Cost: the entries of the prefix, what their lists hold, and the candidates left where l shingles must be shared, each of which
    costs a look at the whole set."""
    need = -(-percent * n // 100)
    total = np.concatenate([[0.0], np.cumsum(estimate)])
    best, least = np.ones(len(n), np.int64), np.full(len(n), np.inf)
    for m in MATCHES:
        size = np.minimum(n - need + m, n)
        lists = total[at[:-1] + size] - total[at[:-1]]
        cost = 4.0 * size + lists + n / 8 * (lists + PASSAGE * size) / m
        take = (m <= np.maximum(need, 1)) & (cost < least)
        best, least = np.where(take, m, best), np.where(take, cost, least)
    return best, np.minimum(n - need + best, n)


def prefixes(docs: DataFrame, counts: np.ndarray, width: int, percent: int) -> DataFrame:
    """(token, node, n, l, place) of the prefix of every set, rare shingles first; within a task a set comes once."""
    shared = docs.sparkSession.sparkContext.broadcast(counts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table_ = shared.value
        usual = table_.mean()
        seen: set[int] = set()
        for batch in batches:
            for _, _, buf, offs in K.slabs(batch.column(0)):
                h, at = K.shingles(buf, offs, width)
                if not len(h):
                    continue
                node, n = node_ids(h, at), np.diff(at)
                doc = np.repeat(np.arange(len(n)), n)
                often = table_[(h & U(BUCKETS - 1)).astype(np.int64)]
                order = np.lexsort((h, often, doc))
                h, often = h[order], often[order]
                matches, size = choose(n, at, np.maximum(often - 2 * usual, 0), percent)
                fresh = np.zeros(len(n), bool)
                for i, x in enumerate(node.tolist()):
                    if n[i] and x not in seen:
                        seen.add(x)
                        fresh[i] = True
                place = np.arange(len(h)) - at[doc]
                take = (place < size[doc]) & fresh[doc]
                d = doc[take]
                yield pa.RecordBatch.from_arrays([pa.array(h[take].view(np.int64)), pa.array(node[d]), pa.array(n[d].astype(np.int32)), pa.array(matches[d].astype(np.int32)), pa.array(place[take].astype(np.int32))], names=["token", "node", "n", "l", "place"])

    return docs.select("text").mapInArrow(run, "token long, node long, n int, l int, place int")


def whole_sets(docs: DataFrame, width: int) -> DataFrame:
    """(node, set) of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, buf, offs in K.slabs(batch.column(0)):
                h, at = K.shingles(buf, offs, width)
                raw = h.tobytes()
                yield pa.RecordBatch.from_arrays([pa.array(node_ids(h, at)), pa.array([raw[8 * a : 8 * b] for a, b in zip(at[:-1].tolist(), at[1:].tolist())], pa.binary())], names=["node", "set"])

    return docs.select("text").mapInArrow(run, "node long, set binary")


def verify(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets reach the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                keep = []
                for x, y in zip(part.column(2), part.column(3)):
                    p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                    both = np.concatenate([p, q])
                    both.sort(kind="stable")
                    inter = int((both[1:] == both[:-1]).sum())
                    keep.append(100 * inter >= percent * (len(both) - inter))
                yield part.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    left = pairs.join(sets.select(F.col("node").alias("b"), F.col("set").alias("set_b")), "b")
    return left.join(sets.select(F.col("node").alias("a"), F.col("set").alias("set_a")), "a").select("a", "b", "set_a", "set_b").mapInArrow(run, "a long, b long")


def groups(docs: DataFrame, width: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """Rows (rid, doc_id, n, node), and (node, component) of the linked nodes.  ``docs``: (rid, doc_id, text)."""
    spark = docs.sparkSession
    ws = Workspace(spark, "jaccard")
    rows = ws.keep(profile(docs, width), "profile")
    short = F.shiftrightunsigned("token", 24)
    lists = ws.keep(prefixes(docs, counters(rows), width, percent), "prefixes")
    # a token that stands once links nothing; 40 bits of it are enough to leave out nearly all of those
    twice = ws.keep(lists.groupBy(short.alias("short")).count().filter("count > 1").select("short"), "twice")
    live = ws.keep(lists.withColumn("short", short).join(twice, "short", "left_semi").groupBy("token", "node").agg(F.min("n").alias("n"), F.min("l").alias("l"), F.min("place").alias("place")), "lists")
    for name in ("prefixes", "twice"):
        ws.drop(name)
    own = ws.keep(live.groupBy("node").agg(F.min("n").alias("n"), F.min("l").alias("l"), F.array_sort(F.collect_list("token")).alias("tokens")), "own")
    hubs = ws.keep(live.groupBy("token").agg(F.count("*").alias("n"), *[F.min_by("node", _rank(end)).alias(name) for end, name in ((F.col("node"), "lo"), (F.bitwise_not("node"), "hi"))]).filter("n > 1").drop("n"), "hubs")
    star = live.select("token", "node").join(hubs, "token").select(F.explode(F.array("lo", "hi")).alias("hub"), "node").select(F.least("hub", "node").alias("a"), F.greatest("hub", "node").alias("b")).filter("a != b")
    tested = ws.keep(matched(ws.keep(star.distinct(), "star"), own, percent), "tested")

    def checked(pairs: DataFrame, step: str) -> DataFrame:
        """The pairs that hold on the whole sets; sets are made of the texts that the pairs name."""
        nodes = pairs.select(F.col("a").alias("node")).unionAll(pairs.select(F.col("b").alias("node"))).distinct()
        one = firsts.join(nodes, "node", "left_semi")
        chosen = ws.keep(one.select("rid"), f"chosen-{step}")
        few = chosen.count() <= BROADCAST_ROWS
        sets = ws.keep(whole_sets(docs.join(F.broadcast(chosen) if few else chosen, "rid", "left_semi"), width), f"sets-{step}")
        out = ws.keep(verify(pairs, sets, percent), f"links-{step}")
        ws.drop(f"sets-{step}")
        return out

    # aggregated before it meets anything, so that a text of very many copies is a row a task
    firsts = ws.keep(rows.filter("rid is not null").groupBy("node").agg(F.min("rid").alias("rid")), "firsts")
    links = checked(tested, "1")
    for name in ("hubs", "star", "chosen-1"):
        ws.drop(name)
    first = ws.keep(connected(links, ws, "first"), "first")
    lists_ = ws.keep(live.filter(f"100 * place <= {100 - percent} * n").drop("l").join(first, "node", "left").withColumn("component", F.coalesce("component", "node")), "marked")
    mixed = ws.keep(lists_.groupBy("token").agg(F.min("component").alias("x"), F.max("component").alias("y")).filter("x < y").select("token"), "mixed")
    bitmaps = rows.filter("n > 0").groupBy("node").agg(*[F.min(c).alias(c) for c in BITS])
    left = ws.keep(lists_.join(mixed, "token", "left_semi").join(bitmaps, "node").select("token", "node", F.col("n").cast("long").alias("n"), "place", "component", *BITS), "open")
    right = left.select(*[F.col(c).alias(f"{c}_b") for c in left.columns])
    apart = sum((F.bit_count(F.col(c).bitwiseXOR(F.col(f"{c}_b"))) for c in BITS[1:]), F.bit_count(F.col(BITS[0]).bitwiseXOR(F.col(f"{BITS[0]}_b"))))
    # sets that link differ in no more than (100 - percent) in (100 + percent) of their sizes' sum, and have the rest after the first shared token
    both = F.col("n") + F.col("n_b")
    first_shared = [(F.col(f"n{x}") - F.col(f"place{x}")) * (100 + percent) >= both * percent for x in ("", "_b")]
    close = first_shared[0] & first_shared[1] & (apart * (100 + percent) <= both * (100 - percent))
    met = left.join(right, (F.col("token") == F.col("token_b")) & (F.col("node") < F.col("node_b")) & (F.col("component") != F.col("component_b")) & _near(F.col("n"), F.col("n_b"), percent) & close)
    pairs = ws.keep(met.select(F.col("node").alias("a"), F.col("node_b").alias("b")).distinct().join(tested, ["a", "b"], "left_anti"), "pairs")
    rest = ws.keep(matched(pairs, own, percent), "rest")
    for name in ("lists", "marked", "mixed", "open"):
        ws.drop(name)
    if not rest.isEmpty():
        first = ws.keep(connected(links.unionAll(checked(rest, "2")), ws, "all"), "components")
    return rows.filter("rid is not null").drop("counts", *BITS), first


def _rank(end):
    """Order within a list: by the number of rarer shingles, then by the end of the node's number."""
    return F.shiftleft(F.least(F.col("place"), F.lit(1 << 22)).cast("long"), 40).bitwiseOR(end.bitwiseAND(F.lit((1 << 40) - 1)))


def _near(x, y, percent: int):
    return 100 * F.least(x, y) >= percent * F.greatest(x, y)


def matched(pairs: DataFrame, own: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) of near sizes whose prefixes share as many tokens as the smaller l of the two."""
    side = lambda x: own.select(F.col("node").alias(x), *[F.col(c).alias(f"{c}_{x}") for c in ("n", "l", "tokens")])
    wide = pairs.join(side("b"), "b").join(side("a"), "a").filter(_near(F.col("n_a"), F.col("n_b"), percent))
    return wide.filter(F.size(F.array_intersect("tokens_a", "tokens_b")) >= F.least("l_a", "l_b")).select("a", "b")


def link(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """(rid, doc_id, n_shingles, component_id, keeper) of each row; keeper is the rid of the row that stands for its component."""
    ws = Workspace(docs.sparkSession, "jaccard-result")
    rows, found = groups(docs, width, percent)
    by_node = rows.filter("n > 0").groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.min_by("rid", "doc_id").alias("best"), F.min("rid").alias("some"))
    tied = by_node.join(found, "node", "left").select("node", "doc_id", F.coalesce("best", "some").alias("best"), F.coalesce("component", "node").alias("component"))
    tied = ws.keep(tied, "nodes")
    tops = ws.keep(tied.groupBy("component").agg(F.min("doc_id").alias("component_id"), F.min_by("best", "doc_id").alias("best"), F.min("best").alias("some")), "tops")
    named = ws.keep(tied.join(tops, "component").select("node", "component_id", F.coalesce(tops["best"], "some").alias("keeper")), "named")
    alone = rows.filter("n = 0").select("rid", "doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"), F.col("rid").alias("keeper"))
    return rows.filter("n > 0").join(named, "node").select("rid", "doc_id", F.col("n").alias("n_shingles"), "component_id", "keeper").unionAll(alone)


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` with one of each group of near duplicates."""
    ws = Workspace(docs.sparkSession, "jaccard-keep")
    numbered = settled(docs, ws).select(F.monotonically_increasing_id().alias("rid"), F.struct("*").alias("row"))
    found = link(numbered.select("rid", F.col("row.doc_id").alias("doc_id"), F.col("row.text").alias("text")), width, percent)
    gone = ws.keep(found.filter("keeper != rid").select("rid"), "gone")
    return numbered.join(gone, "rid", "left_anti").select("row.*")


def op4_adaptive_prefix_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text").withColumn("rid", F.monotonically_increasing_id())
    return link(docs, width=4, percent=85).select("doc_id", "n_shingles", "component_id")
