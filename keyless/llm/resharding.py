"""Resharding by a minimum-cost flow: as few bytes as possible leave the shard where they are.

Every old shard is a line of bytes: blocks by the hash of doc_id, documents by doc_id within a block.  From the sizes of the
old shards and the capacities of the new ones (equal shares of all bytes) a transport problem is solved on the driver, over
shards only.  What a shard sends away is taken from the end of its line, so a document goes where its first byte falls, and
only documents of an overfull shard move.  Sizes of new shards then differ from equal shares by less than a document for
each transfer.

Defined cases: null text has size 16 and the checksum of no bytes; null doc_ids are one place in the order, and rows that tie
are ordered by checksum; repeated rows are placed each; a text of any length is one document and goes to one shard; an empty table
gives no rows.  The law is ``bytes``: sizes of shards are near equal.  Equal texts are documents of their own and are not kept together,
since a group of them may be larger than a shard.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from keyless.llm.workspace import Workspace, table

SHARDS = 40
OLD = 32
BLOCKS = 64
#: Bytes of a block beyond which the lines are cut finer, up to so many blocks; bytes of documents a task.
BLOCK_BYTES = 256 << 20
MOST_BLOCKS = 4096
TASK_BYTES = 128 << 20


def cheapest_transfers(old: list[int], capacity: list[int]) -> dict[tuple[int, int], int]:
    """Bytes from each old shard to each new one at least cost, where a byte that stays costs nothing and any other one.

    Successive shortest paths with potentials from a source over old shards and new shards to a sink."""
    n, m = len(old), len(capacity)
    source, sink = n + m, n + m + 1
    graph: list[list[list[int]]] = [[] for _ in range(n + m + 2)]

    def edge(a: int, b: int, room: int, cost: int) -> None:
        graph[a].append([b, room, cost, len(graph[b])])
        graph[b].append([a, 0, -cost, len(graph[a]) - 1])

    total = sum(old)
    for i, size in enumerate(old):
        edge(source, i, size, 0)
        for j in range(m):
            edge(i, n + j, total, int(i != j))
    for j, room in enumerate(capacity):
        edge(n + j, sink, room, 0)
    potential = [0] * len(graph)
    while True:
        far = [1 << 60] * len(graph)
        far[source], heap, came = 0, [(0, source)], {}
        while heap:
            d, a = heapq.heappop(heap)
            if d > far[a]:
                continue
            for k, (b, room, cost, _) in enumerate(graph[a]):
                if room and (nd := d + cost + potential[a] - potential[b]) < far[b]:
                    far[b], came[b] = nd, (a, k)
                    heapq.heappush(heap, (nd, b))
        if far[sink] == 1 << 60:
            break
        potential = [p + f if f < 1 << 60 else p for p, f in zip(potential, far)]
        flow, b = 1 << 62, sink
        while b != source:
            a, k = came[b]
            flow, b = min(flow, graph[a][k][1]), a
        b = sink
        while b != source:
            a, k = came[b]
            graph[a][k][1] -= flow
            graph[b][graph[a][k][3]][1] += flow
            b = a
    return {(i, e[0] - n): graph[e[0]][e[3]][1] for i in range(n) for e in graph[i] if n <= e[0] < n + m and graph[e[0]][e[3]][1]}


def equal_shares(total: int, shards: int) -> list[int]:
    return [total * (j + 1) // shards - total * j // shards for j in range(shards)]


def placement(docs: DataFrame, old_shard, shards: int = SHARDS, blocks: int = BLOCKS, carry: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """(rows, runs): the rows as ``reshard`` gives them, lazily, and the kept table (shard, old_shard, block, count, slot_base) of runs
    of rows that stay together.

    All decisions are made on sizes and ids; what is carried is shuffled once, by ranges of the old lines, so that a task holds rows
    for few shards."""
    spark = docs.sparkSession
    ws = Workspace(spark, "reshard")
    own = {"old_shard", "shard", "slot", "size", "text_crc32"}
    carry = [c for c in (docs.columns if carry is None else carry) if c.lower() not in own]
    raw = F.encode(F.coalesce("text", F.lit("")), "UTF-8")
    # what is carried stays in one struct, apart from the names used here
    line = docs.select(old_shard.cast("int").alias("old_shard"), (F.octet_length(raw).cast("long") + 16).alias("size"), F.crc32(raw).alias("text_crc32"), F.col("doc_id").alias("id"), F.struct(*carry).alias("row"))
    keys = ["old_shard", "block"]
    while True:
        # the line of a shard is cut in blocks by content as well as by id, so no id or text gathers in one
        cut = line.withColumn("block", F.pmod(F.xxhash64("id", "text_crc32", F.lit(7)), F.lit(blocks)).cast("int"))
        sizes = {(r[0], r[1]): r[2] for r in cut.groupBy(*keys).agg(F.sum("size")).collect()}  # old shards times blocks
        if max(sizes.values(), default=0) <= BLOCK_BYTES or blocks >= MOST_BLOCKS:
            break
        blocks = min(MOST_BLOCKS, blocks * -(-max(sizes.values()) // BLOCK_BYTES))
    if not sizes:
        runs = spark.createDataFrame([], "shard int, old_shard int, block int, count long, slot_base long")
        return line.select("old_shard", F.lit(0).alias("shard"), F.lit(0).cast("long").alias("slot"), "size", "text_crc32", "row.*"), runs
    old = [0] * (max(s for s, _ in sizes) + 1)
    bases = []
    for s, b in sorted(sizes):
        bases.append((s, b, old[s]))
        old[s] += sizes[s, b]
    flows = cheapest_transfers(old, equal_shares(sum(old), shards))
    cuts = []
    for s in range(len(old)):
        at = 0
        for j in sorted((j for i, j in flows if i == s), key=lambda j: (j != s, j)):
            cuts.append((s, at, at + flows[s, j], j))
            at += flows[s, j]
    tie = [F.col("id").asc_nulls_first(), "text_crc32", "size"]
    base = spark.createDataFrame(bases, "old_shard int, block int, base long")
    ends = spark.createDataFrame(cuts, "old_shard int, a long, b long, to int").groupBy("old_shard").agg(F.collect_list(F.struct("a", "b", "to")).alias("cuts"))
    order = Window.partitionBy(*keys).orderBy(*tie).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    first_byte = F.col("base") + F.sum("size").over(order) - F.col("size")
    to = F.filter("cuts", lambda c: (c["a"] <= F.col("first_byte")) & (F.col("first_byte") < c["b"]))[0]["to"]

    def placed(rows: DataFrame) -> DataFrame:
        return rows.join(F.broadcast(base), keys).withColumn("first_byte", first_byte).join(F.broadcast(ends), "old_shard").withColumn("shard", to).drop("cuts", "base", "first_byte")

    counts = ws.keep(placed(cut.drop("row")).groupBy("shard", *keys).count(), "counts")
    before = Window.partitionBy("shard").orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
    runs = ws.keep(counts.withColumn("slot_base", F.coalesce(F.sum("count").over(before), F.lit(0))), "runs")  # old shards times blocks, and a few
    parts = max(min(len(sizes), int(spark.conf.get("spark.sql.shuffle.partitions"))), sum(old) // TASK_BYTES)
    nth = F.row_number().over(Window.partitionBy(*keys, "shard").orderBy(*tie)).cast("long") - 1
    rows = placed(cut.repartitionByRange(parts, *keys)).withColumn("nth", nth).join(F.broadcast(runs.drop("count")), ["shard", *keys])
    return rows.select("old_shard", "shard", (F.col("slot_base") + F.col("nth")).alias("slot"), "size", "text_crc32", "row.*"), runs


def reshard(docs: DataFrame, old_shard, shards: int = SHARDS, blocks: int = BLOCKS, carry: list[str] | None = None) -> DataFrame:
    """(old_shard, shard, slot, size, text_crc32) before the columns named in ``carry`` (all by default, clashing names excepted).

    ``old_shard``: an expression for the present shard, 0-based; ``blocks``: parts of the line of a shard, more where they are large."""
    return placement(docs, old_shard, shards, blocks, carry)[0]


def affected(placed: DataFrame) -> DataFrame:
    """The shards that receive or lose rows; there are no more of them than old and new shards."""
    return placed.filter("shard != old_shard").select(F.explode(F.array("shard", "old_shard")).alias("shard")).distinct()


def rewrite(placed: DataFrame, folder: str, moved: DataFrame | None = None) -> DataFrame:
    """Write the shards that receive or lose rows below ``folder``, one directory a shard, each file a range of slots; those shards and
    their rows.

    A shard whose rows all stay keeps its present files.  Rows of ``reshard`` are written by the tasks that placed them."""
    rows = placed.join(F.broadcast(affected(placed) if moved is None else moved), "shard", "left_semi")
    rows.write.option("compression", "zstd").partitionBy("shard").parquet(folder)
    return placed.sparkSession.read.schema(rows.schema).parquet(folder)


def op9_flow_resharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "shards")
    # the present layout: shards by the hash of the id
    placed, runs = placement(table(spark, sf_dir, "documents", "doc_id", "text"), F.pmod(F.xxhash64("doc_id"), F.lit(OLD)), carry=["doc_id", "text"])
    moved = ws.keep(affected(runs), "affected")
    raw = F.encode(F.coalesce("text", F.lit("")), "UTF-8")
    # of affected shards, sizes and checksums are those of the text as written
    rows = rewrite(placed, f"{ws.path}/rewritten", moved).withColumns({"size": F.octet_length(raw).cast("long") + 16, "text_crc32": F.crc32(raw)}).drop("text")
    if not runs.join(F.broadcast(moved), "shard", "left_anti").isEmpty():
        rows = rows.unionByName(placed.drop("text").join(F.broadcast(moved), "shard", "left_anti"))
    return rows.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "old_shard")
