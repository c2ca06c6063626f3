"""Variants of the stores that are rarely the best choice, and measures of the work that building takes."""

from __future__ import annotations

import math
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyless import codecs, flows, hashing as H, linalg as A, store as S
from keyless.shared import scratch
from keyless.workloads import check, check_sql, query, read, retrieval

#: Blocks of two keys, at most three, on five slots: all their matrices stand in a table.
TABLES = S.Plan(kind="table", k=3, block=2, headroom=0.5, slack=0.6, tries=1, equal_segments=True)

retrieval("order_priority_small_tables", "orders", ["o_orderkey"], "o_orderpriority", "dictionary", TABLES)
retrieval("part_size_square_clip", "part", ["p_partkey"], "p_size", codecs.offset(1, 6), S.Plan(kind="square", block=128, tries=64, weights="whole"))
retrieval("order_status_field_ring", "orders", ["o_orderkey"], "o_orderstatus", "dictionary", S.Plan(kind="field", sets="ring", run=12, block=64, slack=0.0, prime=257, tries=32))


@query(check_sql("as_many_cells_as_keys", "SELECT count(*) FROM part"))
def field_ring_cells(spark, sf_dir):
    """Two runs of about 2 log n: no cell more than there are keys, and every key gives its value."""
    df = read(spark, sf_dir, "part", "p_partkey", "p_size")
    st = S.build(df, ["p_partkey"], F.col("p_size"), S.Plan(kind="field", sets="ring", run=12, block=64, slack=0.0, prime=257, tries=32))
    size = st.segments.agg(F.sum("n_slots").alias("slots"), F.sum("n_keys").alias("keys"), F.count_if(F.col("status") != S.GOOD).alias("bad"))
    wrong = S.verify(st, df, F.col("p_size")).select("n", "errors")
    return check(size.join(F.broadcast(wrong)), "as_many_cells_as_keys", F.max("n"), F.max(F.abs(F.col("slots") - F.col("keys")) + F.col("bad") + F.col("errors")))  # one row each


@query()
def overflow_small_tables(spark, sf_dir):
    """(reason, share) of the keys of blocks of two, by whether the block was too large or its rows dependent."""
    seg = S.build(read(spark, sf_dir, "orders", "o_orderkey"), ["o_orderkey"], F.lit(0), TABLES).segments
    reason = F.when(F.col("status") == S.GOOD, "none").when(F.col("n_keys") > 3, "oversize").otherwise("dependent")
    total = seg.agg(F.sum("n_keys").alias("total"))
    return seg.groupBy(reason.alias("reason")).agg(F.sum("n_keys").alias("n")).join(F.broadcast(total)).select("reason", (F.col("n") / F.col("total")).alias("share"))  # one row


def _in_blocks(df: DataFrame, keys: list[str], block: int) -> DataFrame:
    rows = S.normalise(df, keys, None, "min")
    return S.clustered(rows, max(1, math.ceil(rows.count() / block)))


@query()
def build_scaling(spark, sf_dir):
    """(source, block, keys, row_sums): the work of the elimination.  With blocks of one size it follows the keys; with the block it grows, to at most
    one sum for each other key of the block, and a sum takes a word for every 64 slots: cubic at most for one system of all keys."""
    out = None

    def run(batches):
        for block, (d1, d2) in S.per_block(batches, ["d1", "d2"]):
            m = S.Plan(k=4).slots_for(len(d1))
            done = A.row_sums(H.np_slots(d1, d2, 4, m, 1000).tolist())
            yield pa.RecordBatch.from_pydict({"n": pa.array([len(d1)], pa.int64()), "sums": pa.array([done], pa.int64())})

    for table, key in (("part", "p_partkey"), ("orders", "o_orderkey")):
        df = read(spark, sf_dir, table, key)
        for size in (32, 64, 128, 256):
            one = _in_blocks(df, [key], size).mapInArrow(run, "n long, sums long")
            one = one.agg(F.sum("n").alias("keys"), F.sum("sums").alias("row_sums")).select(F.lit(table).alias("source"), F.lit(size).alias("block"), "keys", "row_sums")
            out = one if out is None else out.unionAll(one)
    return out


@query(check_sql("rank_implies_placement", "SELECT count(*) FROM part"))
def rank_implies_placement(spark, sf_dir):
    """Where the rows of a block are independent, its keys have places of their own, and even among the pivots; some block is so."""

    def run(batches):
        for _, (d1, d2) in S.per_block(batches, ["d1", "d2"]):
            m = max(5, math.ceil(len(d1) / 0.9))
            rows = H.np_slots(d1, d2, 4, m, 2000).tolist()
            pivots, full = A.eliminate(rows)
            placed = full and A.match(rows) is not None and A.match([[c for c in r if c in pivots] for r in rows]) is not None
            yield pa.RecordBatch.from_pydict({"n": pa.array([len(d1)], pa.int64()), "independent": [full], "placed": [placed]})

    got = _in_blocks(read(spark, sf_dir, "part", "p_partkey"), ["p_partkey"], 64).mapInArrow(run, "n long, independent boolean, placed boolean")
    return check(got, "rank_implies_placement", F.sum("n"), F.count_if(F.col("independent") & ~F.col("placed")) + (F.count_if("independent") == 0).cast("int"))


@query("WITH w AS (SELECT max(ts) - INTERVAL 1 DAY AS w FROM events WHERE event_id % 2 = 0) SELECT count_if(event_id % 2 = 0 OR ts > w)::BIGINT AS kept, count_if(event_id % 2 = 1 AND ts <= w)::BIGINT AS late FROM events, w")
def stream_late(spark, sf_dir):
    """All events arrive in two parts, those of odd number after the even ones; of the second part the state drops and counts what is more than a
    day behind the latest event of the first."""
    base = scratch(spark, f"stream-late-{uuid.uuid4().hex[:6]}")
    events, late = read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")), 0
    for rest in (0, 1):
        events.filter(F.pmod("event_id", F.lit(2)) == rest).write.mode("append").parquet(f"{base}-in")
        stream = spark.readStream.schema(events.schema).parquet(f"{base}-in").withWatermark("ts", "1 day").dropDuplicates(["event_id", "ts"]).select("event_id")
        run = stream.writeStream.format("parquet").option("checkpointLocation", f"{base}-state").outputMode("append").trigger(availableNow=True).start(f"{base}-out")
        run.awaitTermination()
        late += sum(op["numRowsDroppedByWatermark"] for p in run.recentProgress for op in p["stateOperators"])
    return spark.read.schema(flows.SCHEMA).parquet(f"{base}-out").agg(F.count("*").alias("kept")).withColumn("late", F.lit(late).cast("bigint"))
