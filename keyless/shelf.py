"""Stores on disk: segments by epoch and range of blocks, beside a row that says how they were built.

A store is static, so a rebuild is a new epoch; readers take the latest epoch whose row is there, which is written last."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import asdict

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless import store as S

#: Blocks of a range; a range is a directory.
RANGE = 1 << 16
META = "epoch int, plan string, keys array<string>, blocks int, n_keys long, overflow boolean, per_range int"


def write(store: S.Store, path: str, epoch: int = 0, per_range: int = RANGE) -> None:
    ranged = store.segments.withColumns({"epoch": F.lit(epoch), "range": F.floor(F.col("block") / per_range).cast("int")})
    parts = max(1, min(-(-store.blocks // 4096), 1 << 16))
    ranged.repartitionByRange(parts, "block").sortWithinPartitions("block").write.mode("append").partitionBy("epoch", "range").parquet(f"{path}/segments")
    if store.overflow is not None:
        write(store.overflow, f"{path}/overflow", epoch, per_range)
    meta = [(epoch, json.dumps(asdict(store.plan)), store.keys, store.blocks, store.n_keys, store.overflow is not None, per_range)]
    store.segments.sparkSession.createDataFrame(meta, META).coalesce(1).write.mode("append").parquet(f"{path}/meta")


def epochs(spark: SparkSession, path: str) -> list[int]:
    return sorted(r[0] for r in spark.read.schema(META).parquet(f"{path}/meta").select("epoch").distinct().collect())  # a row for each build


def read(spark: SparkSession, path: str, epoch: int | None = None, decode: Callable[[Column], Column] = lambda c: c) -> S.Store:
    """The store of an epoch, the latest where none is named; its segments are read when they are looked up."""
    epoch = epochs(spark, path)[-1] if epoch is None else epoch
    meta = spark.read.schema(META).parquet(f"{path}/meta").filter(F.col("epoch") == epoch).first()
    segments = scan(spark, path, epoch).drop("epoch", "range")
    second = read(spark, f"{path}/overflow", epoch) if meta["overflow"] else None
    return S.Store(S.Plan(**json.loads(meta["plan"])), list(meta["keys"]), segments, meta["blocks"], meta["n_keys"], second, decode)


def scan(spark: SparkSession, path: str, epoch: int, first: int | None = None, last: int | None = None, per_range: int = RANGE) -> DataFrame:
    """The segments of an epoch, of blocks from ``first`` to ``last`` only where these are named: other ranges are not read."""
    out = spark.read.schema(f"{S.SEGMENTS}, epoch int, range int").parquet(f"{path}/segments").filter(F.col("epoch") == epoch)
    if first is not None:
        out = out.filter((F.col("range") >= first // per_range) & (F.col("block") >= first))
    return out if last is None else out.filter((F.col("range") <= last // per_range) & (F.col("block") <= last))
