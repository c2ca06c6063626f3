"""Stores beside streams: a stream probes a static store; windows, joins and epochs around it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyless import store as S


def probe(stream: DataFrame, store: S.Store, keys: list[str] | None = None, out: str = "value") -> DataFrame:
    """Lookup of a stream: a stream-static join and a projection, without state."""
    return S.lookup(stream, store, keys, out)


def tumbling(stream: DataFrame, time: str, width: str, late: str, *by: str) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.window(time, width), *by).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), *by, "n")


def sliding(stream: DataFrame, time: str, width: str, step: str, late: str) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.window(time, width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, time: str, gap: str, late: str, *by: str) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap), *by).agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), *by, "n")


def interval_join(left: DataFrame, right: DataFrame, on: str, left_time: str, right_time: str, within: str, late: str) -> DataFrame:
    a, b = left.withWatermark(left_time, late), right.withWatermark(right_time, late).withColumnRenamed(on, f"{on}_r")
    return a.join(b, F.expr(f"{on} = {on}_r and {right_time} >= {left_time} and {right_time} <= {left_time} + interval {within}"))


def epochs(keys: list[str], value: Column, plan: S.Plan, publish: Callable[[S.Store, int], None]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: rebuild from the rows of a batch and publish the store with its epoch."""
    return lambda batch, epoch: publish(S.build(batch, keys, value, plan, "max"), epoch)


def overlay(answers: DataFrame, changed: DataFrame, key: str, out: str = "value") -> DataFrame:
    """Keys changed since the epoch win over the store; ``changed`` has the last value of each."""
    return answers.join(changed.select(key, F.col(out).alias("__new")), key, "left").withColumn(out, F.coalesce("__new", out)).drop("__new")
