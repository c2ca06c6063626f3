"""Connected components by alternating large-star and small-star steps; no link, label or node reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyless.llm.workspace import Workspace


def connected(links: DataFrame, ws: Workspace, name: str = "cc", most: int = 60) -> DataFrame:
    """(node, component) of the nodes of ``links`` (a, b); the component is the smallest node of each."""
    edges = ws.keep(links.filter("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), f"{name}-0")

    def mark(df: DataFrame) -> tuple:
        r = df.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).collect()[0]
        return tuple(r)

    seen, k = mark(edges), 0
    while k < most:
        k += 1
        # large star: everything larger than a node is tied to the least neighbour
        both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = ws.keep(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), f"{name}-{k}-l")
        large = ws.keep(both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v").distinct(), f"{name}-{k}-a")
        # small star: the smaller neighbours of a node are tied to the least of them
        low = ws.keep(large.groupBy("u").agg(F.min("v").alias("m")), f"{name}-{k}-s")
        tied = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v")
        edges = ws.keep(tied.unionAll(low.select("u", F.col("m").alias("v"))).distinct(), f"{name}-{k}")
        now = mark(edges)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components did not settle in {most} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionAll(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
