"""Ways of working that only show on larger tables."""

import time

from pyspark.sql import functions as F

from keyless import baselines, workloads
from keyless import flows  # noqa: F401


def test_bloom_array_is_linear_in_its_words(spark):
    bits = 60 * 150_000
    df = spark.range(20_000)
    bloom = baselines.bloom_build(df, "id", bits, 4)
    began = time.monotonic()
    got = baselines.bloom_maybe(spark.range(20_000, 40_000).unionAll(df), "id", bloom, bits, 4, by_word=False)
    n = got.agg(F.count_if(F.col("maybe") & (F.col("id") < 20_000)).alias("a"), F.count_if("maybe").alias("b")).first()
    assert n["a"] == 20_000 and n["b"] < 20_100 and time.monotonic() - began < 30


def test_sessions_are_read_from_files(spark, sf):
    assert workloads.QUERIES["stream_session"](spark, sf).inputFiles()
