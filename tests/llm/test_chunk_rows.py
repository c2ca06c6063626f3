"""Chunks of one text are rows over the tasks, and the result is that of the whole text."""

import time
from collections import Counter

import numpy as np

from keyless.llm import bpe, vocab


def test_long_texts_in_small_chunks(spark):
    pattern = vocab.default_pattern()
    e = vocab.rank_encoder(vocab.default_path(vocab.RANKS), pattern)
    rng = np.random.default_rng(8)
    alphabet = list("ab '\n\t 1!é中") + ["'s", "n't", "   ", " word", " x"]
    texts = ["".join(alphabet[i] for i in rng.integers(0, len(alphabet), int(n))) for n in rng.integers(0, 900, 60)] + ["x" * 700, " " * 500, "ab cd " * 100, "x" * 300 + " y" * 200 + "z" * 300, None, ""]
    docs = spark.createDataFrame([(i, t, "clash") for i, t in enumerate(texts)], "doc_id long, text string, ids string").repartition(3)
    out = bpe.encode_rows(docs, chunk=60, overlap=20).collect()
    assert {r["doc_id"]: (list(r["ids"]), bytes(r["decoded"])) for r in out} == {i: (e.encode_ordinary(t or ""), (t or "").encode()) for i, t in enumerate(texts)}
    assert max(r["n_pieces"] for r in out) > 5


def test_chunks_are_rows_of_many_tasks(spark):
    docs = spark.createDataFrame([(1, "some words and more " * 30_000)], "doc_id long, text string")
    chunks = bpe.chunk_rows(docs, 10_000, 500).repartition(8, "rid", "k")
    where = Counter(r[0] for r in chunks.selectExpr("spark_partition_id()").collect())
    assert sum(where.values()) == 60 and len(where) > 4


def test_stitching_is_linear_without_white_space():
    pattern = vocab.default_pattern()
    seconds = []
    for n in (500_000, 2_000_000):
        began = time.process_time()
        assert bpe.stitch("x" * n, pattern) == [(0, n)]
        seconds.append(time.process_time() - began)
    assert seconds[1] < 10 * seconds[0] + 0.5
