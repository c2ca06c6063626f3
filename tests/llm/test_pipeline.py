"""Each stage of the pipeline on its own input: columns, and what it must keep and drop."""

import corpus_pipeline
from keyless.llm.workspace import Workspace
from tests.llm.test_operators import slow_links, slow_quality, slow_removed


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, ws = docs.columns, Workspace(spark, "test-pipeline")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["quality_rules", "near_duplicates", "repeated_passages", "packed_sequences"]
    kept = ws.keep(stages["quality_rules"](spark, docs, sf), "1")
    assert kept.columns == columns
    assert not {r["doc_id"] for r in docs.collect() if slow_quality(r["text"])[-1]} & {r["doc_id"] for r in kept.collect()}
    one = ws.keep(stages["near_duplicates"](spark, kept, sf), "2")
    assert one.columns == columns
    groups = {d: c for d, _, c in slow_links([(r["doc_id"], r["text"]) for r in kept.collect()], 5, 80)}
    left = [groups[r["doc_id"]] for r in one.collect()]
    assert sorted(left) == sorted(set(groups.values()))
    cut = ws.keep(stages["repeated_passages"](spark, one, sf), "3")
    assert cut.columns == columns
    rows = [(r["doc_id"], r["text"]) for r in one.collect()]
    want = {d: n - gone for (d, _), (n, gone, _, _) in zip(rows, slow_removed([t for _, t in rows])) if n > gone or not n}
    have = {r["doc_id"]: len(r["text"].encode()) for r in cut.collect()}
    assert set(have) == set(want) and all(want[d] <= have[d] <= want[d] + 8 * 10 for d in want)
    packed = stages["packed_sequences"](spark, cut, sf).collect()
    assert {r["doc_id"] for r in packed} == set(have)


def test_null_and_repeated_rows_pass_through(spark, edge):
    docs = spark.read.parquet(f"{edge}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:3]:
        assert stage(spark, docs, edge).columns == docs.columns
