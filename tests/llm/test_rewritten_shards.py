"""op9 writes the affected shards and returns what was written."""

import glob
from collections import Counter

from pyspark.sql import functions as F

from keyless.llm import entry, resharding
from keyless.llm.workspace import Workspace


def test_op9_rewrites(spark, sf, monkeypatch):
    folders, plain = [], resharding.rewrite
    monkeypatch.setattr(resharding, "rewrite", lambda placed, folder, *a: folders.append(folder) or plain(placed, folder, *a))
    rows = entry.queries()["op9_flow_resharding"](spark, sf).collect()
    assert len(folders) == 1
    touched = {x for r in rows if r["shard"] != r["old_shard"] for x in (r["shard"], r["old_shard"])}
    path = folders[0].removeprefix("file://")
    assert {int(d.rsplit("=")[-1]) for d in glob.glob(f"{path}/shard=*")} == touched & {r["shard"] for r in rows}
    back = spark.read.parquet(folders[0]).select("doc_id", "shard", "slot", F.crc32(F.encode(F.coalesce("text", F.lit("")), "UTF-8"))).collect()
    assert Counter(map(tuple, back)) == Counter((r["doc_id"], r["shard"], r["slot"], r["text_crc32"]) for r in rows if r["shard"] in touched)


def test_untouched_shards_are_not_written(spark, tmp_path):
    placed = spark.createDataFrame([(0, 0, 0), (1, 1, 0), (2, 1, 1)], "old_shard int, shard int, slot long")
    assert {r["shard"] for r in resharding.rewrite(placed, str(tmp_path / "out")).collect()} == {1}
    assert not glob.glob(f"{tmp_path}/out/shard=0")
