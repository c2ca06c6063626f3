"""No row of the archive's shuffle holds more than a chunk of a payload."""

import hashlib

from pyspark.sql import functions as F

from keyless.llm import warc
from keyless.llm.workspace import Workspace


def test_archives_are_fed_by_chunks(spark, monkeypatch):
    html = {1: "é" * 5000, 2: "é" * 5000, 3: "x" * 1000, 4: "", 5: None, 6: "y" * 2001}
    pages = spark.createDataFrame([(p, f"u{p}", t) for p, t in html.items()], "page_id long, url string, html string").repartition(2)
    widest, frame = [], type(pages)
    plain = frame.mapInArrow

    def seen(self, f, schema, *a, **b):
        if schema == warc.MANIFEST:
            widest.extend(self.agg(F.max(F.octet_length(c))).first()[0] for c, kind in self.dtypes if kind == "binary")
        return plain(self, f, schema, *a, **b)

    monkeypatch.setattr(frame, "mapInArrow", seen)
    ws = Workspace(spark, "warc-test")
    folder = f"{ws.path}/archives"
    manifest = ws.keep(warc.write(pages, folder, ws, chunk=1000), "manifest")
    assert widest == [1000]
    got = {r["page_id"]: r for r in warc.read(manifest, folder, 300).collect()}
    for p, t in html.items():
        data = (t or "").encode()
        assert (got[p]["payload_bytes"], got[p]["payload_digest"], got[p]["url"]) == (len(data), warc.base32(hashlib.sha1(data).digest()), f"u{p}")
    assert {p: r["refers_to"] for p, r in got.items() if r["record_type"] == "revisit"} == {1: 2, 4: 5}
