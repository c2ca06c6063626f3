"""The round trips carry the whole table: every row and every column."""

import glob

import pytest

from keyless import relational


@pytest.mark.parametrize("kind", ["orc", "json", "csv"])
def test_whole_orders_make_the_trip(spark, sf, tmp_path, monkeypatch, kind):
    monkeypatch.setattr("keyless.shared.scratch", lambda s, name: f"file://{tmp_path}/{name}")
    orders = spark.read.parquet(f"{sf}/orders.parquet")
    asked = relational.QUERIES[f"rt_{kind}"](spark, sf)
    assert asked.schema == orders.schema
    assert asked.exceptAll(orders).isEmpty() and orders.exceptAll(asked).isEmpty()
    assert glob.glob(f"{tmp_path}/rt-{kind}/part-*")
    back = spark.read.schema(orders.schema).format(kind).load(f"file://{tmp_path}/rt-{kind}")
    assert back.count() == orders.count()
    assert back.exceptAll(orders).isEmpty() and orders.exceptAll(back).isEmpty()
