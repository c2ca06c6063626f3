"""Operators with an SQL form against DuckDB."""

import pytest

from keyless.llm import entry
from tests.compare import connect, same


@pytest.mark.parametrize("name", sorted(entry.oracle_sql()))
def test_query(spark, sf, name):
    same(entry.queries()[name](spark, sf), connect(sf), entry.oracle_sql()[name])
