"""Every query of the engine that SQL can express equals its DuckDB definition (smallest scale)."""

from __future__ import annotations

import pytest

from comparing import as_rows
from ivfspark import registry

SQL = registry.oracle_sql()


@pytest.mark.parametrize("key", sorted(SQL))
def test_query_equals_sql(key, spark, small, duck):
    import __spark_entry__

    df = __spark_entry__.queries()[key](spark, small)
    found = df.collect()
    cursor = duck.execute(SQL[key])
    names = [d[0] for d in cursor.description]
    assert sorted(names) == sorted(df.columns)
    assert as_rows(df.columns, [tuple(r) for r in found]) == as_rows(names, cursor.fetchall())


def test_every_sql_has_a_query():
    assert set(SQL) <= set(registry.queries())


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 10
