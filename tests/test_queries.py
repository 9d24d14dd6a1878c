"""Every query against its SQL on the smallest tables."""

from __future__ import annotations

import pytest
from codeschema import queries as Q
from conftest import SF, rows, sql_rows


@pytest.mark.parametrize("name", sorted(Q.QUERIES))
def test_query_equals_sql(spark, duck, name):
    assert rows(Q.QUERIES[name](spark, SF)) == sql_rows(duck, Q.ORACLES[name])


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 1
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
