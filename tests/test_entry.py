from __future__ import annotations

import __spark_entry__ as e


def test_contract(spark):
    names, sql = set(e.queries()), set(e.oracle_sql())
    assert sql <= names
    assert e.entry(spark).count() == 29
