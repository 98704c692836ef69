"""Queries that once made their data up read given tables, with the rows of their SQL."""

import pytest

from tests.conftest import rows_of


@pytest.mark.parametrize("name, table", [("empty_bag_leaf", "events"), ("gyo_order", "lineitem"), ("op_memory_relation", "customer")])
def test_reads_given_tables(spark, sf, duck, monkeypatch, name, table):
    from joindash.sources import tables
    from joindash.workloads import registry

    read, opened = tables.read_table, []
    monkeypatch.setattr(tables, "read_table", lambda s, d, n, *a: opened.append(n) or read(s, d, n, *a))
    assert rows_of(registry.queries()[name](spark, sf).toPandas()) == rows_of(duck.sql(registry.oracle_sql()[name]).df())
    assert table in opened
