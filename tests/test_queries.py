"""A spread of registered queries against DuckDB on the smallest tables (the driver runs them all)."""

import re

import pytest

from tests.conftest import rows_of

PICK = re.compile(r"^(ring_(sum|var|gram)|ann_|crm_v2_i[578]|flight_v5_i1|tpch_q(4|5|9)$|m2n_total_i1|docs_quality|op_(cube|join_asof|join_range|frames|json|dates|vector_udf)|st_(session|append_delta)|base_wide_cube|aug_month_gram|cyclic_prejoin|empty_bag)")


def names():
    from joindash.workloads import registry

    return [n for n in registry.queries() if PICK.match(n)]


@pytest.mark.parametrize("name", names())
def test_query(spark, sf, duck, name):
    from joindash.workloads import registry

    assert rows_of(registry.queries()[name](spark, sf).toPandas()) == rows_of(duck.sql(registry.oracle_sql()[name]).df())


def test_entry_and_guard(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
