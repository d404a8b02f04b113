"""Every registered query of the engine against its SQL, workloads included."""

import pytest

from conftest import same_rows
from tallquant.plans import catalog, relational  # noqa: F401

@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_against_sql(spark, small, duck, name):
    got, want = same_rows(catalog.QUERIES[name](spark, small), duck, catalog.ORACLES[name])
    assert got == want


def test_every_query_has_sql():
    assert set(catalog.QUERIES) == set(catalog.ORACLES)


def test_entry_module():
    import __spark_entry__ as entry

    assert set(catalog.QUERIES) <= set(entry.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())
