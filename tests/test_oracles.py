"""Every registered query of the library against its SQL, on the smallest tables."""

import pytest

from callweave.plans import catalog
from tests.conftest import DATA
from tests.helpers import same_rows


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_equals_sql(name, spark, duck):
    same_rows(catalog.QUERIES[name](spark, DATA), duck, catalog.ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLES)))
def test_query_without_sql_runs(name, spark):
    assert catalog.QUERIES[name](spark, DATA).count() > 0


def test_entry_and_names(spark):
    import __spark_entry__ as e

    assert e.entry(spark).columns == ["word", "n"]
    assert set(e.oracle_sql()) <= set(e.queries())
