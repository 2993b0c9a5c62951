"""Queries whose results once came from values in the code alone: they follow their tables."""

import duckdb
import pytest

from callweave.plans import catalog
from callweave.tables import NAMES
from tests.conftest import DATA
from tests.helpers import plain, same_rows

MORE = DATA.replace("0.001", "0.01")
QUERIES = [
    "balance_rule",
    "elastic_makespan",
    "join_cross_grid",
    "premium_break_even",
    "published_arithmetic",
    "scan_range",
    "shuffle_growth_model",
    "shuffle_medium_model",
]


@pytest.mark.parametrize("name", QUERIES)
def test_result_follows_its_table(name, spark):
    con = duckdb.connect()
    for table in NAMES:
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{MORE}/{table}.parquet'")
    run = catalog.QUERIES[name]
    same_rows(run(spark, MORE), con, catalog.ORACLES[name])
    few, many = (sorted(str(plain(tuple(r))) for r in run(spark, d).collect()) for d in (DATA, MORE))
    assert few != many
