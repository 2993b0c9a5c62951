import os
import sys

import duckdb
import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from callweave.session import LOCAL, build_session

    root = tmp_path_factory.mktemp("spark")
    conf = {"spark.checkpoint.dir": f"file://{root}/shared", "spark.sql.warehouse.dir": f"file://{root}/warehouse", "spark.driver.memory": "6g"}
    s = build_session("local[8]", {**LOCAL, **conf}, "tests")
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    from callweave.tables import NAMES

    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for name in NAMES:
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{DATA}/{name}.parquet'")
    return con


@pytest.fixture(scope="session")
def t(spark):
    from callweave.tables import load

    return lambda name: load(spark, DATA, name)
