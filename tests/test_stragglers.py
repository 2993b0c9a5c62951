import duckdb

from callweave.plans import catalog
from tests.helpers import same_rows

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def test_calls_right_at_the_bound(spark, tmp_path):
    """Three times a median, rounded in seconds or in milliseconds, and medians between two values."""
    values = {f"odd{k}": [k / 100, k / 100, round(3 * k / 100, 2)] for k in range(1, 400, 3)}
    values |= {f"even{k}": [0.0, k / 100, 0.07 * k, 3 * (k / 100 * 0.5 + 0.07 * k * 0.5)] for k in range(1, 400, 3)}
    rows = [(v, kind) for kind, vs in values.items() for v in vs] + [(None, "odd1"), (9.0, None)]
    spark.createDataFrame([(i, None, 1, kind, v, "{}") for i, (v, kind) in enumerate(rows)], EVENTS).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
    assert same_rows(catalog.QUERIES["straggler_flags"](spark, str(tmp_path)), con, catalog.ORACLES["straggler_flags"]) >= 20
