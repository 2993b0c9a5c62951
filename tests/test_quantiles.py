import random

from pyspark.sql import functions as F

from callweave.measures.quantiles import exact_quantiles

SHARES = {"p0": 0.0, "p50": 0.5, "p90": 0.9, "p99": 0.99, "p100": 1.0}


def test_equal_to_percentile(spark):
    rng = random.Random(3)
    rows = [("many", rng.random()) for _ in range(30_000)] + [("ties", float(rng.randint(0, 3))) for _ in range(5_000)]
    rows += [("one", 4.0), ("two", 1.0), ("two", 2.0), ("none", None), (None, 3.0), (None, 5.0), ("some", None), ("some", 7.0)]
    df = spark.createDataFrame(rows, "kind string, t double")
    want = {r[0]: r[1:] for r in df.groupBy("kind").agg(*[F.percentile("t", s) for s in SHARES.values()]).collect()}
    for width, accuracy in ((1e-4, 100_000), (0.02, 200)):  # the second sketch is coarse: brackets err, results don't
        got = {r[0]: r[1:] for r in exact_quantiles(df, "kind", "t", SHARES, width, accuracy).collect()}
        assert got.keys() == want.keys()
        for k in want:
            assert all(a == b or abs(a - b) < 1e-12 for a, b in zip(got[k], want[k])), k


def test_empty(spark):
    assert exact_quantiles(spark.createDataFrame([], "kind string, t double"), "kind", "t", SHARES).count() == 0
