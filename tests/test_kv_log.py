import pytest

from callweave.operators import rangesort
from callweave.sources import kv_live
from callweave.sources.kv_log import KvLog
from callweave.tables import load
from tests.conftest import DATA


def test_values_of_two_writers(tmp_path):
    first, second = KvLog(f"file:{tmp_path}/new folder", 3), KvLog(f"file://{tmp_path}/new folder", 3)
    at = {(w, k): (*tier.put(k, f"{w}{k}".encode() * k), len(f"{w}{k}") * k) for w, tier in (("a", first), ("b", second)) for k in range(40)}
    first.close()
    second.close()
    assert {s for s, *_ in at.values()} == {0, 1, 2} and all(at["a", k][0] == at["b", k][0] for k in range(40))
    assert all(first.get(*place) == f"{w}{k}".encode() * k for (w, k), place in at.items())
    with pytest.raises(EOFError):
        first.get(*at["a", 39][:3], 1 << 20)


def test_sort_holds_no_rows_on_the_driver(spark, monkeypatch):
    """No live shards in this process, and blocks of bounded bytes whatever a map task reads."""
    monkeypatch.setattr(kv_live, "KvCluster", None)
    rows = load(spark, DATA, "lineitem")
    bounds = rangesort.sample_bounds(rows, ["l_extendedprice"], 5)
    tagged = rows.coalesce(1).crossJoin(bounds).withColumn("part_id", rangesort.find_range(rangesort.F.struct("l_extendedprice"), rangesort.F.col("bounds"))).drop("bounds")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 500)
    try:
        out = rangesort.sort_through_kv(tagged, ["l_extendedprice"], 5, 2, 100_000)
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert out.blocks.count() > 15 and out.blocks.selectExpr("max(bytes)").first()[0] < 200_000
    assert out.blocks.selectExpr("sum(rows)").first()[0] == rows.count() == out.count()
    assert rangesort.validate_sorted(out, ["l_extendedprice"]).select("n", "within", "between").first()[1:] == (0, 0)
    assert out.select(*rows.columns).exceptAll(rows).isEmpty()
