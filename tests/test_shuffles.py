"""Shuffles by stored objects and by the key-value tier: no exchange takes part, and odd inputs sort alike every way."""

import random
import socket

import pytest
from pyspark.sql import functions as F

from callweave.operators import mapreduce, rangesort
from callweave.sources.kv_live import KvClient, KvCluster
from callweave.tables import bucketed, load
from tests.conftest import DATA

WAYS = [{}, {"shuffle": "objects"}, {"shuffle": "kv"}, {"rounds": 2}]


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_no_exchange_behind_stored_objects(spark):
    tagged = load(spark, DATA, "lineitem").withColumn("part_id", F.floor(F.col("l_quantity") / 10).cast("int"))
    with bucketed(tagged, 5, "part_id") as ranges:
        assert "Exchange" not in plan(rangesort.sorted_ranges(ranges, ["l_extendedprice"]))
        assert "Exchange" not in plan(ranges.groupBy("part_id").count())
        assert ranges.count() == tagged.count()


@pytest.mark.parametrize("way", WAYS)
@pytest.mark.parametrize("kind", ["heavy", "equal", "few", "none", "nulls"])
def test_every_way_sorts_odd_inputs(spark, way, kind):
    r = random.Random(1)
    rows = {"heavy": [(7 if r.random() < 0.9 else r.randrange(50), i, "x") for i in range(400)], "equal": [(1, i, "y") for i in range(60)], "few": [(3, 1, "a"), (2, 2, "b")], "none": [], "nulls": [(r.choice([None, 1, 2]), i, r.choice([None, "é", "z"])) for i in range(90)]}[kind]
    df = spark.createDataFrame(rows, "k int, i long, s string").repartition(3)
    placed = rangesort.with_global_rank(rangesort.range_sort(df, ["k", "s", "i"], 7, **way))
    low = lambda v: (v is not None, v if v is not None else 0)
    want = sorted(rows, key=lambda x: (low(x[0]), (x[2] is not None, x[2] or ""), x[1]))
    assert [(x["k"], x["i"], x["s"]) for x in placed.orderBy("rk").collect()] == want
    assert sorted(x[0] for x in placed.select("rk").collect()) == list(range(1, len(rows) + 1))


def test_ranges_by_halving(spark):
    bounds = F.array(*map(F.lit, (10, 20, 20, 30)))
    got = spark.range(0, 41, 5).select(rangesort.find_range(F.col("id").cast("int"), bounds).alias("n")).collect()
    assert [x[0] for x in got] == [0, 0, 1, 1, 3, 3, 4, 4, 4]
    assert spark.range(1).select(rangesort.find_range(F.lit(1), F.array().cast("array<int>"))).first()[0] == 0


def test_blocks_of_the_key_value_way(spark):
    rows = load(spark, DATA, "lineitem")
    out = rangesort.range_sort(rows, ["l_extendedprice", "l_orderkey", "l_linenumber"], 6, shuffle="kv")
    census = out.blocks.collect()
    assert sum(x["rows"] for x in census) == rows.count() and {x["reduce_id"] for x in census} == set(range(6))
    sizes = [x[0] for x in out.groupBy("part_id").count().select("count").collect()]
    assert max(sizes) < 2 * min(sizes)


def test_shards_refuse_who_lacks_the_secret():
    with KvCluster(1) as cluster:
        client = KvClient(cluster.addresses)
        client.put("a", 1)
        assert client.get("a") == 1
        client.close()
        host, port, _ = cluster.addresses[0]
        with pytest.raises((ConnectionError, OSError)):
            KvClient([(host, port, "00" * 32)]).get("a")
        with socket.create_connection((host, port), timeout=5) as sock:
            sock.sendall(b"\x00" * 100)
            assert len(sock.recv(32)) == 32 and cluster.servers[0].operations == 2


def test_postings_are_bounded(spark):
    df = spark.createDataFrame([(i, "the " + "abc"[i % 3]) for i in range(100)], "id long, text string")
    rows = mapreduce.postings(df, "id", "text", 16).collect()
    assert max(len(x["ids"]) for x in rows) == 16 and sorted(i for x in rows if x["word"] == "the" for i in x["ids"]) == list(range(100))
