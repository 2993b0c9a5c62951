from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from callweave.measures import trace as m
from callweave.micro import kernels
from callweave.plans.surface import register
from callweave.sources import kv
from callweave.sources.kv_live import KvClient, KvCluster
from callweave.streaming import streams
from callweave.tables import shared_path


def test_frame_kv(spark):
    table = spark.createDataFrame([("a", "1", 1), ("b", "2", 2)], "key string, value string, version long")
    puts = spark.createDataFrame([("b", "9", 5), ("b", "8", 4), ("c", "7", 3)], table.schema)
    new = kv.put(table, puts)
    assert sorted(map(tuple, new.collect())) == [("a", "1", 1), ("b", "9", 5), ("c", "7", 3)]
    taken, left = kv.take(new, spark.createDataFrame([("a",), ("z",)], "key string"))
    assert [r["key"] for r in taken.collect()] == ["a"] and left.count() == 2
    got = kv.get(new, spark.createDataFrame([("z",), ("c",)], "key string"))
    assert {r["key"]: r["value"] for r in got.collect()} == {"z": None, "c": "7"}
    same = kv.range_update(new, "key", "x", "y", "value", lambda v: F.lit("0"))
    assert sorted(same.collect()) == sorted(new.collect())
    assert new.select(kv.shard_of(F.col("key"), 3).alias("s")).where("s < 0 or s > 2").isEmpty()


def test_live_kv():
    with KvCluster(3) as cluster:
        c = KvClient(cluster.addresses)
        for i in range(20):
            c.put(i, i)
        assert c.get(7) == 7 and c.get("absent") is None and c.add(7, 5) == 12
        assert c.range_add(0, 9, 100) == 10 and c.get(3) == 103 and c.get(15) == 15
        assert c.script(15, lambda old, by: old * by, 4) == 60
        assert sum(len(c.dump(s)) for s in range(3)) == 20
        c.close()


def test_published_measures(spark):
    assert round(100 * m.slowdown(98.6, 84)) == 17
    assert m.ideal_makespan(100, 100, 300) == m.ideal_makespan(10_000, 10_000, 300) == 300
    assert not m.servers_cheaper(2, 0.5) and m.servers_cheaper(2, 0.51)
    b = spark.range(1).select(*[c.alias(k) for k, c in m.balance(F.lit(1400.0), F.lit(35.0), F.lit(300.0)).items()]).first()
    assert (b["fill_s"], b["compute_s"]) == (40.0, 220.0) and m.memory_for(300, 35, 80 / 300) == 1400


def test_charges_round_up(spark):
    df = spark.createDataFrame([(1, 0.0), (2, 1.0), (3, 100.0), (4, 100.1)], "call_id long, duration_ms double")
    got = [r[0] for r in df.orderBy("call_id").select(m.call_charge(F.col("duration_ms"))).collect()]
    unit = Decimal("0.0000025")
    assert got == [0 * unit, unit, unit, 2 * unit]


def test_greedy_is_within_its_bound():
    import random

    r = random.Random(1)
    durations = [r.random() for _ in range(500)]
    for p in (1, 3, 16):
        low = max(sum(durations) / p, max(durations))
        assert low <= m.greedy_makespan(durations, p) + 1e-9 <= (2 - 1 / p) * low + 1e-6


def test_concurrency_by_hand(spark):
    rows = [(1, 1, "a", 0, 1.0, 0), (2, 1, "a", 500, 1.0, 0), (3, 1, "a", 1000, 1.0, 0)]
    trace = spark.createDataFrame(rows, "call_id long, worker long, phase string, start_us long, duration_ms double, bytes long")
    r = m.concurrency(trace).first()
    assert r["peak"] == 2 and abs(r["mean_active"] - 1.5) < 1e-9
    assert m.makespan(trace).first()["elapsed_ms"] == 2.0


def test_late_rows_and_restart(spark, t):
    e = streams.with_time(t("events")).select("event_id", "ts")
    out, log, src = shared_path(spark), shared_path(spark), shared_path(spark)
    e.limit(10).coalesce(1).write.parquet(src)
    for _ in range(3):
        streams.on_arrival(streams.read_stream(spark, e.schema, src), lambda b: b, out, log)
    assert spark.read.schema(e.schema).parquet(f"{out}/*").count() == 10


def test_watermark_needs_a_zone(spark, t):
    stream = streams.replay(t("events").select("event_id", "ts"), 1, "ts")
    with pytest.raises(Exception, match="(?i)timestamp"):
        stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).count()


def test_micro(spark):
    assert kernels.bench_matmul(spark, 2, 64, 2).where("gflops > 0").count() == 2
    path, seconds, rate = kernels.bench_object_write(spark, 2, 1)
    assert rate > 0 and kernels.bench_object_read(spark, path)[1] > 0
    assert kernels.bench_kv(spark, 2, ops=20).where("ops = 40 and pairs_per_s > 0").count() == 2
    assert set(kernels.bench_launch(spark, 2)) == {"first", "warm"}
    root = shared_path(spark)
    assert set(kernels.bench_local_vs_remote(spark, root, root, 1, 1)) == {"local", "remote"}


def test_sql_surface(spark):
    register(spark)
    r = spark.sql("SELECT callweave_steps(101, 100) AS s, round(callweave_fill_seconds(1400, 35), 2) AS f, round(callweave_slowdown(98.6, 84), 3) AS d, callweave_shuffle_files(2500, 1) AS n").first()
    assert (r["s"], r["f"], r["d"], r["n"]) == (2, 40.0, 0.174, 6_250_000.0)


def test_plans_prune_and_choose_joins(spark, t):
    from callweave.plans import catalog
    from tests.conftest import DATA

    text = lambda name: catalog.QUERIES[name](spark, DATA)._jdf.queryExecution().executedPlan().toString()
    pruned = text("scan_prune")
    assert "PushedFilters: [IsNotNull(l_shipdate), GreaterThanOrEqual(l_shipdate" in pruned and "ReadSchema: struct<l_extendedprice:double,l_shipdate:timestamp_ntz>" in pruned
    assert "SortMergeJoin" in text("join_smj") and "ShuffledHashJoin" in text("join_shj")
    assert "CartesianProduct" not in text("join_interval") and "BroadcastNestedLoop" not in text("join_theta")
    assert "CartesianProduct" not in text("matmul_sql")


def test_spread_deals_out_single_files_only(spark, t):
    from callweave.tables import settle, spread

    one = spread(t("documents"), "doc_id")
    assert "REPARTITION_BY_NUM" in one._jdf.queryExecution().executedPlan().toString() and one.count() == t("documents").count()
    many = settle(spark.range(100).repartition(20))
    assert spread(many) is many
    literal = spark.createDataFrame([(1,)], "a int")
    assert spread(literal) is literal


def test_experiments_give_their_tables(spark):
    from callweave.micro import experiments as x
    from tests.conftest import DATA

    assert {r["phase"] for r in x.featurize_and_fit(spark, DATA, 2, 1).collect()} == {"start latency", "set-up", "featurization", "fetch", "fit"}
    assert x.word_count_routes(spark, DATA).where("seconds > 0").count() == 5
    modes = {r["mode"]: r["distance"] for r in x.training_modes(spark, DATA, 60).collect()}
    assert modes["stale by 2, rate too high"] > 10 * modes["synchronous"]
    sorts = x.sort_sweep(spark, DATA, (4,), (1, 2)).collect()
    assert sorted((r["way"], r["shards"]) for r in sorts) == [("kv", 1), ("kv", 2), ("native", 0), ("objects", 0), ("two rounds", 0)]
    maps = spark.sparkContext.defaultParallelism
    assert {r["blocks"] for r in sorts} == {4 * maps}  # 2 * 4**1.5 = 4 * 4 objects a part in two rounds as well
    assert x.block_reads(spark, DATA).count() == 2
    assert x.compute_scaling(spark, (1, 2), 64).count() == x.object_scaling(spark, (1, 2), 1).count() == x.kv_scaling(spark, (1,), (1, 2), 10).count() == 2
