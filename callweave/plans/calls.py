"""Workloads of the map primitive: calls, retries, ledgers, limits, key-value traffic."""

from __future__ import annotations

import json

from pyspark.sql import functions as F

from callweave.calls.ledger import Ledger, first_outcomes, missing_calls, resume
from callweave.calls.runner import run_calls, run_map_table
from callweave.calls.spec import RetryPolicy
from callweave.calls.vault import FunctionVault
from callweave.calls.worker import call_attempt
from callweave.plans.registry import query
from callweave.sources import kv
from callweave.tables import as_key_values, as_trace, settle, shared_path


@query("SELECT o_orderkey AS call_id, o_orderkey * o_orderkey AS result FROM orders")
def map_square_rows(t, spark):
    return run_map_table(t("orders"), lambda k: k * k, ["o_orderkey"], "long", "o_orderkey", slots=8, clock=False).select("call_id", "result")


@query("""SELECT p_partkey AS call_id, CASE p_size % 3 WHEN 0 THEN length(p_name) WHEN 1 THEN p_size * 7 ELSE length(replace(p_type, ' ', '')) END AS result FROM part""")
def map_mixed_functions(t, spark):
    vault = FunctionVault(spark)
    ids = [vault.store(f) for f in (lambda p: len(p["p_name"]), lambda p: p["p_size"] * 7, lambda p: len(p["p_type"].replace(" ", "")))]
    which = F.element_at(F.array(*map(F.lit, ids)), (F.col("p_size") % 3 + 1).cast("int"))
    calls = t("part").select(F.col("p_partkey").alias("call_id"), which.alias("fn_id"), F.struct("p_name", "p_size", "p_type").alias("payload"))
    return run_calls(calls, vault, "long", slots=8, clock=False).select("call_id", "result")


@query("SELECT page_id AS call_id, octet_length(encode(html)) AS n_bytes, md5(html) AS digest FROM pages")
def map_object_sizes(t, spark):
    import hashlib

    def look(html):
        data = html.encode()
        return {"n_bytes": len(data), "digest": hashlib.md5(data).hexdigest()}

    out = run_map_table(t("pages"), look, ["html"], "struct<n_bytes:long,digest:string>", "page_id", slots=8, clock=False)
    return out.select("call_id", "result.n_bytes", "result.digest")


@query("SELECT event_id AS call_id, CAST(round(value * 100) AS BIGINT) * 3 AS result FROM events")
def map_batched_calls(t, spark):
    rows = t("events").withColumn("cents", F.round(F.col("value") * 100).cast("long"))
    return run_map_table(rows, lambda cents: [3 * c for c in cents], ["cents"], "long", "event_id", batch_size=64, clock=False).select("call_id", "result")


@query("SELECT o_orderkey AS call_id, CAST(CASE WHEN o_orderkey % 3 = 0 THEN 2 ELSE 1 END AS INTEGER) AS attempt, 'ok' AS status, o_orderkey + 1 AS result FROM orders")
def call_retry_ledger(t, spark):
    def flaky(key, attempt):
        if key % 3 == 0 and attempt == 1:
            raise OSError("lost worker")
        return key + 1

    out = run_map_table(t("orders"), call_attempt(flaky), ["o_orderkey"], "long", "o_orderkey", retry=RetryPolicy(max_attempts=3), isolation="reuse", clock=False)
    return first_outcomes(out).select("call_id", "attempt", "status", "result")


@query("SELECT o_orderkey AS call_id, o_orderkey % 7 AS result, o_totalprice < 200000 AS first_run FROM orders")
def call_resume_antijoin(t, spark):
    ledger = Ledger(spark, shared_path(spark), "resume", "long")
    calls = t("orders").select(F.col("o_orderkey").alias("call_id"), F.col("o_orderkey").alias("payload"))
    early = t("orders").where("o_totalprice < 200000").select(F.col("o_orderkey").alias("call_id"), F.col("o_orderkey").alias("payload"))
    resume(early, lambda k: k % 7, ledger, "long", slots=8)
    before = ledger.snapshot().select("call_id", F.lit(True).alias("first_run"))
    before = settle(before)
    resume(calls, lambda k: k % 7, ledger, "long", slots=8)
    return ledger.snapshot().join(before, "call_id", "left").select("call_id", "result", F.coalesce("first_run", F.lit(False)).alias("first_run"))


@query("""SELECT user_id AS call_id, CAST(count(*) AS BIGINT) AS outcomes, CAST(coalesce(min(event_id) FILTER (event_id % 4 <> 0), min(event_id)) AS BIGINT) AS kept,
          CASE WHEN count(*) FILTER (event_id % 4 <> 0) > 0 THEN 'ok' ELSE 'failed' END AS status FROM events GROUP BY user_id""")
def ledger_dedupe(t, spark):
    outcomes = t("events").select(F.col("user_id").alias("call_id"), F.col("event_id").alias("attempt"), F.when(F.col("event_id") % 4 == 0, "failed").otherwise("ok").alias("status"))
    counts = outcomes.groupBy("call_id").agg(F.count(F.lit(1)).alias("outcomes"))
    return first_outcomes(outcomes).join(counts, "call_id").select("call_id", "outcomes", F.col("attempt").alias("kept"), "status")


@query("SELECT o_orderkey AS call_id FROM orders WHERE o_orderstatus <> 'F' OR o_totalprice > 400000")
def ledger_missing(t, spark):
    """Orders stand for calls: finished ones were run, and those above a price failed."""
    status = F.when(F.col("o_totalprice") > 400_000, "failed").otherwise("ok")
    done = t("orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("call_id"), status.alias("status"))
    return missing_calls(t("orders").select(F.col("o_orderkey").alias("call_id")), done)


@query("""SELECT user_id AS call_id, CASE WHEN n % 41 = 3 THEN 'timed_out' WHEN n % 7 = 5 THEN 'over_memory' WHEN n % 5 = 2 THEN 'over_scratch' WHEN n % 11 = 0 THEN 'failed' ELSE 'ok' END AS verdict
          FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1)""")
def call_limit_verdicts(t, spark):
    """A call a user, which by its number of events sleeps, allocates, fills its scratch folder or fails; the worker's limits judge it."""
    from callweave.calls.spec import CallLimits

    def strain(n):
        import os
        import time

        if n % 41 == 3:
            time.sleep(60)
        if n % 7 == 5:
            return len(bytearray(2_000_000_000))
        if n % 5 == 2:
            with open(os.path.join(os.environ["CALL_SCRATCH"], "spill"), "wb") as f:
                f.truncate(20_000_000)
        elif n % 11 == 0:
            raise ValueError("bad input")
        return n

    calls = t("events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    limits = CallLimits(seconds=2, memory_mb=1000, scratch_mb=10)
    return run_map_table(calls, strain, ["n"], "long", "user_id", slots=8, clock=False, limits=limits).select("call_id", F.col("status").alias("verdict"))


@query("SELECT CAST(user_id AS VARCHAR) AS key, rpad(max_by(props, event_id), 128, '.') AS value, max(event_id) AS version FROM events GROUP BY user_id")
def kv_last_write(t, spark):
    return kv.last_write(as_key_values(t("events"), 10))


@query("""WITH last AS (SELECT CAST(user_id AS VARCHAR) AS key, max(event_id) AS version FROM events GROUP BY user_id),
          asks AS (SELECT CAST(c_custkey AS VARCHAR) AS key FROM customer)
          SELECT key, version, version IS NOT NULL AS found FROM asks LEFT JOIN last USING (key)""")
def kv_get_join(t, spark):
    asks = t("customer").select(F.col("c_custkey").cast("string").alias("key"))
    got = kv.get(kv.last_write(as_key_values(t("events"), 10)), asks)
    return got.select("key", "version", F.col("version").isNotNull().alias("found"))


@query("SELECT event_id, user_id, round(CASE WHEN user_id BETWEEN 20 AND 60 THEN value * 2 + 1 ELSE value END, 4) AS value FROM events")
def kv_range_update(t, spark):
    changed = kv.range_update(t("events"), "user_id", 20, 60, "value", lambda v: v * 2 + 1)
    return changed.select("event_id", "user_id", F.round("value", 4).alias("value"))


@query("""WITH l AS (SELECT CAST(user_id % 10 AS INTEGER) AS shard, count(*) AS n FROM events GROUP BY 1)
          SELECT shard, n, round(n / avg(n) OVER (), 6) AS skew FROM l""")
def kv_shard_load(t, spark):
    loads = kv.shard_load(as_key_values(t("events"), 10))
    mean = loads.agg(F.avg("n").alias("mean"))
    return loads.crossJoin(F.broadcast(mean)).select("shard", "n", F.round(F.col("n") / F.col("mean"), 6).alias("skew"))


@query("""SELECT user_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents, max(event_id) AS version FROM events GROUP BY user_id""")
def kv_atomic_script(t, spark):
    import pandas as pd

    puts = t("events").select("user_id", F.round(F.col("value") * 100).cast("long").alias("cents"), F.col("event_id").alias("version"))

    def add_up(key, frame):
        return pd.DataFrame({"user_id": [key], "cents": [int(frame["cents"].sum())], "version": [int(frame["version"].iloc[-1])]})

    return kv.apply_script(puts, add_up, "user_id long, cents long, version long", key="user_id")


@query("SELECT CAST(user_id AS VARCHAR) AS key, CAST(max(event_id) AS VARCHAR) AS value FROM events GROUP BY user_id")
def scan_kv_source(t, spark):
    """The last version of each user goes to live shards by the sink and comes back by the source, a partition a shard."""
    from callweave.sources.kv_live import KvCluster, driver_host
    from callweave.sources.kv_source import KvSource

    cluster = KvCluster(4, driver_host(spark))
    spark.dataSource.register(KvSource)
    where = json.dumps(cluster.addresses)
    last = kv.last_write(as_key_values(t("events"), 4)).select(F.lit(0).alias("shard"), "key", F.col("version").cast("string").alias("value"))
    last.write.format("callweave_kv").option("addresses", where).mode("append").save()
    back = settle(spark.read.format("callweave_kv").option("addresses", where).load())
    cluster.close()
    return back.select("key", "value")


@query("""WITH asks AS (SELECT event_id, user_id FROM events WHERE event_type = 'purchase'), puts AS (SELECT event_id, user_id, value FROM events WHERE event_type = 'view')
          SELECT a.event_id, a.user_id, p.event_id AS read_version, p.value FROM asks a ASOF LEFT JOIN puts p ON a.user_id = p.user_id AND a.event_id > p.event_id""")
def join_asof(t, spark):
    """Each purchase reads the user's latest earlier view: one window over both, no range join."""
    from pyspark.sql import Window

    e = t("events").where("event_type in ('purchase', 'view')")
    view = F.when(F.col("event_type") == "view", F.struct(F.col("event_id").alias("version"), "value"))
    last = F.last(view, ignorenulls=True).over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    read = e.withColumn("put", last).where("event_type = 'purchase'")
    return read.select("event_id", "user_id", F.col("put.version").alias("read_version"), F.col("put.value").alias("value"))


@query("SELECT page_id, octet_length(encode(html)) AS n_bytes, sha256(html) AS digest FROM pages")
def scan_binary_files(t, spark):
    """Pages written as objects of their own folder each, read back by the object source; digests by a call per object."""
    import hashlib

    from callweave.calls.runner import run_map_objects

    path = shared_path(spark)
    t("pages").select("page_id", F.col("html").alias("value")).repartition(4).write.option("lineSep", "\x00").partitionBy("page_id").text(path)

    def look(data):
        data = data.rstrip(b"\0")
        return {"n_bytes": len(data), "digest": hashlib.sha256(data).hexdigest()}

    out = run_map_objects(spark, look, path, "struct<n_bytes:long,digest:string>", glob="*.txt", clock=False)
    return out.select(F.regexp_extract("path", r"page_id=(\d+)", 1).cast("long").alias("page_id"), "result.n_bytes", "result.digest")


@query("SELECT user_id AS worker, event_type AS phase, count(*) AS calls FROM events GROUP BY ALL")
def trace_layout(t, spark):
    return as_trace(t("events")).groupBy("worker", "phase").agg(F.count(F.lit(1)).alias("calls"))
