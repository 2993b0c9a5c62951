import threading
import time

import pytest
from pyspark.sql import functions as F

from callweave.calls.closure import ClosureError, closure_report, pack_closure, unpack_closure
from callweave.calls.ledger import Ledger, first_outcomes, resume, submit_map
from callweave.calls.runner import assert_stateless, collect_in_order, prewarm, run_calls, run_map, run_map_expr, run_map_objects, run_map_table, serial_map, thread_map
from callweave.calls.spec import CallLimits, RetryPolicy, RuntimeSpec
from callweave.calls.vault import FunctionVault
from callweave.calls.worker import call_attempt
from callweave.sources.objects import ObjectStore, append_frame, compact_frame
from callweave.tables import shared_path


def test_map_equals_loop_and_keeps_order(spark):
    offset = 7
    f = lambda x: x * x + offset
    values = list(range(100, 0, -1))
    assert collect_in_order(run_map(spark, f, values, "long", slots=5)) == serial_map(f, values) == thread_map(f, values)


@pytest.mark.parametrize("values", [[], [3]])
def test_tiny_lists(spark, values):
    assert collect_in_order(run_map(spark, lambda x: x + 1, values, "long")) == [v + 1 for v in values]


def test_null_payload_reaches_the_function(spark):
    calls = spark.createDataFrame([(0, None), (1, "a")], "call_id long, payload string")
    assert collect_in_order(run_map(spark, lambda x: x is None, calls, "boolean")) == [True, False]


def test_failed_call_is_a_row(spark):
    rows = {r["call_id"]: r for r in run_map(spark, lambda x: 10 // x, [0, 5], "long").collect()}
    assert rows[0]["status"] == "failed" and "ZeroDivisionError" in rows[0]["error"] and rows[1]["result"] == 2
    with pytest.raises(RuntimeError, match="call 0"):
        collect_in_order(run_map(spark, lambda x: 10 // x, [0, 5], "long"))


def test_retry_sees_the_same_input(spark):
    def flaky(x, attempt):
        if attempt < 3:
            raise OSError
        return x

    out = run_map(spark, call_attempt(flaky), [4, 5], "long", retry=RetryPolicy(3), isolation="reuse").collect()
    assert [(r["result"], r["attempt"]) for r in sorted(out)] == [(4, 3), (5, 3)]
    bad = run_map(spark, lambda x: 1 / 0, [1], "double", retry=RetryPolicy(4)).first()
    assert (bad["attempt"], bad["status"]) == (4, "failed")
    once = run_map(spark, lambda x: 1 / 0, [1], "double", retry=RetryPolicy(4, retry_on=(OSError,))).first()
    assert once["attempt"] == 1


def test_limits(spark):
    def slow(x):
        time.sleep(x)
        return x

    out = run_map(spark, slow, [0.0, 5.0], "double", limits=CallLimits(seconds=0.3), slots=2)
    assert [r["status"] for r in out.orderBy("call_id").collect()] == ["ok", "timed_out"]
    fat = run_map(spark, lambda mb: len(bytearray(mb << 20)), [1, 3000], "long", limits=CallLimits(memory_mb=500))
    assert [r["status"] for r in fat.orderBy("call_id").collect()] == ["ok", "over_memory"]

    def litter(mb):
        import os

        with open(os.path.join(os.environ["CALL_SCRATCH"], "x"), "wb") as f:
            f.write(b"0" * (mb * 1_000_000))
        return mb

    out = run_map(spark, litter, [1, 4], "long", limits=CallLimits(scratch_mb=2))
    assert [r["status"] for r in out.orderBy("call_id").collect()] == ["ok", "over_scratch"]


def test_unpicklable_closure_names_the_value():
    lock = threading.Lock()
    with pytest.raises(ClosureError, match="lock"):
        pack_closure(lambda x: lock)
    assert ("closure", "lock") in [r[:2] for r in closure_report(lambda x: lock) if r[2] != "ok"]
    packed = pack_closure(lambda x: x + 1)
    assert unpack_closure(packed.data)(1) == 2 and len(packed.fn_id) == 24


def test_isolation_and_leak_probe(spark):
    seen = []

    def leaky(x):
        seen.append(x)
        return len(seen)

    fresh = run_map(spark, leaky, [1, 2, 3], "long", slots=1)
    assert collect_in_order(fresh) == [1, 1, 1]
    with pytest.raises(AssertionError, match="keeps state"):
        assert_stateless(spark, leaky, [1, 2, 3], "long")
    assert_stateless(spark, lambda x: x, [1, 2, 3], "long")


def test_mixed_functions_and_vault_restore(spark):
    vault = FunctionVault(spark)
    a, b = vault.store(lambda x: x + 1), vault.store(lambda x: x * 10)
    other = FunctionVault(spark)
    other.restore(vault.frame())
    calls = spark.createDataFrame([(0, a, 5), (1, b, 5)], "call_id long, fn_id string, payload long")
    assert collect_in_order(run_calls(calls, other, "long")) == [6, 50] and other.load(b)(2) == 20


def test_batches_table_and_expression(spark, t):
    sums = run_map(spark, lambda xs: [x + len(xs) for x in xs], list(range(10)), "long", batch_size=4, slots=1)
    assert sorted(r["result"] - r["call_id"] for r in sums.collect()) == [2, 2] + [4] * 8
    rows = t("part")
    python = run_map_table(rows, lambda p: p["p_size"] + 1, ["p_size", "p_name"], "long", "p_partkey").select("call_id", "result")
    native = run_map_expr(rows, (F.col("p_size") + 1).cast("long"), "p_partkey")
    assert python.exceptAll(native).isEmpty() and native.exceptAll(python).isEmpty()


def test_runtime_environment(spark):
    import os

    spec = RuntimeSpec(env={"CALLWEAVE_X": "7"})
    assert collect_in_order(run_map(spark, lambda x: os.environ["CALLWEAVE_X"], [1], "string", runtime=spec)) == ["7"]


def test_ledger_resume_runs_only_what_is_missing(spark):
    ledger = Ledger(spark, shared_path(spark), "j", "long")
    calls = spark.range(10).select(F.col("id").alias("call_id"), F.col("id").alias("payload"))
    assert ledger.missing(calls).count() == 10
    assert resume(calls, lambda x: x if x < 6 else 1 // 0, ledger, "long") == 4
    assert resume(calls, lambda x: -x, ledger, "long") == 0
    assert {r["call_id"]: r["result"] for r in ledger.snapshot().collect()} == {i: i if i < 6 else -i for i in range(10)}
    assert resume(calls, lambda x: 99, ledger, "long") == 0 and ledger.raw().count() == 14


def test_duplicate_outcomes_collapse(spark):
    rows = [(1, 2, "ok", 5), (1, 1, "failed", None), (1, 3, "ok", 6), (2, 1, "failed", None)]
    out = first_outcomes(spark.createDataFrame(rows, "call_id long, attempt int, status string, result long"))
    assert sorted(map(tuple, out.select("call_id", "attempt", "status", "result").collect())) == [(1, 2, "ok", 5), (2, 1, "failed", None)]


def test_background_job(spark):
    calls = spark.range(4).select(F.col("id").alias("call_id"), F.col("id").alias("payload"))
    job = submit_map(calls, lambda x: x * 2, Ledger(spark, shared_path(spark), "bg", "long"), "long")
    assert job.wait(60) and job.pending().isEmpty()
    assert sorted(r["result"] for r in job.fetch().collect()) == [0, 2, 4, 6]


def test_objects(spark):
    store = ObjectStore(spark, shared_path(spark))
    store.put("a/x.bin", b"hello")
    store.put("a/y.bin", b"\x00\xff")
    assert store.get("a/x.bin") == b"hello" and store.get("a/y.bin") == b"\x00\xff" and store.exists("a/x.bin") and store.list("a") == ["a/x.bin", "a/y.bin"]
    sizes = run_map_objects(spark, len, f"{store.root}/a", "long")
    assert sorted(r["result"] for r in sizes.collect()) == [2, 5]
    for part in (b"1", b"2", b"3"):
        store.append("log", part)
    assert store.read_parts("log") == b"123" and len(store.list("log")) == 3
    store.compact("log")
    assert store.read_parts("log") == b"123" and len(store.list("log")) == 1
    store.append("log", b"4")
    assert store.read_parts("log") == b"1234"
    assert store.delete("a/x.bin") and not store.exists("a/x.bin")
    path, target = shared_path(spark), shared_path(spark)
    for i in range(3):
        append_frame(spark.range(i, i + 1), path)
    compact_frame(spark, path, target, 1)
    assert spark.read.parquet(target).count() == 3


def test_prewarm(spark):
    assert prewarm(spark, 4) == 4
