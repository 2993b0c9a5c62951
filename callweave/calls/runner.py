"""Parallel map over lists, table rows, objects and expressions."""

from __future__ import annotations

import importlib
import os
from collections.abc import Callable, Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from callweave.calls.closure import pack_closure
from callweave.calls.spec import CallLimits, RetryPolicy, RuntimeSpec
from callweave.calls.vault import FunctionVault
from callweave.calls.worker import CodeCache, call_with_retry

ONCE = RetryPolicy(max_attempts=1)


def outcome_schema(result_type: str | T.DataType, clock: bool = True) -> T.StructType:
    kind = T._parse_datatype_string(result_type) if isinstance(result_type, str) else result_type
    fields = [("call_id", T.LongType()), ("attempt", T.IntegerType()), ("status", T.StringType()), ("result", kind), ("error", T.StringType())]
    return T.StructType([T.StructField(n, t) for n, t in fields + [("elapsed_ms", T.DoubleType())] * clock])


def _deal(df: DataFrame, slots: int | None) -> DataFrame:
    """Spread calls by the hash of their id, so that a recomputed partition holds the same calls."""
    return df.repartition(slots, "call_id") if slots else df


def run_calls(
    calls: DataFrame,
    vault: FunctionVault,
    result_type: str | T.DataType,
    *,
    limits: CallLimits | None = None,
    retry: RetryPolicy = ONCE,
    slots: int | None = None,
    batch_size: int | None = None,
    isolation: str = "fresh",
    runtime: RuntimeSpec | None = None,
    clock: bool = True,
) -> DataFrame:
    """Run rows (call_id, fn_id, payload): each may name another function of the vault.

    `batch_size` above one hands the function a list of payloads and expects a
    list of results. Outcomes are rows (call_id, attempt, status, result, error,
    elapsed_ms); a failed call is a row, not a failed job.
    """
    if runtime:
        runtime.install(calls.sparkSession)
    code, env, packages = vault.broadcast(), dict(runtime.env) if runtime else {}, runtime.packages if runtime else ()
    size = batch_size or 1

    def loop(frames: Iterable[pd.DataFrame]):
        os.environ.update(env)
        for name in packages:
            importlib.import_module(name)
        cache = CodeCache(code.value, isolation)
        for frame in frames:
            out = []
            ids, fns, payloads = frame["call_id"].tolist(), frame["fn_id"].tolist(), frame["payload"].tolist()
            if size == 1:
                for call_id, fn_id, value in zip(ids, fns, payloads):
                    out.append((call_id, *call_with_retry(cache.getter(fn_id), value, limits, retry)))
            else:
                for at in range(0, len(ids), size):
                    n, status, results, error, ms = call_with_retry(cache.getter(fns[at]), payloads[at : at + size], limits, retry)
                    group = ids[at : at + size]
                    results = results if status == "ok" else [None] * len(group)
                    out += [(i, n, status, r, error, ms / len(group)) for i, r in zip(group, results)]
            columns = ["call_id", "attempt", "status", "result", "error", "elapsed_ms"]
            done = pd.DataFrame(out, columns=columns, dtype=object)
            yield done if clock else done[columns[:-1]]

    dealt = _deal(calls.select(F.col("call_id").cast("long"), "fn_id", "payload"), slots)
    return dealt.mapInPandas(loop, outcome_schema(result_type, clock))


def run_map(spark: SparkSession, fn: Callable, elements: Iterable | DataFrame, result_type, **options) -> DataFrame:
    """One call per element of an in-memory list, or per row of a frame (call_id, payload)."""
    if not isinstance(elements, DataFrame):
        rows = list(enumerate(elements))
        elements = spark.createDataFrame(rows, ["call_id", "payload"]) if rows else spark.createDataFrame([], "call_id long, payload long")
    vault = FunctionVault(spark)
    fn_id = vault.store(fn)
    return run_calls(elements.withColumn("fn_id", F.lit(fn_id)), vault, result_type, **options)


def run_map_table(df: DataFrame, fn: Callable, cols: list[str], result_type, id_col: str, **options) -> DataFrame:
    """One call per table row; only `cols` reach Python, as a dictionary (one column: the bare value)."""
    payload = F.col(cols[0]) if len(cols) == 1 else F.struct(*cols)
    return run_map(df.sparkSession, fn, df.select(F.col(id_col).cast("long").alias("call_id"), payload.alias("payload")), result_type, **options)


def run_map_objects(spark: SparkSession, fn: Callable, path: str, result_type, glob: str = "*", **options) -> DataFrame:
    """One call per stored object below `path`: fn(bytes). Outcomes carry the object's path."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", glob).option("recursiveFileLookup", "true").load(path)
    calls = files.select(F.xxhash64("path").alias("call_id"), F.col("content").alias("payload"))
    return run_map(spark, lambda b: fn(bytes(b)), calls, result_type, **options).join(files.select(F.xxhash64("path").alias("call_id"), "path"), "call_id")


def run_map_expr(df: DataFrame, result: Column, id_col: str) -> DataFrame:
    """The native map: an expression per row, inside generated code."""
    return df.select(F.col(id_col).cast("long").alias("call_id"), result.alias("result"))


def collect_in_order(outcomes: DataFrame) -> list:
    """Results in the order of the input list; raises if a call failed. For lists that the caller could hold before."""
    rows = outcomes.orderBy("call_id").collect()
    bad = next((r for r in rows if r["status"] != "ok"), None)
    if bad:
        raise RuntimeError(f"call {bad['call_id']}: {bad['status']}: {bad['error']}")
    return [r["result"] for r in rows]


def serial_map(fn: Callable, values: Iterable) -> list:
    """The plain loop that a parallel map must equal."""
    return [fn(v) for v in values]


def thread_map(fn: Callable, values: Iterable, threads: int = 8) -> list:
    from concurrent.futures import ThreadPoolExecutor

    with ThreadPoolExecutor(threads) as pool:
        return list(pool.map(fn, values))


def assert_stateless(spark: SparkSession, fn: Callable, values: list, result_type) -> None:
    """Raise if results differ between a forward and a backward pass in one worker: state leaked from call to call."""
    n = len(values)
    forth = collect_in_order(run_map(spark, fn, values, result_type, isolation="reuse", slots=1))
    back = collect_in_order(run_map(spark, fn, values[::-1], result_type, isolation="reuse", slots=1))
    if forth != back[::-1]:
        raise AssertionError(f"{pack_closure(fn).name} keeps state between its {n} calls")


def prewarm(spark: SparkSession, slots: int) -> int:
    """Start `slots` Python workers before there is input; returns how many answered."""
    return spark.range(slots, numPartitions=slots).mapInPandas(lambda frames: frames, "id long").count()
