"""The record of finished calls: appended files, one visible outcome per call, restart of what is missing."""

from __future__ import annotations

import threading
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.calls.runner import outcome_schema, run_map


def first_outcomes(outcomes: DataFrame, key: str = "call_id") -> DataFrame:
    """One row per call: an "ok" one if there is any, of those the lowest attempt. Partial before the shuffle."""
    others = [c for c in outcomes.columns if c != key]
    rank = F.struct(F.when(F.col("status") == "ok", 0).otherwise(1), "attempt")
    best = outcomes.groupBy(key).agg(F.min_by(F.struct(*others), rank).alias("b"))
    return best.select(key, *[F.col(f"b.{c}").alias(c) for c in others])


def missing_calls(calls: DataFrame, done: DataFrame, key: str = "call_id") -> DataFrame:
    return calls.join(done.where("status = 'ok'").select(key), key, "left_anti")


class Ledger:
    """Outcomes of one job below `path`; a commit is a Spark append, so it is all or nothing per job."""

    def __init__(self, spark: SparkSession, path: str, job_id: str, result_type):
        self.spark, self.path, self.schema = spark, f"{path.rstrip('/')}/job_id={job_id}", outcome_schema(result_type)

    def commit(self, outcomes: DataFrame) -> None:
        outcomes.select(*self.schema.fieldNames()).write.mode("append").parquet(self.path)

    def exists(self) -> bool:
        at = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        return at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at)

    def raw(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path) if self.exists() else self.spark.createDataFrame([], self.schema)

    def snapshot(self) -> DataFrame:
        return first_outcomes(self.raw())

    def missing(self, calls: DataFrame) -> DataFrame:
        return missing_calls(calls, self.raw())


def resume(calls: DataFrame, fn: Callable, ledger: Ledger, result_type, rounds: int = 1, **options) -> int:
    """Run what the ledger lacks, up to `rounds` times; returns how many calls are still missing."""
    for _ in range(rounds):
        left = ledger.missing(calls)
        if left.isEmpty():
            return 0
        ledger.commit(run_map(calls.sparkSession, fn, left, result_type, **options))
    return ledger.missing(calls).count()


class JobHandle:
    """A map that runs in the background; done means that its outcomes are in storage."""

    def __init__(self, calls: DataFrame, fn: Callable, ledger: Ledger, result_type, options: dict):
        self.calls, self.ledger, self.error = calls, ledger, None
        self.thread = threading.Thread(target=self._run, args=(fn, result_type, options), daemon=True)
        self.thread.start()

    def _run(self, fn, result_type, options):
        try:
            resume(self.calls, fn, self.ledger, result_type, **options)
        except Exception as e:
            self.error = e

    def done(self) -> bool:
        return not self.thread.is_alive()

    def pending(self) -> DataFrame:
        return self.ledger.missing(self.calls)

    def wait(self, seconds: float | None = None) -> bool:
        self.thread.join(seconds)
        if self.error:
            raise self.error
        return self.done()

    def fetch(self) -> DataFrame:
        self.wait()
        return self.ledger.snapshot()


def submit_map(calls: DataFrame, fn: Callable, ledger: Ledger, result_type, **options) -> JobHandle:
    """Start a map over (call_id, payload) and return at once."""
    return JobHandle(calls, fn, ledger, result_type, options)
