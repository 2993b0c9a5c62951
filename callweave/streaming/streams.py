"""Streams: replayed tables, windows, sessions, joins, keyed state, and functions triggered by arriving files."""

from __future__ import annotations

from collections.abc import Callable
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from callweave.tables import exists, shared_path


def replay(df: DataFrame, files: int, order: str, path: str | None = None, one_per_batch: bool = True) -> DataFrame:
    """A stream of `df`: files in the order of a column, one to a micro-batch, oldest first.

    The table is cut by time ranges of `order`, each written on its own so that
    files age in their order.
    """
    spark, path = df.sparkSession, path or shared_path(df.sparkSession)
    bounds = df.agg(F.percentile_approx(order, [i / files for i in range(1, files)], 10_000)).first()[0] if files > 1 else []
    low = None
    for high in [*(bounds or []), None]:
        part = df if low is None else df.where(F.col(order) > low)
        part = part if high is None else part.where(F.col(order) <= high)
        part.coalesce(1).write.mode("append").parquet(path)
        low = high
    return read_stream(spark, df.schema, path, one_per_batch)


def read_stream(spark: SparkSession, schema, path: str, one_per_batch: bool = True) -> DataFrame:
    reader = spark.readStream.schema(schema)
    if one_per_batch:
        reader = reader.option("maxFilesPerTrigger", 1)
    return reader.parquet(path)


def settle_stream(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Run all available input to the end and return the final rows as a table.

    Append goes to files. For update and complete each micro-batch is stored
    with its number; of complete the last batch counts, of update each key's
    last row.
    """
    spark, path, log = stream.sparkSession, shared_path(stream.sparkSession), shared_path(stream.sparkSession)
    schema = stream.schema
    if mode == "append":
        run_to_end(spark, stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", log).outputMode("append"))
        return spark.read.schema(schema).parquet(path)

    def store(batch, number):
        batch.withColumn("__batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    run_to_end(spark, stream.writeStream.foreachBatch(store).option("checkpointLocation", log).outputMode(mode))
    rows = spark.read.schema(schema.add("__batch", "long")).parquet(f"{path}/*")
    if mode == "complete":
        last = rows.agg(F.max("__batch").alias("__last"))
        return rows.join(F.broadcast(last), F.col("__batch") == F.col("__last")).drop("__batch", "__last")
    others = [c for c in rows.columns if c not in keys and c != "__batch"]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*others), "__batch").alias("s")).select(*keys, "s.*")


@contextmanager
def state_partitions(spark: SparkSession):
    """Start streams with no more state partitions than slots: state is not coalesced as batch shuffles are.

    A stream keeps the number that it starts with, in its log too, so a restart
    on a larger cluster keeps it as well.
    """
    key, slots = "spark.sql.shuffle.partitions", max(8, spark.sparkContext.defaultParallelism)
    before = spark.conf.get(key)
    spark.conf.set(key, str(min(int(before), slots)))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def run_to_end(spark: SparkSession, writer) -> None:
    with state_partitions(spark):
        q = writer.trigger(availableNow=True).start()
    q.awaitTermination()


def with_time(df: DataFrame, col: str = "ts") -> DataFrame:
    """Watermarks need timestamps with a zone."""
    return df.withColumn(col, F.col(col).cast("timestamp"))


def count_windows(stream: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start_us, event_type, n, total) of tumbling or sliding windows."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    agg = stream.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return agg.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n", "total")


def sessions(stream: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """(user_id, start_us, end_us, n): sessions end after `gap` without an event."""
    agg = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.max("ts").alias("last"))
    return agg.select("user_id", F.unix_micros("w.start").alias("start_us"), F.unix_micros("last").alias("end_us"), "n")


def running_counts(stream: DataFrame) -> DataFrame:
    """(user_id, n, total_cents) after each batch of the user's events, by keyed state."""

    def fold(key, frames, state: GroupState):
        n, cents = state.get if state.exists else (0, 0)
        for f in frames:
            n, cents = n + len(f), cents + int((f["value"] * 100).round().sum())
        state.update((n, cents))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total_cents": [cents]})

    return stream.groupBy("user_id").applyInPandasWithState(fold, "user_id long, n long, total_cents long", "n long, cents long", "update", GroupStateTimeout.NoTimeout)


def on_arrival(stream: DataFrame, fn: Callable[[DataFrame], DataFrame], path: str, checkpoint: str) -> None:
    """Run `fn` on each arriving batch and store what it returns once: a batch that is run again after a restart overwrites its own folder."""

    def store(batch, number):
        fn(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    run_to_end(stream.sparkSession, stream.writeStream.foreachBatch(store).option("checkpointLocation", checkpoint))


def stream_training(stream: DataFrame, x: str | list[str], y: str, rate: float, model: str, log: str, start=None) -> DataFrame:
    """(version, idx, weight) of a linear model, bias first, whose rows arrive as a stream: one update a micro-batch.

    Micro-batch n reads version n of the folder `model` and overwrites version
    n + 1, so a batch that runs again after a crash changes nothing, and a
    restart with the same `log` goes on from the stored version. A batch without
    rows repeats its version.
    """
    from callweave.operators.paramserver import gradient_step

    spark, size = stream.sparkSession, 2 if isinstance(x, str) else len(x) + 1
    schema = "version long, idx int, weight double"

    def store(version, weights):
        rows = [(version, i, float(w)) for i, w in enumerate(weights)]
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{model}/{version:012d}")

    def update(batch, number):
        w = np.array([r["weight"] for r in spark.read.schema(schema).parquet(f"{model}/{number:012d}").orderBy("idx").collect()])
        store(number + 1, w - rate * gradient_step(batch, x, y, w))

    if not exists(spark, f"{model}/{0:012d}/_SUCCESS"):
        store(0, np.zeros(size) if start is None else start)
    run_to_end(spark, stream.writeStream.foreachBatch(update).option("checkpointLocation", log))
    return spark.read.schema(schema).parquet(f"{model}/*")
