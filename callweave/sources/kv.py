"""The key-value tier as frames: deterministic puts, gets, range updates and scripts over (shard, key, value, version)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def shard_of(key: Column, shards: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(shards)).cast("int")


def last_write(puts: DataFrame, key: str = "key", value: str = "value", version: str = "version") -> DataFrame:
    """(key, value, version): the value of the highest version, combined before the shuffle."""
    return puts.groupBy(key).agg(F.max_by(value, version).alias(value), F.max(version).alias(version))


def get(table: DataFrame, keys: DataFrame, key: str = "key") -> DataFrame:
    """Every asked key once per ask, with its value or null."""
    return keys.join(table, key, "left")


def range_update(table: DataFrame, key: str, low, high, value: str, change: Callable[[Column], Column]) -> DataFrame:
    """One conditional projection at the side that owns the rows; nothing moves."""
    return table.withColumn(value, F.when(F.col(key).between(low, high), change(F.col(value))).otherwise(F.col(value)))


def put(table: DataFrame, puts: DataFrame, key: str = "key") -> DataFrame:
    """Table after puts: untouched keys keep their row, touched ones get their last write."""
    new = last_write(puts, key)
    return table.join(new, key, "left_anti").select(key, "value", "version").unionByName(new)


def take(table: DataFrame, keys: DataFrame, key: str = "key") -> tuple[DataFrame, DataFrame]:
    """(taken rows, table without them)."""
    return table.join(keys, key, "left_semi"), table.join(keys, key, "left_anti")


def apply_script(puts: DataFrame, script: Callable, schema: str, key: str = "key", order: str = "version") -> DataFrame:
    """Run script(key, ordered frame of its puts) -> frame per key: an atomic read-modify-write.

    A key's puts must fit a task; sums, counts and last writes have native forms that need no script.
    """

    def run(ids, frame):
        return script(ids[0], frame.sort_values(order))

    return puts.groupBy(key).applyInPandas(run, schema)


def shard_load(puts: DataFrame, shard: str = "shard") -> DataFrame:
    """(shard, n) of each shard."""
    return puts.groupBy(shard).agg(F.count(F.lit(1)).alias("n"))
