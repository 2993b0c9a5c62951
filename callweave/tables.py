"""Tables of a data folder, and tables in the folder that driver and executors share."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_path(spark: SparkSession) -> str:
    """A new path below spark.checkpoint.dir, or below the warehouse where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/callweave_scratch"
    return f"{base.rstrip('/')}/cw-{uuid.uuid4().hex}"


def settle(df: DataFrame) -> DataFrame:
    """Write to the shared folder and read back: later readers neither repeat the work nor see it differ."""
    path = shared_path(df.sparkSession)
    df.write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._shared_path = path
    return back


def forget(df: DataFrame) -> None:
    """Delete what settle() stored, once no frame reads it any more."""
    path = getattr(df, "_shared_path", None)
    if path:
        delete(df.sparkSession, path)


def exists(spark: SparkSession, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def qualified(spark: SparkSession, path: str) -> str:
    """The path with the file system that Spark takes it for."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).makeQualified(at).toString()


def delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def bucketed(df: DataFrame, parts: int, *keys: str):
    """`df` written by each of its tasks as an object for every bucket of `keys`, and read back a bucket to a task.

    This is a shuffle by storage: M tasks leave up to M * parts objects, and an
    aggregate or window by `keys` over what is read needs no exchange. Objects
    and their table end with the block.
    """
    spark, path, name = df.sparkSession, shared_path(df.sparkSession), f"cw_{uuid.uuid4().hex}"
    df.write.format("parquet").bucketBy(parts, *keys).option("path", path).saveAsTable(name)
    try:
        yield spark.table(name)
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        delete(spark, path)


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """Deal out the rows of a table whose row groups are fewer than the session's slots; others pass as they are.

    A scan can't be cut below a row group (128 MB by default), so a table of one
    small file would keep one slot busy. Larger tables are never shuffled here.
    """
    slots = df.sparkSession.sparkContext.defaultParallelism
    groups = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) >> 27
    if groups >= slots:
        return df
    files = len(df.inputFiles())
    return df.repartition(slots, *keys) if 0 < files < slots else df


def as_trace(events: DataFrame) -> DataFrame:
    """Task trace: (call_id, worker, phase, start_us, duration_ms, bytes) from the event table."""
    return events.select(
        F.col("event_id").alias("call_id"),
        F.col("user_id").alias("worker"),
        F.col("event_type").alias("phase"),
        F.unix_micros(F.col("ts").cast("timestamp")).alias("start_us"),
        (F.col("value") * 1000).alias("duration_ms"),
        F.length("props").cast("bigint").alias("bytes"),
    )


def as_key_values(events: DataFrame, shards: int) -> DataFrame:
    """Puts of 128-byte values: (shard, key, value, version) from the event table."""
    return events.select(
        F.pmod("user_id", F.lit(shards)).cast("int").alias("shard"),
        F.col("user_id").cast("string").alias("key"),
        F.rpad("props", 128, ".").alias("value"),
        F.col("event_id").alias("version"),
    )
