"""Micro-benchmarks of the building blocks: compute, object I/O, key-value operations, launch. Times are live, never oracle-checked."""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.sources.kv_live import KvClient, KvCluster, driver_host
from callweave.tables import shared_path


def bench_matmul(spark: SparkSession, workers: int, size: int = 256, repeats: int = 4) -> DataFrame:
    """(worker, gflops) of a dense product in each of `workers` tasks."""

    def run(frames):
        import numpy as np

        for frame in frames:
            out = []
            for w in frame["id"]:
                a = np.random.default_rng(w).random((size, size))
                began = time.perf_counter()
                for _ in range(repeats):
                    a = a @ a / size
                out.append((w, 2 * size**3 * repeats / (time.perf_counter() - began) / 1e9))
            yield pd.DataFrame(out, columns=["worker", "gflops"])

    return spark.range(workers, numPartitions=workers).mapInPandas(run, "worker long, gflops double")


def bench_object_write(spark: SparkSession, workers: int, mb: int = 8, path: str | None = None) -> tuple[str, float, float]:
    """(path, seconds, MB/s in total) of `workers` tasks writing incompressible blocks of one MB through the storage layer."""
    path = path or shared_path(spark)

    def fill(batches):
        import os

        import pyarrow as pa

        for b in batches:
            for _ in range(b.num_rows):
                yield pa.RecordBatch.from_arrays([pa.array([os.urandom(1_000_000)], pa.binary())], ["block"])

    blocks = spark.range(workers * mb, numPartitions=workers).mapInArrow(fill, "block binary")
    began = time.perf_counter()
    blocks.write.option("compression", "none").parquet(path)
    seconds = time.perf_counter() - began
    return path, seconds, workers * mb / seconds


def bench_object_read(spark: SparkSession, path: str) -> tuple[float, float]:
    """(seconds, MB/s) of reading the written objects."""
    began = time.perf_counter()
    size = spark.read.parquet(path).agg(F.sum(F.octet_length("block"))).first()[0]
    seconds = time.perf_counter() - began
    return seconds, size / 1e6 / seconds


def bench_local_vs_remote(spark: SparkSession, local: str, remote: str, workers: int = 4, mb: int = 8) -> dict[str, float]:
    """MB/s of the same writer at two roots."""
    return {name: bench_object_write(spark, workers, mb, f"{root.rstrip('/')}/bench-{time.time_ns()}")[2] for name, root in (("local", local), ("remote", remote))}


def bench_kv(spark: SparkSession, workers: int, ops: int = 200, shards: int = 2, value_bytes: int = 128) -> DataFrame:
    """(worker, ops, pairs_per_s, latency_ms): synchronous put and get pairs; a pair is two operations."""
    cluster = KvCluster(shards, driver_host(spark))
    addresses = cluster.addresses

    def run(frames):
        for frame in frames:
            out = []
            for w in frame["id"]:
                client, value = KvClient(addresses), b"x" * value_bytes
                began = time.perf_counter()
                for i in range(ops):
                    client.put((int(w), i), value)
                    client.get((int(w), i))
                took = time.perf_counter() - began
                client.close()
                out.append((w, 2 * ops, ops / took, took / (2 * ops) * 1000))
            yield pd.DataFrame(out, columns=["worker", "ops", "pairs_per_s", "latency_ms"])

    rows = spark.range(workers, numPartitions=workers).mapInPandas(run, "worker long, ops long, pairs_per_s double, latency_ms double").collect()
    cluster.close()
    return spark.createDataFrame(rows)


def bench_launch(spark: SparkSession, calls: int = 8) -> dict[str, float]:
    """Milliseconds to the first answer of a cold and of a warm set of workers."""
    out = {}
    for mode in ("first", "warm"):
        began = time.perf_counter()
        spark.range(calls, numPartitions=calls).mapInPandas(lambda frames: frames, "id long").count()
        out[mode] = (time.perf_counter() - began) * 1000
    return out
