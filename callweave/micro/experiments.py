"""The experiments end to end, at the size of the machine at hand: each returns a small result table.

Times are live. What to look for is how each measure moves with its parameter;
absolute figures belong to the machine.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.calls.runner import run_map
from callweave.learn import linear
from callweave.measures import trace as m
from callweave.micro import kernels
from callweave.operators import mapreduce, paramserver, rangesort
from callweave.tables import load, settle, shared_path, spread


def _timed(action) -> float:
    began = time.perf_counter()
    action()
    return time.perf_counter() - began


def _sink(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def compute_scaling(spark: SparkSession, workers=(1, 2, 4, 8), size: int = 384) -> DataFrame:
    """(workers, mean_gflops, total_gflops): the dense kernel on more and more workers."""
    rows = []
    for w in workers:
        r = kernels.bench_matmul(spark, w, size, 6).agg(F.avg("gflops"), F.sum("gflops")).first()
        rows.append((w, r[0], r[1]))
    return spark.createDataFrame(rows, "workers int, mean_gflops double, total_gflops double")


def object_scaling(spark: SparkSession, workers=(1, 2, 4, 8), mb: int = 24) -> DataFrame:
    """(workers, write_mb_s, read_mb_s) in total."""
    rows = []
    for w in workers:
        path, _, write = kernels.bench_object_write(spark, w, mb)
        rows.append((w, write, kernels.bench_object_read(spark, path)[1]))
    return spark.createDataFrame(rows, "workers int, write_mb_s double, read_mb_s double")


def kv_scaling(spark: SparkSession, workers=(1, 2, 4, 8), shards=(1, 4), ops: int = 300) -> DataFrame:
    """(workers, shards, pairs_per_s, latency_ms): synchronous 128-byte pairs of put and get per worker."""
    rows = []
    for s in shards:
        for w in workers:
            r = kernels.bench_kv(spark, w, ops, s).agg(F.avg("pairs_per_s"), F.avg("latency_ms")).first()
            rows.append((w, s, r[0], r[1]))
    return spark.createDataFrame(rows, "workers int, shards int, pairs_per_s double, latency_ms double")


def featurize_and_fit(spark: SparkSession, sf_dir: str, slots: int = 8, repeats: int = 3) -> DataFrame:
    """Phase times of map, gather and learn on one machine: start, set-up, featurization, fetch and fit."""
    vectors = settle(load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("call_id"), F.col("embedding").alias("payload"), "label"))

    def describe(px):
        began = time.time()
        import numpy as np

        ready = time.time()
        img = np.asarray(px, float).reshape(8, 8)[1:7, 1:7]
        dx, dy = np.diff(img, axis=1)[:-1], np.diff(img, axis=0)[:, :-1]
        energy, way = abs(dx) + abs(dy), (dx < 0) + 2 * (dy < 0)
        cell = (np.arange(5) // 3)[:, None] * 2 + np.arange(5) // 3
        out = np.bincount((cell * 4 + way).ravel(), energy.ravel(), 16)
        return {"start": began, "setup": (ready - began) * 1000, "work": (time.time() - ready) * 1000, "x": out.tolist()}

    kind = "struct<start:double,setup:double,work:double,x:array<double>>"
    rows = []
    for _ in range(repeats):
        submitted = time.time()
        done = settle(run_map(spark, describe, vectors.select("call_id", "payload"), kind, slots=slots, isolation="reuse"))
        fetched = []
        rows.append(("fetch", 1000 * _timed(lambda: fetched.append(done.join(vectors, "call_id").select("result.x", "label").toArrow()))))
        x, y = np.stack(fetched[0]["x"].to_pylist()), fetched[0]["label"].to_pylist()
        rows.append(("fit", 1000 * _timed(lambda: linear.fit_ridge(x, y))))
        calls = done.agg(F.avg("result.start"), F.avg("result.setup"), F.avg("result.work")).first()
        rows += [("start latency", 1000 * (calls[0] - submitted)), ("set-up", calls[1]), ("featurization", calls[2])]
    trace = spark.createDataFrame(rows, "phase string, duration_ms double")
    return m.phase_summary(trace)


def word_count_routes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(route, seconds, slowdown against the native plan) of the same counts."""
    docs = settle(spread(load(spark, sf_dir, "documents").select("text")))
    routes = {
        "native": lambda: mapreduce.word_count(docs),
        "native, no combiner": lambda: mapreduce.word_count(docs, combine=False),
        "native, objects": lambda: mapreduce.word_count(docs, shuffle="objects", parts=8),
        "stateless calls": lambda: mapreduce.word_count_opaque(docs, parts=8),
        "stateless calls, objects": lambda: mapreduce.word_count_opaque(docs, parts=8, shuffle="objects"),
    }
    _sink(routes["native"]())
    took = {k: min(_timed(lambda: _sink(f())) for _ in range(2)) for k, f in routes.items()}
    return spark.createDataFrame([(k, v, m.slowdown(v, took["native"])) for k, v in took.items()], "route string, seconds double, slowdown double")


def sort_sweep(spark: SparkSession, sf_dir: str, parts=(4, 8, 16), shards=(1, 4)) -> DataFrame:
    """(way, parts, shards, seconds, blocks): the range sort, run by each way over parts, and over shards for the key-value tier.

    Blocks of the key-value way are those that it put; of the others, the most that maps times ranges can make.
    """
    rows, out = load(spark, sf_dir, "lineitem"), []
    keys, maps = ["l_extendedprice", "l_orderkey", "l_linenumber"], spark.sparkContext.defaultParallelism
    for p in parts:
        for way, options in (("native", {}), ("objects", {"shuffle": "objects"}), ("two rounds", {"rounds": 2})):
            out.append((way, p, 0, _timed(lambda: rangesort.range_sort(rows, keys, p, **options)), rangesort.shuffle_files(p, options.get("rounds", 1)) * maps // p))
        for s in shards:
            held = []
            seconds = _timed(lambda: held.append(rangesort.range_sort(rows, keys, p, shuffle="kv", shards=s)))
            out.append(("kv", p, s, seconds, held[0].blocks.count()))
    return spark.createDataFrame(out, "way string, parts int, shards int, seconds double, blocks long")


def block_reads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(mode, seconds) of counting words in text objects that are read in parallel blocks, or by one task each."""
    path = shared_path(spark)
    load(spark, sf_dir, "documents").select("text").coalesce(1).write.option("compression", "none").text(path)
    count = lambda blocks: mapreduce.word_count(mapreduce.read_lines(spark, path, blocks), "line")
    took = [(mode, min(_timed(lambda: _sink(count(blocks))) for _ in range(2))) for mode, blocks in (("blocks", True), ("whole", False))]
    return spark.createDataFrame(took, "mode string, seconds double")


def training_modes(spark: SparkSession, sf_dir: str, steps: int = 120) -> DataFrame:
    """(mode, bias, slope, distance to the exact solution) of synchronous, stale, replayed and lock-free training."""
    data = settle(load(spark, sf_dir, "lineitem").select((F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 100000).alias("y")))
    a, b = paramserver.moments(data, "x", "y")
    exact, gradient = np.linalg.solve(a, b), lambda w: a @ w - b
    ends = {
        "synchronous": paramserver.train(gradient, steps, 0.2)[-1],
        "stale by 2": paramserver.train(gradient, steps, 0.2, 2)[-1],
        "stale by 2, rate too high": paramserver.train(gradient, steps, 0.55, 2)[-1],
        "replayed, 4 workers": paramserver.replay_async(gradient, steps, 4, 0.2)[-1],
        "lock-free, live": paramserver.train_async(data, "x", "y", passes=1, batch=4096, rate=0.2),
    }
    return spark.createDataFrame([(k, float(w[0]), float(w[1]), float(np.abs(w - exact).max())) for k, w in ends.items()], "mode string, bias double, slope double, distance double")


def local_against_shared(spark: SparkSession, local: str | None = None) -> DataFrame:
    """(root, write_mb_s): the same writer on a local folder and on shared storage."""
    rates = kernels.bench_local_vs_remote(spark, local or shared_path(spark), shared_path(spark), 4, 24)
    return spark.createDataFrame(list(rates.items()), "root string, write_mb_s double")


def run_all(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {
        "compute scaling": compute_scaling(spark), "object store scaling": object_scaling(spark), "key-value scaling": kv_scaling(spark), "local against shared storage": local_against_shared(spark),
        "featurize, gather, fit": featurize_and_fit(spark, sf_dir), "word count routes": word_count_routes(spark, sf_dir), "sort sweep": sort_sweep(spark, sf_dir), "block reads": block_reads(spark, sf_dir), "training modes": training_modes(spark, sf_dir),
    }
