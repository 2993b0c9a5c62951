"""Parameter sweeps, simulations with independent seeds, restarts, and optimisers that call a map in their loop."""

from __future__ import annotations

import itertools
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.calls.runner import collect_in_order, run_map


def grid(**values: list) -> list[dict]:
    """All combinations, in the order of the lists."""
    return [dict(zip(values, combo)) for combo in itertools.product(*values.values())]


def sweep(spark: SparkSession, train_fn: Callable, points: list[dict], data=None, **options) -> DataFrame:
    """(point_id, params, score): train_fn(params, data) for each point; `data` is broadcast once."""
    shared = spark.sparkContext.broadcast(data)
    scores = run_map(spark, lambda p: float(train_fn(p, shared.value)), [{k: float(v) for k, v in p.items()} for p in points], "double", **options)
    params = spark.createDataFrame([(i, {k: float(v) for k, v in p.items()}) for i, p in enumerate(points)], "call_id long, params map<string,double>")
    return scores.where("status = 'ok'").join(params, "call_id").select(F.col("call_id").alias("point_id"), "params", F.col("result").alias("score"))


def best(scores: DataFrame, by: list[str] | None = None, score: str = "score", tie: str = "point_id") -> DataFrame:
    """The row of least score (per group), ties to the smaller point."""
    others = [c for c in scores.columns if c not in (by or [])]
    top = scores.groupBy(*(by or [])).agg(F.min_by(F.struct(*others), F.struct(score, tie)).alias("b"))
    return top.select(*(by or []), "b.*")


def hashed_uniform(key: Column, salt: str, bits: int = 24) -> Column:
    """Whole number in [0, 2**24) that depends only on the key and the salt: the same on every retry."""
    digest = F.md5(F.concat(key.cast("string"), F.lit(f":{salt}")).cast("binary"))
    return F.conv(F.substring(digest, 1, bits // 4), 16, 10).cast("long")


def simulate(draws: DataFrame, value: Column) -> DataFrame:
    """(estimate, error, n) of independent draws: mean and its standard error."""
    return draws.agg(F.avg(value).alias("estimate"), (F.stddev_samp(value) / F.sqrt(F.count(value))).alias("error"), F.count(value).alias("n"))


def simulate_calls(spark: SparkSession, sim_fn: Callable[[int], float], seeds: int, **options) -> DataFrame:
    """The same for a Python simulation: one call a seed."""
    draws = run_map(spark, sim_fn, spark.range(seeds).select(F.col("id").alias("call_id"), F.col("id").alias("payload")), "double", **options)
    return simulate(draws, F.col("result"))


def best_of_restarts(spark: SparkSession, solve: Callable[[int], tuple[float, float]], seeds: int, **options) -> DataFrame:
    """(seed, loss, answer) of the seed with the least loss."""
    runs = run_map(spark, solve, list(range(seeds)), "struct<loss:double,answer:double>", **options).where("status = 'ok'")
    return best(runs.select(F.col("call_id").alias("point_id"), F.col("result.loss").alias("score"), F.col("result.answer").alias("answer")))


def optimise_loop(spark: SparkSession, evaluate: Callable[[list[float]], float], start: list[float], rounds: int = 20, population: int = 16, spread: float = 1.0, seed: int = 0, **options) -> tuple[list[float], float, list[float]]:
    """(best point, its value, best value per round): an optimiser whose costly evaluations are one parallel map a round."""
    import numpy as np

    rng = np.random.default_rng(seed)
    centre, value, trace = np.array(start, float), float("inf"), []
    for _ in range(rounds):
        points = [centre.tolist()] + [(centre + spread * rng.standard_normal(len(centre))).tolist() for _ in range(population - 1)]
        values = collect_in_order(run_map(spark, lambda p: float(evaluate(p)), points, "double", **options))
        at = int(np.argmin(values))
        if values[at] < value:
            centre, value = np.array(points[at]), values[at]
        else:
            spread *= 0.7
        trace.append(value)
    return centre.tolist(), value, trace
