"""Exact quantiles per group, without all values of a group in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def exact_quantiles(df: DataFrame, by: str, value: str, shares: dict[str, float], width: float = 1e-4, accuracy: int = 100_000) -> DataFrame:
    """One row a group: `by`, and a column per share with its quantile, interpolated between neighbours by their weights.

    A sketch brackets each quantile, rows are counted between the brackets, and
    only those in the interval that holds a wanted rank are sorted: some two
    `width`s of a group's rows, equal ones counted as one before they move.
    Null values count for nothing; a group without others has null quantiles.
    The sketches, one row a group, are broadcast: groups are phases or types, of which there are few.
    """
    rows = df.select(F.col(by).alias("g"), F.col(value).cast("double").alias("v"))
    ends = sorted({min(1.0, max(0.0, s + d)) for s in shares.values() for d in (-width, width)})
    sketch = rows.groupBy("g").agg(F.percentile_approx("v", ends, accuracy).alias("ends"), F.count("v").alias("n"))
    at = sketch.select(F.col("g").alias("k"), "ends")
    interval = sum(((F.col("ends")[i] < F.col("v")).cast("int") for i in range(len(ends))), F.lit(0))
    placed = rows.where("v IS NOT NULL").join(F.broadcast(at), F.col("g").eqNullSafe(F.col("k"))).select("g", "v", interval.alias("b"))
    upward = Window.partitionBy("g").orderBy("b")
    counts = placed.groupBy("g", "b").agg(F.count(F.lit(1)).alias("c")).withColumn("upto", F.sum("c").over(upward))
    counts = counts.withColumn("n", F.max("upto").over(Window.partitionBy("g"))).withColumn("before", F.col("upto") - F.col("c"))
    ranks = {name: s * (F.col("n") - 1) for name, s in shares.items()}
    wanted = F.lit(False)
    for h in ranks.values():
        wanted = wanted | F.floor(h).between(F.col("before"), F.col("upto") - 1) | F.ceil(h).between(F.col("before"), F.col("upto") - 1)
    need = counts.where(wanted).select(F.col("g").alias("k"), F.col("b").alias("i"), "before", "n")
    kept = placed.join(F.broadcast(need), F.col("g").eqNullSafe(F.col("k")) & (F.col("b") == F.col("i")))
    kept = kept.groupBy("g", "b", "before", "n", "v").agg(F.count(F.lit(1)).alias("c"))
    kept = kept.withColumn("end", F.col("before") + F.sum("c").over(Window.partitionBy("g", "b").orderBy("v"))).withColumn("start", F.col("end") - F.col("c"))
    holds = lambda r: F.max(F.when(r.between(F.col("start"), F.col("end") - 1), F.col("v")))
    out = []
    for name, h in ranks.items():
        low, part = holds(F.floor(h)), F.max(h - F.floor(h))
        out.append(F.when(part == 0, low).otherwise(low * (1 - part) + holds(F.ceil(h)) * part).alias(name))  # by weights, as SQL's quantile_cont does
    found = kept.groupBy(F.col("g").alias("k")).agg(*out)
    return sketch.join(F.broadcast(found), F.col("g").eqNullSafe(F.col("k")), "left").select(F.col("g").alias(by), *shares)
