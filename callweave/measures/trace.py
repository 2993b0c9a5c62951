"""Measures over task traces (call_id, worker, phase, start_us, duration_ms, bytes)."""

from __future__ import annotations

import heapq
from decimal import Decimal

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from callweave.measures.quantiles import exact_quantiles


def phase_summary(trace: DataFrame, digits: int = 4) -> DataFrame:
    """Count, mean, sample standard deviation and 95th percentile of each phase's time."""
    d = F.col("duration_ms")
    p95 = exact_quantiles(trace, "phase", "duration_ms", {"p95_ms": 0.95}).withColumnRenamed("phase", "k")
    each = trace.groupBy("phase").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(d), digits).alias("mean_ms"), F.round(F.stddev_samp(d), digits).alias("std_ms"))
    return each.join(F.broadcast(p95), F.col("phase").eqNullSafe(F.col("k")), "left").select(*each.columns, F.round("p95_ms", digits).alias("p95_ms"))


def makespan(trace: DataFrame) -> DataFrame:
    """One row: first start, last end, elapsed milliseconds."""
    end = F.max(F.col("start_us") + F.round(F.col("duration_ms") * 1000).cast("long"))
    return trace.agg(F.min("start_us").alias("start_us"), end.alias("end_us")).withColumn("elapsed_ms", (F.col("end_us") - F.col("start_us")) / 1000)


def slowdown(ours: float, theirs: float) -> float:
    return ours / theirs - 1


def throughput(trace: DataFrame, work: str = "bytes") -> DataFrame:
    """Rate per worker (its work by its busy time), and the means and totals over workers, in one row."""
    each = trace.groupBy("worker").agg((F.sum(work) / F.sum("duration_ms") * 1000).alias("rate"))
    return each.agg(F.count(F.lit(1)).alias("workers"), F.avg("rate").alias("mean_rate"), F.sum("rate").alias("total_rate"))


def linearity(points: DataFrame, x: str, y: str) -> DataFrame:
    return points.agg(F.regr_slope(y, x).alias("slope"), F.regr_r2(y, x).alias("r2"))


def concurrency_steps(trace: DataFrame, bucket_us: int = 86_400_000_000) -> DataFrame:
    """(at_us, active, lasts_us) after each change of the number of running calls; ends count before starts at equal times.

    Changes are summed per instant, then carried over time buckets, so the
    running sum is made within buckets and one small window over their totals.
    """
    end = F.col("start_us") + F.round(F.col("duration_ms") * 1000).cast("long")
    changes = trace.select(F.explode(F.array(F.struct(F.col("start_us").alias("at_us"), F.lit(1).alias("d")), F.struct(end.alias("at_us"), F.lit(-1).alias("d")))).alias("c"))
    instants = changes.groupBy(F.col("c.at_us").alias("at_us")).agg(F.sum("c.d").alias("d")).withColumn("bucket", F.floor(F.col("at_us") / bucket_us))
    totals = instants.groupBy("bucket").agg(F.sum("d").alias("total"), F.min("at_us").alias("first_us"))
    order = Window.orderBy("bucket")
    carried = totals.select(
        "bucket", F.coalesce(F.sum("total").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.lead("first_us").over(order).alias("next_us")
    )
    inside = Window.partitionBy("bucket").orderBy("at_us")
    return instants.join(carried, "bucket").select(
        "at_us", (F.col("before") + F.sum("d").over(inside)).alias("active"), (F.coalesce(F.lead("at_us").over(inside), "next_us") - F.col("at_us")).alias("lasts_us")
    )


def concurrency(trace: DataFrame) -> DataFrame:
    """One row: most calls at once, and the mean over time."""
    s = concurrency_steps(trace)
    return s.agg(F.max("active").alias("peak"), (F.sum(F.col("active") * F.col("lasts_us")) / F.sum("lasts_us")).alias("mean_active"))


def latency_quantiles(trace: DataFrame, shares=(0.5, 0.9, 0.99)) -> DataFrame:
    return exact_quantiles(trace, "phase", "duration_ms", {f"p{round(s * 100)}": s for s in shares})


def time_breakdown(trace: DataFrame) -> DataFrame:
    """Mean time per call of each phase, and its share of all time."""
    each = trace.groupBy("phase").agg(F.sum("duration_ms").alias("total_ms"), F.avg("duration_ms").alias("mean_ms"))
    return each.withColumn("share", F.col("total_ms") / F.sum("total_ms").over(Window.partitionBy(F.lit(1))))


def overhead_share(trace: DataFrame, overhead: list[str]) -> DataFrame:
    part = F.sum(F.when(F.col("phase").isin(overhead), F.col("duration_ms")).otherwise(0.0))
    return trace.agg((part / F.sum("duration_ms")).alias("overhead_share"))


def flag_stragglers(trace: DataFrame, ratio: float = 1.5, time: str = "duration_ms") -> DataFrame:
    """Calls that took over `ratio` times their phase's median (one row a phase is broadcast).

    `time` is compared in the unit it is stored in: a call right at the bound may
    fall on its other side once both are multiplied and rounded.
    """
    medians = exact_quantiles(trace, "phase", time, {"median": 0.5})
    return trace.join(F.broadcast(medians), "phase").where(F.col(time) > ratio * F.col("median"))


def histogram(df: DataFrame, value: Column, width: float, low: float = 0.0) -> DataFrame:
    return df.groupBy(F.floor((value - low) / width).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def relative_change(df: DataFrame, order: str, value: str) -> DataFrame:
    """`df` with the change of `value` against the row before; for small result tables."""
    before = F.lag(value).over(Window.orderBy(order))
    return df.withColumn("change", F.col(value) / before - 1)


def wave_makespan(trace: DataFrame, slots: list[int]) -> DataFrame:
    """(p, makespan_ms, efficiency) if call i runs on slot i mod p, for each p."""
    each = trace.select("call_id", "duration_ms", F.explode(F.array(*map(F.lit, slots))).alias("p"))
    per_slot = each.groupBy("p", F.pmod("call_id", F.col("p")).alias("slot")).agg(F.sum("duration_ms").alias("busy"))
    out = per_slot.groupBy("p").agg(F.max("busy").alias("makespan_ms"), F.sum("busy").alias("work_ms"))
    return out.select("p", "makespan_ms", (F.col("work_ms") / (F.col("p") * F.col("makespan_ms"))).alias("efficiency"))


def ideal_makespan(calls: int | Column, slots: int | Column, seconds: float) -> float | Column:
    """Time of equal calls in waves: as many slots as calls take one call's time."""
    waves = F.ceil(calls / slots) if isinstance(calls, Column) else -(-calls // slots)
    return waves * seconds


def greedy_makespan(durations: list[float], slots: int) -> float:
    """List scheduling: each call to the slot that is free first."""
    free = [0.0] * slots
    for d in durations:
        heapq.heapreplace(free, free[0] + d)
    return max(free)


# Money and resources


def call_charge(duration_ms: Column, gb: Decimal = Decimal("1.5"), gb_hour: Decimal = Decimal("0.06"), step_ms: int = 100) -> Column:
    """Price of a call: started steps times the price of one."""
    price = (gb * gb_hour * step_ms / Decimal(3_600_000)).quantize(Decimal("0.0000001"))
    return (F.ceil(duration_ms / step_ms).cast("decimal(18,0)") * F.lit(price)).cast("decimal(28,7)")


def node_charge(shards: Column, node_hour: Decimal, seconds: Column) -> Column:
    """Hourly nodes, prorated by started seconds."""
    return (shards.cast("decimal(18,0)") * F.lit(node_hour).cast("decimal(18,8)") * F.ceil(seconds).cast("decimal(18,0)") / F.lit(3600)).cast("decimal(28,7)")


def job_cost(trace: DataFrame, shards: int, node_hour: Decimal, seconds: float, **price) -> DataFrame:
    """One row: charge of the calls, of the key-value nodes, and of both."""
    calls = trace.agg(F.sum(call_charge(F.col("duration_ms"), **price)).alias("calls_usd"))
    nodes = node_charge(F.lit(shards), node_hour, F.lit(seconds))
    return calls.withColumn("nodes_usd", nodes).withColumn("total_usd", F.col("calls_usd") + F.col("nodes_usd"))


def servers_cheaper(premium: float | Column, utilisation: float | Column) -> bool | Column:
    """Whether servers used to `utilisation` cost less than functions at `premium` times their price."""
    return utilisation * premium > 1


def balance(memory_mb: Column, mb_per_s: Column, limit_s: Column) -> dict[str, Column]:
    """Fill and flush memory once: seconds of reading, writing, compute, and the share of I/O."""
    fill = memory_mb / mb_per_s
    return {"fill_s": fill, "flush_s": fill, "compute_s": limit_s - 2 * fill, "io_share": 2 * fill / limit_s}


def memory_for(limit_s: float, mb_per_s: float, io_share: float) -> float:
    """Memory that a call fills and flushes in its share of I/O."""
    return mb_per_s * limit_s * io_share / 2


def predict_cost(trace: DataFrame, fit: Column, work: str = "bytes") -> DataFrame:
    """One row: charges predicted from a line fitted on the calls where `fit` holds, and charged, for the others."""
    line = trace.where(fit).agg(F.regr_intercept("duration_ms", work).alias("a"), F.regr_slope("duration_ms", work).alias("b"))
    rest = trace.where(~fit).crossJoin(F.broadcast(line))
    guess = F.greatest(F.col("a") + F.col("b") * F.col(work), F.lit(0.0))
    return rest.agg(F.sum(guess).alias("predicted_ms"), F.sum("duration_ms").alias("actual_ms"), F.sum(call_charge(F.col("duration_ms"))).alias("charged_usd"))


def shard_skew(loads: DataFrame) -> DataFrame:
    return loads.agg(F.max("n").alias("most"), F.avg("n").alias("mean"), (F.max("n") / F.avg("n")).alias("skew"))
