"""Bulk-synchronous supersteps: compute, exchange, barrier; state lives in storage between steps."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.tables import settle


def bsp_run(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], supersteps: int, halt: Callable[[DataFrame, DataFrame], bool] | None = None, store_every: int = 1) -> tuple[DataFrame, int]:
    """(last state, steps done). Storing the state each `store_every` steps bounds the plan and survives lost executors."""
    done = 0
    for i in range(supersteps):
        new = step(state, i)
        if (i + 1) % store_every == 0:
            new = settle(new)
        done += 1
        stop = halt is not None and halt(state, new)
        state = new
        if stop:
            break
    return state, done


def spread_labels(edges: DataFrame, max_steps: int = 50) -> DataFrame:
    """(node, component): smallest node of each connected component of undirected (a, b) edges.

    Every step takes the least label of the neighbours and then jumps to that
    label's own label, so long chains halve.
    """
    both = settle(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    state = settle(both.select(F.col("a").alias("node")).distinct().withColumn("component", F.col("node")))

    def step(now, _):
        heard = both.join(now.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("heard"))
        least = now.join(heard, "node").select("node", F.least("component", "heard").alias("component"))
        up = least.select(F.col("node").alias("component"), F.col("component").alias("jump"))
        return least.join(up, "component").select("node", F.col("jump").alias("component"))

    def settled(old, new):
        return old.join(new.withColumnRenamed("component", "after"), "node").where("component <> after").isEmpty()

    return bsp_run(state, step, max_steps, settled)[0]


def rank_links(edges: DataFrame, steps: int = 5, damping: float = 0.85) -> DataFrame:
    """(node, rank) after `steps` rounds of link ranking over directed (src, dst); dangling ranks are not returned."""
    degrees = edges.groupBy("src").agg(F.count(F.lit(1)).alias("degree"))
    links = settle(edges.join(degrees, "src"))
    nodes = settle(edges.select(F.col("src").alias("node")).unionByName(edges.select(F.col("dst").alias("node"))).distinct())
    n = nodes.count()
    state = nodes.withColumn("rank", F.lit(1.0 / n))

    def step(now, _):
        sent = links.join(now, links.src == now.node).groupBy(F.col("dst").alias("node")).agg(F.sum(F.col("rank") / F.col("degree")).alias("got"))
        return nodes.join(sent, "node", "left").select("node", (F.lit((1 - damping) / n) + damping * F.coalesce("got", F.lit(0.0))).alias("rank"))

    return bsp_run(state, step, steps)[0]
