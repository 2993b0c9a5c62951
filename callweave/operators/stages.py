"""Stage graphs: which calls wait on which, and pools for branches that may run at once."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import SparkSession


def plan_stages(waits_on: dict[str, list[str]]) -> list[list[str]]:
    """Levels of a graph: a stage stands one level below the last of those it waits on. Cycles raise."""
    level: dict[str, int] = {}
    left = {k: set(v) for k, v in waits_on.items()}
    for d in {x for v in waits_on.values() for x in v} - set(left):
        left[d] = set()
    depth = 0
    while left:
        ready = sorted(k for k, v in left.items() if not v)
        if not ready:
            raise ValueError(f"cycle among {sorted(left)}")
        for k in ready:
            level[k] = depth
            del left[k]
        for v in left.values():
            v.difference_update(ready)
        depth += 1
    return [sorted(k for k, d in level.items() if d == i) for i in range(depth)]


def run_stages(spark: SparkSession, waits_on: dict[str, list[str]], work: dict[str, Callable[[dict], object]]) -> dict[str, object]:
    """Run each level's stages at once, each in a scheduler pool of its own; a stage gets the results so far."""
    done: dict[str, object] = {}
    for names in plan_stages(waits_on):

        def one(name):
            spark.sparkContext.setLocalProperty("spark.scheduler.pool", name)
            return name, work[name](done)

        with ThreadPoolExecutor(len(names)) as pool:
            for name, result in list(pool.map(inheritable_thread_target(spark)(one), names)):
                done[name] = result
    return done
