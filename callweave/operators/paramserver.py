"""Parameter servers for linear least squares: synchronous, with bounded staleness, replayed and live lock-free training."""

from __future__ import annotations

import json
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.operators.gather import TooLarge
from callweave.sources.kv_live import KvClient, KvCluster, new_secret


def moments(df: DataFrame, x: str, y: str) -> tuple[np.ndarray, np.ndarray]:
    """A and b of the gradient A w - b for weights (bias, slope): means over the table, one aggregate."""
    r = df.agg(F.avg(x), F.avg(F.col(x) * F.col(x)), F.avg(y), F.avg(F.col(x) * F.col(y))).first()
    return np.array([[1.0, r[0]], [r[0], r[1]]]), np.array([r[2], r[3]])


def gradient_step(df: DataFrame, x: str | list[str], y: str, w) -> np.ndarray:
    """Full-batch gradient at `w` (bias first): the model goes out as literals, a sum a weight comes back. No limit of rows."""
    names = [x] if isinstance(x, str) else list(x)
    miss = sum((F.lit(float(v)) * F.col(c) for v, c in zip(w[1:], names)), F.lit(float(w[0]))) - F.col(y)
    r = df.agg(F.avg(miss), *[F.avg(miss * F.col(c)) for c in names]).first()
    return np.array([0.0 if v is None else v for v in r])


def train(gradient: Callable[[np.ndarray], np.ndarray], steps: int, rate: float, staleness: int = 0, start=(0.0, 0.0)) -> list[np.ndarray]:
    """All versions of the model. Step t uses version t - staleness; zero is the synchronous case."""
    versions = [np.array(start, float)]
    for t in range(steps):
        versions.append(versions[-1] - rate * gradient(versions[max(0, t - staleness)]))
    return versions


def replay_async(gradient: Callable[[np.ndarray], np.ndarray], steps: int, workers: int, rate: float, start=(0.0, 0.0)) -> list[np.ndarray]:
    """Lock-free training in a fixed interleaving: `workers` read one version and apply their gradients one after another."""
    versions = [np.array(start, float)]
    for j in range(steps // workers):
        read = versions[j * workers]
        for _ in range(workers):
            versions.append(versions[-1] - rate / workers * gradient(read))
    return versions


def stable_rate(largest_eigenvalue: float, staleness: int) -> float:
    """Learning rates below this converge under a constant delay."""
    return 2 * np.cos(np.pi * staleness / (2 * staleness + 1)) / largest_eigenvalue


def _pull(state, start, version):
    """At a shard: its block of a version, the newest for None; nothing while the version isn't there."""
    state = state or {"at": 0, "w": {0: start}, "sums": {}}
    return state, state["w"].get(state["at"] if version is None else version)


def _join(state, step, part, workers, rate, keep):
    """At a shard: the last worker's part of a step makes the next version; versions older than `keep` steps go."""
    total, n = state["sums"].pop(step, (0.0, 0))
    if n + 1 < workers:
        state["sums"][step] = total + part, n + 1
    else:
        state["w"][step + 1] = state["w"][step] - rate * (total + part)
        state["at"] = step + 1
        if keep is not None:
            state["w"].pop(step - keep, None)
    return state, None


def _nudge(state, update):
    """At a shard: an update takes effect at once, whatever version it was computed from."""
    state["w"][0] = state["w"][0] + update
    return state, None


class _Model:
    """A worker's view of a model whose blocks lie on shards."""

    def __init__(self, addresses, start):
        from pyspark import cloudpickle

        self.client, self.blocks = KvClient(addresses), np.array_split(np.asarray(start, float), len(addresses))
        self.ends = np.cumsum([len(b) for b in self.blocks])[:-1]
        self.code = {f: cloudpickle.dumps(f) for f in (_pull, _join, _nudge)}

    def _call(self, shard: int, fn, *args):
        return self.client.call("model", self.code[fn], *args, shard=shard)

    def pull(self, version: int | None = None) -> np.ndarray:
        out = []
        for shard, block in enumerate(self.blocks):
            while (got := self._call(shard, _pull, block, version)) is None:
                time.sleep(0.0005)
            out.append(got)
        return np.concatenate(out)

    def push(self, fn, vector: np.ndarray, before: tuple = (), after: tuple = ()) -> None:
        for shard, part in enumerate(np.split(vector, self.ends)):
            self._call(shard, fn, *before, part, *after)


def _with_shards(df: DataFrame, x, y: str, start, loop: Callable, versions: list | None, shards: int, workers: int, worker_bytes: int) -> np.ndarray:
    """Run loop(model, rows with a leading one, targets, all rows, workers) in concurrent tasks, the first of which host the shards.

    The tasks are one barrier stage: they need `workers` free slots at a time,
    and a lost one starts all again, with new shards, so that no update counts
    twice. Returns the model, or the versions asked for, a row each.
    """
    names, secret = [x] if isinstance(x, str) else list(x), new_secret()
    workers = min(workers, df.sparkSession.sparkContext.defaultParallelism)
    shards, start = min(shards, workers), np.zeros(len(names) + 1) if start is None else np.asarray(start, float)

    def work(frames):
        import pandas as pd
        from pyspark import BarrierTaskContext

        task, parts, size = BarrierTaskContext.get(), [], 0
        for frame in frames:
            parts.append(frame.to_numpy(float))
            size += parts[-1].nbytes
            if size > worker_bytes:
                raise TooLarge(f"a worker's rows exceed {worker_bytes} bytes; use more workers, or train() with gradient_step")
        rows = np.concatenate(parts) if parts else np.empty((0, len(names) + 1))
        me = task.partitionId()
        host = task.getTaskInfos()[me].address.rsplit(":", 1)[0]
        tier = KvCluster(1, host, secret) if me < shards else None
        seen = [json.loads(m) for m in task.allGather(json.dumps([len(rows), tier and tier.addresses[0][:2]]))]
        model = _Model([(*address, secret) for _, address in seen if address], start)
        model.pull(0)
        task.barrier()
        loop(model, np.c_[np.ones(len(rows)), rows[:, :-1]], rows[:, -1], sum(n for n, _ in seen), workers)
        task.barrier()
        out = [model.pull(v).tolist() for v in versions or [None]] if me == 0 else []
        task.barrier()
        model.client.close()
        if tier:
            tier.close()
        if out:
            yield pd.DataFrame({"weights": out})

    rows = df.select(*[F.col(c).cast("double") for c in (*names, y)]).dropna().repartition(workers)
    found = [r[0] for r in rows.mapInPandas(work, "weights array<double>", barrier=True).collect()]
    return np.array(found or [start] * len(versions or [None]))  # a frame known to be empty runs no task


def train_server(
    df: DataFrame, x: str | list[str], y: str, *, steps: int, rate: float, staleness: int = 0, shards: int = 2, workers: int = 4, start=None, history: bool = True, worker_bytes: int = 1 << 30
) -> np.ndarray:
    """Versions (rows) of a linear model, bias first, trained by workers and shards; `history=False` keeps the last only.

    At step t each worker pulls version t - staleness, takes the gradient of its
    own rows and pushes it; the shard makes version t + 1 of all workers' parts.
    With staleness zero that is a superstep. Rows stay in the workers: beyond
    `worker_bytes` TooLarge is raised, and train() with gradient_step is the way.
    Rows that hold nulls take no part; of no rows all versions are the start.
    """
    keep = None if history else staleness

    def loop(model, rows, targets, total, size):
        for t in range(steps):
            miss = rows @ model.pull(max(0, t - staleness)) - targets
            model.push(_join, miss @ rows / max(total, 1), (t,), (size, rate, keep))

    return _with_shards(df, x, y, start, loop, list(range(steps + 1)) if history else None, shards, workers, worker_bytes)


def train_async(
    df: DataFrame, x: str | list[str], y: str, *, shards: int = 2, workers: int = 4, passes: int = 20, batch: int = 64, rate: float = 0.2, start=None, worker_bytes: int = 1 << 30
) -> np.ndarray:
    """Lock-free training: workers pull the newest model, take a mini-batch gradient and push it, without waiting for one another."""

    def loop(model, rows, targets, total, size):
        rng = np.random.default_rng(len(rows))
        for _ in range(passes):
            order = rng.permutation(len(rows))
            for at in range(0, len(rows), batch):
                pick = order[at : at + batch]
                miss = rows[pick] @ model.pull() - targets[pick]
                model.push(_nudge, -rate * (miss @ rows[pick]) / len(pick))

    return _with_shards(df, x, y, start, loop, None, shards, workers, worker_bytes)[-1]


def model_frame(spark: SparkSession, weights, shards: int, version: int) -> DataFrame:
    """(shard, idx, weight, version) rows of a model."""
    return spark.createDataFrame([(i % shards, i, float(w), version) for i, w in enumerate(weights)], "shard int, idx int, weight double, version long")
