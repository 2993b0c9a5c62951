"""Nearest neighbours by inverted lists with an adaptive scan of dimensions.

Centroids are fitted on a bounded sample, every vector is indexed. A query scans
its nearest list first, which bounds its k-th distance; that bound goes with it
to the other probed lists. Within a list vectors are rotated at random and read
in blocks of columns: after each block a hypothesis test on the partial distance
drops candidates whose whole distance is unlikely to be below the bound. What
survives is measured exactly, on the original vectors in double precision.

How many lists are probed is calibrated on the sample, where brute force is
cheap, for a recall of `recall` there; rows lie no closer in a sample than in
the whole table, so the figure is on the safe side. A query probes further lists
until those hold k others. Lists are cut into blocks, and a list's queries too,
as many as probe that very list, so that no task holds a whole hot list and a
stored row is moved once for each block of queries that look at its list.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.llm.common import bounded_sample, cut
from callweave.llm.vectors import matrix, rotation, sound_vectors


@dataclass(frozen=True)
class AnnParams:
    """`sample` bounds the rows that centroids and calibration see; `block` and `queries` bound a task's share of a list."""

    k: int = 10
    sample: int = 20_000
    max_lists: int = 2048
    block: int = 4096
    queries: int = 1024
    columns: int = 16
    epsilon: float = 3.0
    recall: float = 0.97
    seed: int = 29


def fit_centroids(x: np.ndarray, lists: int, seed: int, rounds: int = 8) -> np.ndarray:
    """Centroids by Lloyd's rounds from seeded rows; an empty list keeps its centroid."""
    rng = np.random.default_rng(seed)
    c = x[rng.permutation(len(x))[:lists]].copy()
    for _ in range(rounds):
        own = nearest_lists(x, c, 1)[:, 0]
        count = np.bincount(own, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, own, x)
        c = np.where(count[:, None] > 0, total / np.maximum(count, 1)[:, None], c)
    return c


def nearest_lists(x: np.ndarray, centroids: np.ndarray, n: int, rows: int = 512) -> np.ndarray:
    """The `n` nearest centroids of each row, nearest first, ties to the smaller number; `rows` rows' distances are held at a time."""
    norms, out = (centroids**2).sum(axis=1), np.empty((len(x), min(n, len(centroids))), np.int64)
    for at in range(0, len(x), rows):
        d = norms[None, :] - 2 * x[at : at + rows] @ centroids.T
        out[at : at + rows] = d.argmin(axis=1)[:, None] if n == 1 else np.argsort(d, axis=1, kind="stable")[:, :n]
    return out


def calibrate(x: np.ndarray, centroids: np.ndarray, p: AnnParams, queries: int = 200) -> int:
    """The least number of probed lists that finds a share `p.recall` of the sample's true neighbours."""
    rng = np.random.default_rng(p.seed + 1)
    q = rng.permutation(len(x))[:queries]
    own = nearest_lists(x, centroids, 1)[:, 0]
    rank = np.argsort(nearest_lists(x[q], centroids, len(centroids)), axis=1)
    d = (x**2).sum(axis=1)[None, :] - 2 * x[q] @ x.T
    d[np.arange(len(q)), q] = np.inf
    near = np.argsort(d, axis=1)[:, : min(p.k, len(x) - 1)]
    needed = np.sort(np.take_along_axis(rank, own[near], axis=1).ravel())
    return int(needed[min(len(needed) - 1, math.ceil(p.recall * len(needed)) - 1)]) + 1 if len(needed) else 1


def scan(q: np.ndarray, bound: float, x: np.ndarray, rotated: np.ndarray, turned: np.ndarray, ids: np.ndarray, own: int, p: AnnParams):
    """Up to k (distance, id) of a block for one query; `turned` is the rotated query, `bound` its k-th distance so far."""
    dim = x.shape[1]
    best_d, best_i = np.zeros(0), np.zeros(0, np.int64)
    for at in range(0, len(x), 1024):
        alive = np.flatnonzero(ids[at : at + 1024] != own) + at
        part = np.zeros(len(alive))
        seen = 0
        while seen < dim and len(alive):
            step = slice(seen, min(dim, seen + p.columns))
            part += ((rotated[alive, step] - turned[step]) ** 2).sum(axis=1)
            seen = step.stop
            if seen < dim and np.isfinite(bound):
                keep = part * (dim / seen) <= (bound * (1 + p.epsilon / math.sqrt(seen))) ** 2
                alive, part = alive[keep], part[keep]
        if len(alive):
            alive = alive[part <= (bound * (1 + 1e-9)) ** 2 + 1e-12]
        if not len(alive):
            continue
        d = np.sqrt(((x[alive] - q) ** 2).sum(axis=1))
        best_d, best_i = np.concatenate((best_d, d)), np.concatenate((best_i, ids[alive]))
        order = np.lexsort((best_i, best_d))[: p.k]
        best_d, best_i = best_d[order], best_i[order]
        if len(best_d) == p.k:
            bound = min(bound, best_d[-1])
    return best_d, best_i


OUT = "query_id long, rank int, vec_id long, score double"


def search(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 100, p: AnnParams = AnnParams()) -> DataFrame:
    """(query_id, rank, vec_id, score) of the nearest rows to each row whose id is divisible by `every`.

    Vectors that are null, zero or hold null or non-finite components take no
    part; vectors of different dimensions have no distance, so each dimension is
    searched on its own. Ties go to the smaller vec_id; repeated ids are
    candidates of their own, except to themselves, and of repeated query ids
    (within a dimension) the row with the smallest vector asks; at least k
    candidates are returned, or all if they are fewer; an empty table gives an
    empty table.
    """
    vecs = sound_vectors(df, id_col, vec_col)
    counts = {r["d"]: r["n"] for r in vecs.groupBy(F.size("vec").alias("d")).agg(F.count(F.lit(1)).alias("n")).collect()}  # a row a dimension
    found = [_search(vecs.where(F.size("vec") == d) if len(counts) > 1 else vecs, n, every, p) for d, n in sorted(counts.items())]
    out = found[0] if found else df.sparkSession.createDataFrame([], OUT)
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def _search(vecs: DataFrame, n: int, every: int, p: AnnParams) -> DataFrame:
    """search() among the `n` vectors of one dimension."""
    spark = vecs.sparkSession
    x = matrix(bounded_sample(vecs, "vec_id", p.sample).toArrow()["vec"])
    centroids = fit_centroids(x, int(min(p.max_lists, max(1, round(math.sqrt(n))), len(x))), p.seed)
    probes = calibrate(x, centroids, p)
    shared = spark.sparkContext.broadcast((centroids, rotation(x.shape[1], p.seed)))  # max_lists rows at most

    def index(batches):
        c, _ = shared.value
        for b in batches:
            own = nearest_lists(matrix(b.column(1)), c, 1)[:, 0] if b.num_rows else np.zeros(0, int)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(own.astype(np.int32))], ["vec_id", "vec", "list"])

    kind = vecs.schema["vec"].dataType.simpleString()
    indexed = cut(vecs.mapInArrow(index, f"vec_id long, vec {kind}, list int"))
    sizes = np.zeros(len(centroids), np.int64)
    for r in indexed.groupBy("list").agg(F.count(F.lit(1)).alias("n")).collect():  # max_lists rows
        sizes[r["list"]] = r["n"]
    queries = indexed.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("vec").alias("q"), F.count(F.lit(1)).alias("own"))

    def probe(batches):
        c, _ = shared.value
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                near = nearest_lists(matrix(part.column(1)), c, len(c))
                held = np.cumsum(sizes[near], axis=1)
                enough = (held < np.asarray(part.column(2))[:, None] + p.k).sum(axis=1) + 1
                depth = np.minimum(np.maximum(probes, enough), len(c))
                row = np.repeat(np.arange(part.num_rows), depth)
                rank = np.arange(len(row)) - np.repeat(np.cumsum(depth) - depth, depth)
                lists = near[row, rank].astype(np.int32)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row)), part.column(1).take(pa.array(row)), pa.array(lists), pa.array(rank.astype(np.int32))], ["query_id", "q", "list", "probe"])

    probed = cut(queries.mapInArrow(probe, f"query_id long, q {kind}, list int, probe int"))
    cuts = spark.createDataFrame([(k, int(-(-v // p.block))) for k, v in enumerate(sizes.tolist()) if v], "list int, cuts int")

    def visit(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []})
        _, turn = shared.value
        v = np.stack(right["vec"].to_numpy()).astype(np.float64)
        q = np.stack(left["q"].to_numpy()).astype(np.float64)
        ids, rotated, turned = right["vec_id"].to_numpy(), v @ turn, q @ turn
        got = [(qid, *scan(q[i], bound, v, rotated, turned[i], ids, qid, p)) for i, (qid, bound) in enumerate(zip(left["query_id"], left["bound"]))]
        return pd.DataFrame({"query_id": np.repeat([g[0] for g in got], [len(g[1]) for g in got]), "vec_id": np.concatenate([g[2] for g in got]), "score": np.concatenate([g[1] for g in got])})

    def scanned(asked):
        """Asked lists (max_lists rows at most) tell how many blocks of queries each of their stored rows meets."""
        asks = asked.groupBy("list").agg(F.ceil(F.count(F.lit(1)) / p.queries).cast("int").alias("asks")).join(F.broadcast(cuts), "list")
        asks, keys = cut(asks), ["list", "cut", "qb"]
        left = asked.join(F.broadcast(asks), "list").withColumn("qb", F.pmod(F.xxhash64("query_id"), F.col("asks")).cast("int"))
        left = left.withColumn("cut", F.explode(F.sequence(F.lit(0), F.col("cuts") - 1))).select(*keys, "query_id", "q", "bound")
        right = indexed.join(F.broadcast(asks), "list").withColumn("cut", F.pmod(F.xxhash64("vec_id"), F.col("cuts")).cast("int"))
        right = right.withColumn("qb", F.explode(F.sequence(F.lit(0), F.col("asks") - 1))).select(*keys, "vec_id", "vec")
        return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(visit, "query_id long, vec_id long, score double")

    first = cut(scanned(probed.where("probe = 0").withColumn("bound", F.lit(float("inf")))))
    kth = first.groupBy("query_id").agg(F.when(F.count(F.lit(1)) >= p.k, F.sort_array(F.collect_list("score"))[p.k - 1]).alias("bound"))
    kth = cut(kth.where("bound is not null"))
    rest = probed.where("probe > 0").join(kth, "query_id", "left").withColumn("bound", F.coalesce("bound", F.lit(float("inf"))))
    found = first.unionByName(scanned(rest))
    top = F.slice(F.array_sort(F.collect_list(F.struct("score", "vec_id"))), 1, p.k)  # k rows a block probed
    ranked = found.groupBy("query_id").agg(top.alias("top")).select("query_id", F.posexplode("top").alias("rank", "hit"))
    return ranked.select("query_id", (F.col("rank") + 1).cast("int").alias("rank"), F.col("hit.vec_id").alias("vec_id"), F.col("hit.score").alias("score"))
