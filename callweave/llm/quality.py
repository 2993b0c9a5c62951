"""Quality classifier: logistic regression on hashed word n-grams, learnt by follow-the-regularised-leader.

Learning sees a bounded sample of labelled rows; scoring sees every whole text,
as a dot product of the text's sparse n-gram shares with the weights.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from callweave.llm.common import Masked, bounded_sample
from callweave.tables import spread

WORD = r"[^\W_]+|[^\w\s]+|_+"


@dataclass(frozen=True)
class QualityParams:
    """`sample` bounds the labelled rows that learning reads; the smallest hashes of doc_id are taken."""

    bits: int = 18
    sample: int = 4000
    epochs: int = 4
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 0.1
    scale: float = 20.0
    threshold: float = 0.7


class Grams:
    """Hashed unigrams and bigrams of words and runs of punctuation; remembers words, up to `memory` of them."""

    def __init__(self, bits: int, memory: int = 100_000):
        self.find, self.mask, self.memory, self.known = re.compile(WORD).findall, (1 << bits) - 1, memory, {}

    def __call__(self, text: str | None) -> np.ndarray:
        words = self.find(text or "")
        new = set(words).difference(self.known)
        if len(self.known) + len(new) > self.memory:
            self.known.clear()
            new = set(words)
        for w in new:
            self.known[w] = zlib.crc32(w.encode("utf-8", "replace"))
        h = np.array([self.known[w] for w in words], dtype=np.uint64)
        pairs = (h[:-1] * np.uint64(0x9E3779B97F4A7C15) + h[1:] * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(29)
        pairs[h[:-1] == h[1:]] = 1  # any word beside itself is one gram
        mask = np.uint64(self.mask)
        return np.concatenate((h & mask, pairs & mask)).astype(np.int64)


def shares(grams: np.ndarray, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """Sparse vector of a text: each gram's share of all grams, times `scale`."""
    index, count = np.unique(grams, return_counts=True)
    return index, count * (scale / max(1, len(grams)))


def ftrl(rows: list[tuple[np.ndarray, np.ndarray, int]], p: QualityParams) -> tuple[np.ndarray, float]:
    """Weights and bias after `epochs` passes over `rows` (index, value, label) in an order fixed by seed."""
    size = (1 << p.bits) + 1
    z, n = np.zeros(size), np.zeros(size)

    def weights(at):
        zs = z[at]
        shrunk = np.sign(zs) * np.maximum(np.abs(zs) - p.l1, 0)
        return -shrunk / ((p.beta + np.sqrt(n[at])) / p.alpha + p.l2)

    order = np.random.default_rng(7)
    for _ in range(p.epochs):
        for i in order.permutation(len(rows)):
            index, value, label = rows[i]
            at, x = np.append(index, size - 1), np.append(value, 1.0)
            w = weights(at)
            g = (1 / (1 + np.exp(-np.clip(w @ x, -35, 35))) - label) * x
            root = np.sqrt(n[at] + g * g)
            z[at] += g - (root - np.sqrt(n[at])) / p.alpha * w
            n[at] += g * g
    w = weights(np.arange(size))
    return w[:-1], float(w[-1])


def held_out(doc_id):
    """True for the quarter of rows that learning never sees."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2


def train_quality(docs: DataFrame, labels: DataFrame, p: QualityParams = QualityParams()) -> tuple[np.ndarray, float]:
    """Learn from at most `p.sample` labelled rows outside the held-out quarter.

    Rows with a null id, label or text, and labels other than 0 and 1, teach
    nothing. If no rows or only one class are left, weights are zero and the
    bias tells that class's share (no rows: score 0.5).
    """
    known = (
        labels.where("quality in (0, 1) and doc_id is not null")
        .where(~held_out(F.col("doc_id")))
        .groupBy(F.col("doc_id").cast("long").alias("doc_id"))
        .agg(F.max("quality").cast("int").alias("quality"))
    )
    known = bounded_sample(known, "doc_id", p.sample)
    bits = p.bits

    def grams(batches):
        hashed = Grams(bits)
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                out = [hashed(t.as_py()) for t in part.column(2)]
                index, count = zip(*(np.unique(g, return_counts=True) for g in out))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(index, pa.list_(pa.int32())), pa.array(count, pa.list_(pa.int32()))],
                    ["doc_id", "quality", "index", "count"],
                )

    texts = docs.where("text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sample = texts.join(F.broadcast(known), "doc_id").select("doc_id", "quality", "text")  # at most p.sample rows of two numbers
    got = sample.mapInArrow(grams, "doc_id long, quality int, index array<int>, count array<int>").toArrow().sort_by("doc_id")
    rows = []
    for label, index, count in zip(got["quality"].to_pylist(), got["index"], got["count"]):
        i, c = np.asarray(index.as_py(), np.int64), np.asarray(count.as_py(), float)
        rows.append((i, c * (p.scale / max(1.0, c.sum())), label))
    if len({r[2] for r in rows}) < 2:
        share = rows[0][2] if rows else 0.5
        return np.zeros(1 << bits), float(np.log((share + 0.01) / (1.01 - share)))
    return ftrl(rows, p)


def score_quality(docs: DataFrame, model: tuple[np.ndarray, float], p: QualityParams = QualityParams()) -> DataFrame:
    """doc_id, held_out, score and predicted of every row; null and empty texts get the score of the bias alone."""
    scored = _scored(spread(docs.select(F.col("doc_id"), F.col("text")), "doc_id"), "text", model, p)
    return scored.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= p.threshold).cast("int").alias("predicted"),
    )


def _scored(df: DataFrame, text: str, model, p: QualityParams) -> DataFrame:
    """`df` with `score`; texts become Python strings a few at a time, whatever an Arrow batch holds."""
    bits, scale, bias = p.bits, p.scale, model[1]
    weights = df.sparkSession.sparkContext.broadcast(model[0].astype(np.float64))  # 2**bits numbers
    at_text = df.columns.index(text)

    def run(batches):
        hashed, w = Grams(bits), weights.value
        for b in batches:
            out = np.empty(b.num_rows)
            for i, t in enumerate(b.column(at_text)):
                g = hashed(t.as_py())
                out[i] = w[g].sum() * (scale / max(1, len(g))) + bias
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(1 / (1 + np.exp(-np.clip(out, -35, 35))))], names)

    schema = T.StructType([*df.schema.fields, T.StructField("score", T.DoubleType())])
    names = schema.fieldNames()
    return df.mapInArrow(run, schema)


def drop_low_quality(docs: DataFrame, labels: DataFrame, train_docs: DataFrame | None = None, p: QualityParams = QualityParams()) -> DataFrame:
    """The rows of `docs`, with their own columns, that the classifier accepts; learnt from `train_docs`, or from `docs`."""
    model = train_quality(docs if train_docs is None else train_docs, labels, p)
    m = Masked(docs)
    return _scored(spread(m.df, m.name("doc_id")), m.name("text"), model, p).where(F.col("score") >= p.threshold).select(m.back())
