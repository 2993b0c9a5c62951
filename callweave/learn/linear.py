"""Linear learners of the gather-then-learn pattern: ridge one-vs-rest, hinge, logistic, and their measures."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.operators.gather import gram


@dataclass(frozen=True)
class LinearModel:
    """Weights (classes, features + 1); the last is the bias. `classes` are the labels in order."""

    weights: np.ndarray
    classes: tuple

    def scores(self, x: np.ndarray) -> np.ndarray:
        return np.c_[x, np.ones(len(x))] @ self.weights.T

    def predict(self, x: np.ndarray) -> list:
        return [self.classes[i] for i in self.scores(x).argmax(axis=1)]

    def apply(self, df: DataFrame, features: str, name: str = "predicted") -> DataFrame:
        """Native prediction: weights are literals; ties go to the class named first."""
        dot = lambda w: F.aggregate(F.zip_with(F.col(features), F.lit(w[:-1].tolist()), lambda a, b: a * b), F.lit(float(w[-1])), lambda s, v: s + v)
        scored = F.array(*[F.struct(dot(w).alias("score"), F.lit(-i).alias("order"), F.lit(c).alias("label")) for i, (w, c) in enumerate(zip(self.weights, self.classes))])
        return df.withColumn(name, F.array_max(scored)["label"])


def fit_ridge(x: np.ndarray, labels, ridge: float = 1e-2) -> LinearModel:
    """One machine, dense algebra: targets +-1 per class, (X'X + ridge I) W = X'Y."""
    classes = tuple(sorted(set(labels)))
    xb = np.c_[x, np.ones(len(x))]
    y = np.where(np.array(labels)[:, None] == np.array(classes)[None, :], 1.0, -1.0)
    return LinearModel(np.linalg.solve(xb.T @ xb + ridge * np.eye(xb.shape[1]), xb.T @ y).T, classes)


def fit_ridge_spread(df: DataFrame, features: str, label: str, ridge: float = 1e-2) -> LinearModel:
    """The same from sums made on the executors: only (d + classes)**2 numbers reach the driver, whatever the rows."""
    classes = tuple(r[0] for r in df.select(label).where(F.col(label).isNotNull()).distinct().orderBy(label).collect())
    targets = [F.when(F.col(label) == c, 1.0).otherwise(-1.0) for c in classes]
    rows = df.where(F.col(label).isNotNull()).select(F.concat(F.transform(features, lambda v: v.cast("double")), F.array(F.lit(1.0), *targets)).alias("row"))
    g = gram(rows, "row").toPandas()
    n = int(g["i"].max()) + 1
    full = np.zeros((n, n))
    full[g["i"], g["j"]] = g["v"]
    d = n - len(classes)
    return LinearModel(np.linalg.solve(full[:d, :d] + ridge * np.eye(d), full[:d, d:]).T, classes)


def _descend(x, y, gradient, steps, rate):
    w = np.zeros(x.shape[1])
    for t in range(1, steps + 1):
        w -= rate / np.sqrt(t) * gradient(w, x, y)
    return w


def standardise(x: np.ndarray) -> np.ndarray:
    s = x.std(axis=0)
    return (x - x.mean(axis=0)) / np.where(s > 0, s, 1)


def fit_hinge(x: np.ndarray, y: np.ndarray, steps: int = 200, rate: float = 0.5, decay: float = 1e-3) -> LinearModel:
    """Full-batch sub-gradient descent of the hinge loss; y is 0 or 1."""
    xb, s = np.c_[x, np.ones(len(x))], np.where(np.asarray(y) == 1, 1.0, -1.0)

    def gradient(w, x, s):
        active = s * (x @ w) < 1
        return decay * w - (x[active] * s[active, None]).sum(axis=0) / len(x)

    w = _descend(xb, s, gradient, steps, rate)
    return LinearModel(np.stack([-w, w]), (0, 1))


def hinge_loss(model: LinearModel, x: np.ndarray, y: np.ndarray) -> float:
    s = np.where(np.asarray(y) == 1, 1.0, -1.0)
    return float(np.maximum(0, 1 - s * model.scores(x)[:, 1]).mean())


def fit_logistic(x: np.ndarray, y: np.ndarray, steps: int = 300, rate: float = 1.0, decay: float = 1e-3) -> LinearModel:
    xb = np.c_[x, np.ones(len(x))]
    w = _descend(xb, np.asarray(y, float), lambda w, x, y: decay * w + x.T @ (1 / (1 + np.exp(-x @ w)) - y) / len(x), steps, rate)
    return LinearModel(np.stack([-w, w]), (0, 1))


def accuracy(df: DataFrame, label: str, predicted: str) -> DataFrame:
    return df.agg(F.count(F.lit(1)).alias("n"), F.avg((F.col(label) == F.col(predicted)).cast("double")).alias("accuracy"))


def confusion(df: DataFrame, label: str, predicted: str) -> DataFrame:
    return df.groupBy(F.col(label).alias("label"), F.col(predicted).alias("predicted")).agg(F.count(F.lit(1)).alias("n"))
