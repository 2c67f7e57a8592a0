"""Bounded samples of labelled rows, and the small numpy networks that learn from them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(folds: int, fold: int, negate: bool = False, id_col: str = "doc_id") -> Column:
    """Whether crc32 of the id's decimal text leaves remainder ``fold`` modulo ``folds``. A null id isn't held out."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(folds)) == fold, F.lit(False))


def sample(labels: DataFrame, label: str, learn: Column, per_class: int, id_col: str = "doc_id") -> DataFrame:
    """id, y: at most ``per_class`` labelled ids of each class among the rows that ``learn`` admits.

    Drawn by the order of a hash of the id, so the draw is alike on every run. An id with two labels counts as 1.
    """
    rows = labels.where(learn & F.col(label).isin(0, 1)).groupBy(id_col).agg(F.max(label).alias("y"))
    drawn = [rows.where(F.col("y") == y).orderBy(F.xxhash64(id_col), id_col).limit(per_class) for y in (0, 1)]
    return drawn[0].unionByName(drawn[1])


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature that minimises the log loss of ``sigmoid(logits / T)``, on a grid."""
    if not len(y):
        return 1.0
    grid = np.exp(np.linspace(-2, 3, 101))
    loss = [np.mean(np.logaddexp(0, np.where(y > 0, -1, 1) * logits / t)) for t in grid]
    return float(grid[int(np.argmin(loss))])


class Adam:
    """Adam steps on a list of arrays, in place."""

    def __init__(self, params: list[np.ndarray], rate: float, decay: float = 0.0):
        self.params, self.rate, self.decay, self.t = params, rate, decay, 0
        self.m, self.v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]

    def step(self, grads: list[np.ndarray]) -> None:
        self.t += 1
        for p, g, m, v in zip(self.params, grads, self.m, self.v, strict=True):
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            p -= self.rate * (m / (1 - 0.9**self.t) / (np.sqrt(v / (1 - 0.999**self.t)) + 1e-8) + self.decay * p)


def auc(score: np.ndarray, y: np.ndarray) -> float:
    """Area under the ROC curve; ties count half."""
    _, inverse, counts = np.unique(score, return_inverse=True, return_counts=True)
    rank = (np.cumsum(counts) - (counts - 1) / 2)[inverse]
    pos = y > 0
    n, m = int(pos.sum()), int((~pos).sum())
    return float((rank[pos].sum() - n * (n + 1) / 2) / (n * m)) if n and m else float("nan")
