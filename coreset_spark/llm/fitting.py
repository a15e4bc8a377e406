"""Logistic regression on a bounded sample, for the classifiers of this subpackage."""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FOLDS = 5


def held_out(doc_id: Column) -> Column:
    """Rows that no fit may see: crc32 of the id as text leaves no remainder by five."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % FOLDS == 0


def held_out_value(doc_id: object) -> bool:
    return zlib.crc32(("" if doc_id is None else str(doc_id)).encode()) % FOLDS == 0


def sampled(labels: DataFrame, label: str, most: int, seed: int) -> DataFrame:
    """(doc_id, y) of about ``most`` labelled rows that are not held out, drawn by a hash of the id; one row per id, the largest label."""
    rows = labels.filter(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id")))
    share = min(1.0, most / max(1, rows.count()))
    drawn = F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(1 << 30)) < int(share * (1 << 30))
    return rows.filter(drawn).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))


@dataclass
class Rows:
    """Sparse rows: row i has the columns index[start[i]:start[i + 1]] with these values."""

    index: np.ndarray
    value: np.ndarray
    row: np.ndarray
    n: int

    @classmethod
    def of(cls, lists: list[list[tuple[int, float]]]) -> Rows:
        row = np.repeat(np.arange(len(lists)), [len(x) for x in lists])
        flat = [p for x in lists for p in x]
        return cls(np.array([p[0] for p in flat], np.int64), np.array([p[1] for p in flat], np.float64), row, len(lists))

    def dot(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, self.value * w[self.index], minlength=self.n)

    def back(self, g: np.ndarray, width: int) -> np.ndarray:
        return np.bincount(self.index, self.value * g[self.row], minlength=width)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def logistic(x: Rows, y: np.ndarray, width: int, l2: float, changes: Rows | None = None, penalty: float = 0.0, steps: int = 300, rate: float = 0.1) -> tuple[np.ndarray, float]:
    """Weights and bias that minimise the mean log loss, l2 * |w|^2 / 2 and penalty * the mean squared change of score; by Adam."""
    w, b = np.zeros(width), 0.0
    m, v = np.zeros(width + 1), np.zeros(width + 1)
    if not x.n:
        return w, b
    for t in range(1, steps + 1):
        error = (sigmoid(x.dot(w) + b) - y) / x.n
        g = x.back(error, width) + l2 * w
        if changes is not None and changes.n and penalty:
            g += changes.back(2 * penalty * changes.dot(w) / changes.n, width)
        full = np.append(g, error.sum())
        m, v = 0.9 * m + 0.1 * full, 0.999 * v + 0.001 * full**2
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    return w, float(b)
