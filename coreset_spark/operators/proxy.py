"""The model that stands in for a language model: softmax regression, with one tanh layer or none, by full-batch gradient descent.

A step is one pass: each task returns one partial gradient, of the size of the parameters, and
their sums come to the driver, which keeps and broadcasts nothing larger than the model.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def matrix(column: pa.Array) -> np.ndarray:
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(n, -1) if n else np.zeros((0, 0))


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


@dataclass
class SoftmaxProxy:
    """classes x dims weights, from zeros; with hidden, a fixed-seed tanh layer is trained below them."""

    classes: int = 10
    dims: int = 64
    hidden: int | None = None
    lr: float = 200.0
    l2: float = 0.0
    weights: dict[str, np.ndarray] = field(default_factory=dict)

    def __post_init__(self) -> None:
        if not self.weights:
            self.weights = {"out": np.zeros((self.classes, self.hidden or self.dims))}
            if self.hidden:
                self.weights["in"] = np.random.default_rng(7).normal(0, 1, (self.hidden, self.dims))

    def copy(self) -> SoftmaxProxy:
        return SoftmaxProxy(self.classes, self.dims, self.hidden, self.lr, self.l2, {k: v.copy() for k, v in self.weights.items()})

    def states(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(x @ self.weights["in"].T) if self.hidden else x

    def forward(self, x: np.ndarray) -> np.ndarray:
        return softmax(self.states(x) @ self.weights["out"].T)

    def gradients(self, x: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        """Sums over the rows of the gradient of the log loss."""
        h = self.states(x)
        error = softmax(h @ self.weights["out"].T)
        error[np.arange(len(y)), y] -= 1
        out = {"out": error.T @ h}
        if self.hidden:
            out["in"] = ((error @ self.weights["out"]) * (1 - h**2)).T @ x
        return out

    def fit_steps(self, rows: DataFrame, steps: int, weight: str | None = None, lr: float | None = None) -> SoftmaxProxy:
        """Trained further on (vec, label): mean gradient, optionally of weighted rows, at the model's rate or another; no rows change nothing."""
        model = self.copy()
        rows = rows.select("vec", "label", (F.col(weight) if weight else F.lit(1.0)).cast("double").alias("weight"))
        for _ in range(steps):
            at = model.copy()

            def partial(batches: Iterator[pa.RecordBatch], at: SoftmaxProxy = at) -> Iterator[pa.RecordBatch]:
                total, n = {k: np.zeros_like(v) for k, v in at.weights.items()}, 0.0
                for b in batches:
                    if not b.num_rows:
                        continue
                    x, y, w = matrix(b.column(0)), b.column(1).to_numpy(zero_copy_only=False), b.column(2).to_numpy(zero_copy_only=False)
                    h = at.states(x)
                    error = softmax(h @ at.weights["out"].T)
                    error[np.arange(len(y)), y] -= 1
                    error *= w[:, None]
                    total["out"] += error.T @ h
                    if at.hidden:
                        total["in"] += ((error @ at.weights["out"]) * (1 - h**2)).T @ x
                    n += w.sum()
                names = [k for k, v in total.items() for _ in range(v.size)] + ["n"]
                places = [i for v in total.values() for i in range(v.size)] + [0]
                values = [*(z for v in total.values() for z in v.ravel()), n]
                yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(places, pa.int32()), pa.array(values, pa.float64())], names=["name", "place", "value"])

            sums = rows.mapInArrow(partial, "name string, place int, value double").groupBy("name", "place").agg(F.sum("value").alias("value")).toPandas()
            n = float(sums.loc[sums["name"] == "n", "value"].iloc[0]) if len(sums) else 0.0
            for k, v in model.weights.items() if n else ():
                part = sums[sums["name"] == k]
                g = np.zeros(v.size)
                g[part["place"].to_numpy()] = part["value"].to_numpy()
                v -= (self.lr if lr is None else lr) * (g.reshape(v.shape) / n + self.l2 * v)
        return model

    def params(self, spark) -> DataFrame:
        w = self.weights["out"]
        rows = [(int(k), int(j), float(w[k, j])) for k in range(w.shape[0]) for j in range(w.shape[1])]
        return spark.createDataFrame(rows, "label int, dim int, value double")

    def extract(self, rows: DataFrame) -> DataFrame:
        """One forward pass: (sample_id, vec, label, score, loss, confidence, predicted, probs); vec is the pooled state."""
        model = self.copy()

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                x, y = matrix(b.column(1)), b.column(2).to_numpy(zero_copy_only=False)
                p = model.forward(x)
                own = p[np.arange(len(y)), y]
                error = p.copy()
                error[np.arange(len(y)), y] -= 1
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), pa.array(list(model.states(x)), pa.list_(pa.float64())), b.column(2), pa.array(np.sqrt((error**2).sum(1))), pa.array(-np.log(np.maximum(own, 1e-300))), pa.array(own), pa.array(p.argmax(1).astype(np.int32)), pa.array(list(p), pa.list_(pa.float64()))],
                    names=["sample_id", "vec", "label", "score", "loss", "confidence", "predicted", "probs"],
                )

        kind = rows.schema["sample_id"].dataType.simpleString()
        return rows.select("sample_id", "vec", F.col("label").cast("int").alias("label")).mapInArrow(run, f"sample_id {kind}, vec array<double>, label int, score double, loss double, confidence double, predicted int, probs array<double>")


def lr_at(step: int, total: int, peak: float, ramp: float = 0.03) -> float:
    """Linear ramp over a share of the steps, then linear decay to zero."""
    up = max(1, round(total * ramp))
    return peak * (step + 1) / up if step < up else peak * max(0.0, (total - step) / max(1, total - up))
