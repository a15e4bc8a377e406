"""The selectors that the adaptive one is compared with. All return (sample_id, rank) of b rows; ties go to the smaller id."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import expressions as X
from ..sources.tables import draw_pool
from . import select
from .ranks import quantile, row_numbers
from .storage import cut


def _best(rows: DataFrame, b: int, *order: Column) -> DataFrame:
    return row_numbers(rows.orderBy(*order, "sample_id").limit(b), *order, F.col("sample_id"), name="rank").select("sample_id", F.col("rank").cast("int").alias("rank"))


def uniform(rows: DataFrame, b: int, seed: int = 42, epoch: int = 0) -> DataFrame:
    """Once with epoch 0, or anew each epoch."""
    return draw_pool(rows.select("sample_id"), b, seed, epoch)


def median_loss(rows: DataFrame, b: int) -> DataFrame:
    """Nearest to the median loss."""
    near = rows.withColumn("_d", F.round(F.abs(F.col("loss") - F.lit(quantile(rows, "loss", 0.5))), 9))
    return _best(near, b, F.col("_d"))


def facility_location(rows: DataFrame, b: int, **options) -> DataFrame:
    return select.select_greedy(rows.withColumn("warped", F.lit(0.0)), None, b, 1.0, **options).select("sample_id", F.col("round").alias("rank"))


def loss_drop(before: DataFrame, after: DataFrame, b: int) -> DataFrame:
    both = before.select("sample_id", F.col("loss").alias("_b")).join(after.select("sample_id", F.col("loss").alias("_a")), "sample_id")
    return _best(both.withColumn("_d", F.round(F.col("_b") - F.col("_a"), 9)), b, F.col("_d").desc())


def longest_completion(rows: DataFrame, b: int, unit: str = "tokens", completion: str = "completion") -> DataFrame:
    n = F.size(F.array_remove(F.split(F.coalesce(completion, F.lit("")), r"\s+"), "")) if unit == "tokens" else F.length(F.coalesce(completion, F.lit("")))
    return _best(rows.withColumn("_n", n), b, F.col("_n").desc())


def grad_norm(rows: DataFrame, b: int) -> DataFrame:
    """Of a softmax layer, the gradient's norm is importance times the norm of the vector."""
    return _best(rows.withColumn("_g", F.round(F.col("score") * X.norm(F.col("vec")), 9)), b, F.col("_g").desc())


def least_confidence(rows: DataFrame, b: int, log_confidence: str = "log_confidence") -> DataFrame:
    """Smallest product of the probabilities, as a sum of logarithms."""
    return _best(rows.withColumn("_c", F.round(log_confidence, 9)), b, F.col("_c"))


def nnls(g: np.ndarray, h: np.ndarray, places: float = 1e-12) -> np.ndarray:
    """Weights w >= 0 of the least w'gw / 2 - h'w, by active sets: a row comes in while it would lower the value, and those that turn negative go out."""
    w, inside = np.zeros(len(h)), np.zeros(len(h), bool)
    while True:
        slope = h - g @ w
        slope[inside] = -np.inf
        if not len(h) or slope.max() <= places * max(1.0, np.abs(h).max()):
            return w
        inside[int(slope.argmax())] = True
        while True:
            at = np.flatnonzero(inside)
            goal = np.zeros(len(h))
            goal[at] = np.linalg.solve(g[np.ix_(at, at)], h[at])
            low = at[goal[at] <= places]
            if not len(low):
                w = goal
                break
            step = min(w[i] / (w[i] - goal[i]) if w[i] > goal[i] else 0.0 for i in low)
            w = w + step * (goal - w)
            inside[at[w[at] <= places]] = False
            w[~inside] = 0


class _Least:
    """Least squares over the rows taken so far: their products are kept, and beyond as many rows as they have numbers, those of the numbers instead."""

    def __init__(self, full: np.ndarray, ridge: float, nonneg: bool) -> None:
        self.full, self.ridge, self.nonneg = full, ridge, nonneg
        self.a, self.n = np.zeros((16, len(full))), 0
        self.g, self.m = np.zeros((16, 16)), None

    def add(self, row: np.ndarray) -> None:
        n = self.n
        if n == len(self.a):
            self.a = np.concatenate([self.a, np.zeros_like(self.a)])
        self.a[n] = row
        self.n = n + 1
        if self.m is not None:
            self.m += np.outer(row, row)
        elif self.ridge > 0 and not self.nonneg and self.n > len(row):
            rows = self.a[: self.n]
            self.m, self.g = rows.T @ rows + self.ridge * np.eye(len(row)), None
        else:
            if n == len(self.g):
                g = np.zeros((2 * n, 2 * n))
                g[:n, :n] = self.g
                self.g = g
            self.g[n, : n + 1] = self.g[: n + 1, n] = self.a[: n + 1] @ row
            self.g[n, n] += self.ridge

    def solve(self) -> tuple[np.ndarray, np.ndarray]:
        """What is left of the full gradient, and, where it is of use, the weights: with more rows than numbers these follow from what is left."""
        rows = self.a[: self.n]
        if self.m is not None:
            at = np.linalg.solve(self.m, self.full)
            return self.ridge * at, at
        g, h = self.g[: self.n, : self.n], rows @ self.full
        w = nnls(g, h) if self.nonneg else np.linalg.solve(g, h)
        return self.full - w @ rows, w

    def weights(self) -> np.ndarray:
        if not self.n:
            return np.zeros(0)
        at = self.solve()[1]
        return at if self.m is None else self.a[: self.n] @ at


def pursue(a: np.ndarray, ids: np.ndarray, b: int, ridge: float = 1e-8, nonneg: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Picks (ids, weights) of orthogonal matching pursuit over the rows of a, whose ids ascend."""
    residual, chosen = a.sum(0), []
    least = _Least(residual, ridge, nonneg)
    for _ in range(min(b, len(ids))):
        c = np.round(a @ residual, 9)
        c[chosen] = -np.inf
        if c.max() <= 0:
            break
        chosen.append(int(c.argmax()))
        least.add(a[chosen[-1]])
        residual = least.solve()[0]
    return ids[chosen], least.weights()


#: Numbers of gradients that one task takes.
ONE_TASK_NUMBERS = 20_000_000


def _in_one(g: pd.DataFrame, b: int, ridge: float, nonneg: bool) -> pd.DataFrame:
    g = g.sort_values("sample_id")
    ids, w = pursue(np.stack(g["grad"].to_list()), g["sample_id"].to_numpy(), b, ridge, nonneg)
    return pd.DataFrame({"round": np.arange(1, len(ids) + 1, dtype=np.int32), "sample_id": ids, "weight": w})


OMP = "round int, sample_id long, weight double"


def omp_select(grads: DataFrame, b: int, ridge: float = 1e-8, nonneg: bool = False) -> DataFrame:
    """Orthogonal matching pursuit: (round, sample_id, weight); each round the row best correlated with what is left of the full
    gradient, then least squares over the rows so far, with weights of at least 0 if asked. One task while the gradients fit it;
    beyond that a round is one pass with the residual broadcast, and a system of b rows on the driver."""
    grads = cut(grads.select("sample_id", "grad"))
    if (grads.agg(F.sum(F.size("grad"))).first()[0] or 0) <= ONE_TASK_NUMBERS:
        return grads.withColumn("one", F.lit(1)).groupBy("one").applyInPandas(lambda g: _in_one(g, b, ridge, nonneg), OMP)

    def total(batches):
        out = None
        for g in batches:
            if len(g):
                part = np.stack(g["grad"].to_list()).sum(0)
                out = part if out is None else out + part
        if out is not None:
            yield pd.DataFrame({"j": np.arange(len(out)), "x": out})

    sums = grads.mapInPandas(total, "j int, x double").groupBy("j").agg(F.sum("x").alias("x")).toPandas().sort_values("j")
    full = sums["x"].to_numpy()
    residual, ids, least = full, [], _Least(full, ridge, nonneg)
    for _ in range(b):
        def best(batches, r=residual, taken=frozenset(ids)):
            for g in batches:
                g = g[~g["sample_id"].isin(taken)]
                if len(g):
                    c = np.round(np.stack(g["grad"].to_list()) @ r, 9)
                    top = g.assign(c=c).sort_values(["c", "sample_id"], ascending=[False, True]).head(1)
                    yield top[["sample_id", "c", "grad"]]

        found = grads.mapInPandas(best, "sample_id long, c double, grad array<double>").orderBy(F.col("c").desc(), "sample_id").limit(1).collect()
        if not found or found[0]["c"] <= 0:
            break
        ids.append(found[0]["sample_id"])
        least.add(np.array(found[0]["grad"]))
        residual = least.solve()[0]
    rows = [(i + 1, int(s), float(w)) for i, (s, w) in enumerate(zip(ids, least.weights(), strict=True))]
    return grads.sparkSession.createDataFrame(rows, OMP)


def omp_per_cluster(grads: DataFrame, b: int, cluster: str = "label", ridge: float = 1e-8, nonneg: bool = False) -> DataFrame:
    """(sample_id, weight) of matching pursuit within clusters, each with an even share of the budget, the first ones one more: less memory,
    one task for each cluster that fits it, and rounds of their own for those that do not."""
    grads = cut(grads.select("sample_id", F.col(cluster).alias("cluster"), "grad"))
    sizes = grads.groupBy("cluster").agg(F.sum(F.size("grad")).alias("n")).orderBy(F.col("cluster").asc_nulls_last()).collect()  # a row a cluster
    share = {r["cluster"]: b // len(sizes) + (i < b % len(sizes)) for i, r in enumerate(sizes)}
    large = [r["cluster"] for r in sizes if r["n"] > ONE_TASK_NUMBERS]
    of = lambda c: F.col("cluster").eqNullSafe(F.lit(c))
    small = grads
    for c in large:
        small = small.filter(~of(c))

    def run(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        return _in_one(g, share[None if pd.isna(key[0]) else key[0]], ridge, nonneg)

    out = small.groupBy("cluster").applyInPandas(run, OMP)
    for c in large:
        out = out.unionByName(omp_select(grads.filter(of(c)), share[c], ridge, nonneg))
    return out.select("sample_id", "weight")


def kmeans(rows: DataFrame, clusters: int, rounds: int = 3) -> DataFrame:
    """(sample_id, cluster) by Lloyd's rounds from the first ids; centres are broadcast: clusters x dims numbers."""
    start = rows.orderBy("sample_id").limit(clusters).toPandas()
    centres = np.stack(start["vec"].to_list())
    assigned = None
    for turn in range(rounds + 1):
        def nearest(batches, c=centres):
            for u in batches:
                if len(u):
                    x = np.stack(u["vec"].to_list())
                    d = (x**2).sum(1)[:, None] + (c**2).sum(1)[None, :] - 2 * x @ c.T
                    yield pd.DataFrame({"sample_id": u["sample_id"], "cluster": np.round(d, 9).argmin(1).astype(np.int32), "vec": list(x)})

        assigned = rows.select("sample_id", "vec").mapInPandas(nearest, "sample_id long, cluster int, vec array<double>")
        if turn < rounds:
            means = assigned.select("cluster", F.posexplode("vec").alias("j", "x")).groupBy("cluster", "j").agg(F.avg("x").alias("x")).toPandas()
            for k, part in means.groupby("cluster"):
                centres[k] = part.sort_values("j")["x"].to_numpy()
    return assigned.select("sample_id", "cluster")


def quotas(counts: DataFrame, b: int, weight: str) -> DataFrame:
    """Largest remainder: (group, quota) whose sum is b."""
    every = Window.partitionBy()
    share = b * F.col(weight) / F.sum(weight).over(every)
    rows = counts.withColumn("_f", F.floor(F.round(share, 9))).withColumn("_r", F.round(share - F.col("_f"), 9))
    order = Window.orderBy(F.col("_r").desc(), "group")
    return rows.select("group", (F.col("_f") + F.when(F.row_number().over(order) <= b - F.sum("_f").over(every), 1).otherwise(0)).cast("long").alias("quota"))


def cluster_reweight(assigned: DataFrame, b: int, scores: DataFrame | None = None, seed: int = 42, epoch: int = 0) -> DataFrame:
    """Draws b rows: clusters get quotas by size times mean score (their weight), rows within them go by hash."""
    rows = assigned if scores is None else assigned.join(scores.select("sample_id", "score"), "sample_id")
    weight = F.count("*").cast("double") if scores is None else F.count("*") * F.avg("score")
    q = quotas(rows.groupBy(F.col("cluster").alias("group")).agg(weight.alias("weight")), b, "weight")
    key = F.md5(F.concat(F.lit(f"{seed}:{epoch}:"), F.col("sample_id").cast("string")))
    order = Window.partitionBy("cluster").orderBy(key)
    ranked = rows.withColumn("_k", F.row_number().over(order))
    return ranked.join(q, F.col("cluster") == F.col("group")).filter(F.col("_k") <= F.col("quota")).select("sample_id", "cluster")
