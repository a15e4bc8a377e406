"""Measures: gradient gap and its surrogate, bounds, representatives, accuracy, overlap, and the printed cost formulas."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import select
from .blocks import meet
from .proxy import matrix


def gradients(extracted: DataFrame) -> DataFrame:
    """(sample_id, label, grad): last-layer gradient, (p - y) times the pooled vector, flattened."""
    e = F.transform("probs", lambda p, k: p - F.when(k == F.col("label"), 1.0).otherwise(0.0))
    return extracted.select("sample_id", "label", F.flatten(F.transform(e, lambda x: F.transform("vec", lambda h: x * h))).alias("grad"))


def _stack(v: pd.Series) -> np.ndarray:
    return np.stack(v.to_list()) if len(v) else np.zeros((0, 1))


def assign_representatives(rows: DataFrame, picks: DataFrame, vec: str = "vec") -> DataFrame:
    """(sample_id, rep_id, dist): each row's nearest pick, ties to the smaller id. Picks are broadcast up to a checked number; beyond it both sides meet in blocks."""
    def nearest(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        d = np.sqrt(np.maximum((x**2).sum(1)[:, None] + (y**2).sum(1)[None, :] - 2 * x @ y.T, 0))
        at = np.round(d, 9).argmin(1)
        return at, d[np.arange(len(x)), at]

    if picks.count() > select.FEW_PICKS:
        def near(u: pa.Table, p: pa.Table) -> pa.Table:
            if not u.num_rows or not p.num_rows:
                return pa.table({"sample_id": pa.array([], pa.int64()), "rep_id": pa.array([], pa.int64()), "dist": pa.array([], pa.float64())})
            p = p.sort_by("sample_id")
            at, d = nearest(matrix(u["vec"].combine_chunks()), matrix(p["vec"].combine_chunks()))
            return pa.table({"sample_id": u["sample_id"], "rep_id": p["sample_id"].to_numpy()[at], "dist": d})

        sides = (x.select("sample_id", F.col(vec).alias("vec")) for x in (rows, picks))
        best = meet(*sides, near, "sample_id long, rep_id long, dist double").groupBy("sample_id").agg(F.min(F.struct(F.round("dist", 9).alias("r"), "rep_id", "dist")).alias("b"))
        return best.select("sample_id", "b.rep_id", "b.dist")
    p = picks.select("sample_id", vec).toPandas().sort_values("sample_id")
    y, ids = _stack(p[vec]), p["sample_id"].to_numpy()

    def run(batches):
        for u in batches:
            if len(u) and len(ids):
                at, d = nearest(_stack(u[vec]), y)
                yield pd.DataFrame({"sample_id": u["sample_id"], "rep_id": ids[at], "dist": d})

    return rows.select("sample_id", vec).mapInPandas(run, "sample_id long, rep_id long, dist double")


def gradient_gap(grads: DataFrame, weights: DataFrame) -> DataFrame:
    """One row: norm of the full gradient less the weighted gradient of the picks (sample_id, weight)."""
    w = grads.join(weights, "sample_id", "left").select("grad", F.coalesce("weight", F.lit(0.0)).alias("weight"))

    def partial(batches):
        total = None
        for b in batches:
            if len(b):
                part = ((1 - b["weight"].to_numpy())[:, None] * _stack(b["grad"])).sum(0)
                total = part if total is None else total + part
        if total is not None:
            yield pd.DataFrame({"j": np.arange(len(total)), "x": total})

    sums = w.mapInPandas(partial, "j int, x double").groupBy("j").agg(F.sum("x").alias("x"))
    return sums.agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("gap"))


def nearest_gradient_bound(grads: DataFrame, picks: DataFrame) -> DataFrame:
    """One row: sum of distances to the nearest pick in gradient space, which bounds the gap of representative weights."""
    chosen = grads.join(picks.select("sample_id"), "sample_id", "left_semi")
    return assign_representatives(grads, chosen, "grad").agg(F.sum("dist").alias("bound"))


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    both = a.select("sample_id").intersect(b.select("sample_id")).agg(F.count("*").alias("common"))
    either = a.select("sample_id").union(b.select("sample_id")).distinct().agg(F.count("*").alias("together"))
    return both.crossJoin(either).select("common", "together", (F.col("common") / F.col("together")).alias("jaccard"))  # one row each


def mix(picks: DataFrame, corpus: DataFrame, by: str) -> DataFrame:
    """Shares of a category among the picks and in the corpus."""
    whole = corpus.groupBy(by).agg(F.count("*").alias("n_corpus"))
    chosen = corpus.join(picks.select("sample_id"), "sample_id", "left_semi").groupBy(by).agg(F.count("*").alias("n_picks"))
    every = Window.partitionBy()
    out = whole.join(chosen, by, "left").withColumn("n_picks", F.coalesce("n_picks", F.lit(0)))
    return out.select(by, "n_corpus", "n_picks", (F.col("n_corpus") / F.sum("n_corpus").over(every)).alias("share_corpus"), (F.col("n_picks") / F.sum("n_picks").over(every)).alias("share_picks"))


def exact_match(rows: DataFrame, *by: str) -> DataFrame:
    """Share of (predicted, reference) that agree, by categories with subtotals."""
    hit = F.avg((F.col("predicted") == F.col("reference")).cast("double")).alias("accuracy")
    return rows.rollup(*by).agg(hit, F.count("*").alias("n"))


def answer_with_fallback(first, second):
    """The first answer where it is a number, else the second."""
    return F.coalesce(F.expr(f"try_cast({first} AS DOUBLE)").cast("string"), F.col(second))


def greedy_ratio(value: float, optimum: float) -> float:
    return value / optimum if optimum else 1.0


# Costs as printed, in units of one multiplication; N rows, T tokens, d dims, L layers, P pool, b budget, S probe, m anchors, n rows of the graph.
def cost_epoch(N, T, d, L):
    return N * L * (d * T**2 + d**2 * T)


def cost_greedy(P, b, d):
    return P * (b**2 * d + b)


def cost_full_refresh(N, T, d, L):
    return N**2 * d + cost_epoch(N, T, d, L)


def cost_check(S, T, d, L):
    return cost_epoch(S, T, d, L)


def cost_recompute(N, m, T, d, L):
    return N + cost_epoch(m, T, d, L)


def cost_propagation(m, n, d):
    return m * n * d


def cost_repair(N, m, n, d):
    return m * (math.log(max(N, 2)) + n * d)


def cost_rebuild(n, d):
    return n**2 * d


def cost_update_printed(S, m, n, N, T, d, L):
    """The printed total multiplies the probe by the anchors."""
    return S * m * L * (d**2 * T + d * T**2) + N + m * (math.log(max(N, 2)) + 2 * n * d)


def cost_update_sum(S, m, n, N, T, d, L):
    """The sum of the parts that it is made of."""
    return cost_check(S, T, d, L) + cost_recompute(N, m, T, d, L) + cost_propagation(m, n, d) + cost_repair(N, m, n, d)
