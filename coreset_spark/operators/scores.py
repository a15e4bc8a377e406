"""Importance: rescaling, the Beta warp that follows difficulty and budget, and the rules it is compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import expressions as X


def importance(probs: Column, label: Column) -> Column:
    """Norm of predicted probability less one-hot, as a column over an array."""
    return F.sqrt(F.aggregate(F.transform(probs, lambda p, k: (p - F.when(k == label, 1.0).otherwise(0.0)) ** 2), F.lit(0.0), lambda s, x: s + x))


def rescale(rows: DataFrame, score: str = "score", out: str = "z", by: str | None = None) -> DataFrame:
    """Min-max to [0, 1] over the corpus or a group; a constant score becomes one half."""
    if by:
        w = Window.partitionBy(by)
        low, high = F.min(score).over(w), F.max(score).over(w)
        return rows.withColumn("_low", low).withColumn("_high", high).withColumn(out, _scaled(score)).drop("_low", "_high")
    bounds = rows.agg(F.min(score).alias("_low"), F.max(score).alias("_high"))
    return rows.crossJoin(F.broadcast(bounds)).withColumn(out, _scaled(score)).drop("_low", "_high")  # one row


def _scaled(score: str) -> Column:
    return F.when(F.col("_high") > F.col("_low"), (F.col(score) - F.col("_low")) / (F.col("_high") - F.col("_low"))).otherwise(0.5)


def beta_params(rows: DataFrame, budget_frac: float, C: float = 10.0, q: float = 1.0, r: float = 0.5, z: str = "z") -> DataFrame:
    """One row: mean, beta_a, beta_b, mode, clamped. beta_a grows with mean difficulty and budget; both shapes stay above 1."""
    raw = 1 + C * F.pow(F.avg(z), F.lit(q)) * budget_frac**r
    one = rows.agg(F.avg(z).alias("mean"), raw.alias("raw"))
    a = F.least(F.greatest(F.col("raw"), F.lit(1 + 1e-9)), F.lit(C - 1 - 1e-9))
    return one.select("mean", a.alias("beta_a"), (C - a).alias("beta_b"), ((a - 1) / (C - 2)).alias("mode"), (a != F.col("raw")).alias("clamped"))


def warp(rows: DataFrame, params: DataFrame, temperature: float = 1.0, z: str = "z", out: str = "warped") -> DataFrame:
    """Beta density at the rescaled score, to the power of the temperature; endpoints are 0, and a temperature of 0 makes all equal."""
    inner = F.exp(temperature * X.log_beta_density(F.col(z), F.col("beta_a"), F.col("beta_b")))
    at = F.lit(1.0) if temperature == 0 else F.when((F.col(z) > 0) & (F.col(z) < 1), inner).otherwise(0.0)
    return rows.crossJoin(F.broadcast(params.select("beta_a", "beta_b"))).withColumn(out, at).drop("beta_a", "beta_b")  # one row


def weighted(rows: DataFrame, cfg, score: str = "score", out: str = "warped") -> DataFrame:
    """The importance that selection uses, by the configured rule."""
    scaled = rescale(rows, score)
    if cfg.importance_rule == "warped":
        return warp(scaled, beta_params(scaled, cfg.budget_frac, cfg.C, cfg.q, cfg.r), cfg.temperature, out=out).drop("z")
    rule = {"largest": F.col("z"), "smallest": 1 - F.col("z"), "raw": F.col(score)}[cfg.importance_rule]
    return scaled.withColumn(out, rule).drop("z")
