"""Approximate aggregates beside the exact ones: distinct counts, quantiles and frequent values."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ranks import quantile


def distinct(rows: DataFrame, column: str, error: float = 0.02) -> DataFrame:
    """One row: the number of distinct values to a relative standard error."""
    return rows.agg(F.approx_count_distinct(column, error).alias("distinct"))


def quantiles(rows: DataFrame, column: str, shares: list[float], accuracy: int = 10_000) -> list[float]:
    """Quantiles whose rank is off by a share of 1 / accuracy at most."""
    return list(rows.agg(F.percentile_approx(column, shares, accuracy).alias("q")).first()["q"])


def kll_quantile(rows: DataFrame, column: str, share: float) -> float:
    """From a mergeable sketch, which may be kept and merged with those of other tables."""
    sketch = rows.agg(F.kll_sketch_agg_double(column).alias("s"))
    return float(sketch.select(F.kll_sketch_get_quantile_double("s", F.lit(share)).alias("q")).first()["q"])


def frequent(rows: DataFrame, column: str, n: int = 10) -> list[tuple[str, int]]:
    """About the n most frequent values with their counts."""
    return [(r["item"], r["count"]) for r in rows.agg(F.expr(f"approx_top_k({column}, {n})").alias("t")).first()["t"]]


def rank_of(rows: DataFrame, column: str, value: float) -> tuple[float, float]:
    """Shares of the rows below a value, and not above it."""
    n, less, equal = rows.agg(F.count(column), F.count_if(F.col(column) < value), F.count_if(F.col(column) <= value)).first()
    return less / max(1, n), equal / max(1, n)


def errors(tokens: DataFrame, numbers: DataFrame) -> DataFrame:
    """(sketch, holds): whether each is within its bounds on (w) and (x); twice the standard error for distinct counts, two hundredths of the rows for ranks."""
    exact = tokens.agg(F.count_distinct("w")).first()[0]
    about = distinct(tokens, "w").first()[0]
    within = lambda v: (s := rank_of(numbers, "x", v))[0] - 0.02 <= 0.5 <= s[1] + 0.02
    top = frequent(tokens, "w", 1)[0][0]
    most = tokens.groupBy("w").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "w").first()
    told = tokens.filter(F.col("w") == top).count()
    rows = [
        ("distinct", abs(about - exact) <= 0.06 * exact), ("median", within(quantiles(numbers, "x", [0.5])[0]) and within(quantile(numbers, "x", 0.5))),
        ("median_kll", within(kll_quantile(numbers, "x", 0.5))), ("most_frequent", told >= 0.9 * most["n"]),
    ]
    return tokens.sparkSession.createDataFrame(rows, "sketch string, holds boolean")
