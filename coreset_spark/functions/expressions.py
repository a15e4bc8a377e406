"""Column expressions: vector arithmetic on arrays, log-gamma and the Beta density.

Array lambdas are interpreted per element, so these serve small inputs and cross-checks; kernels on Arrow blocks do the bulk.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

# Coefficients of the Lanczos approximation with g = 7.
LANCZOS = (
    0.99999999999980993, 676.5203681218851, -1259.1392167224028, 771.32342877765313, -176.61502916214059,
    12.507343278686905, -0.13857109526572012, 9.9843695780195716e-6, 1.5056327351493116e-7,
)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def axpy(t: float, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * t + y)


def normalise(a: Column) -> Column:
    n = norm(a)
    return F.when(n > 0, F.transform(a, lambda x: x / n)).otherwise(a)


def log_gamma(x: Column) -> Column:
    """ln Gamma for x >= 0.5; Spark has no gamma function."""
    y = x - 1
    total = F.lit(LANCZOS[0])
    for i, c in enumerate(LANCZOS[1:], 1):
        total = total + c / (y + i)
    t = y + 7.5
    return 0.5 * math.log(2 * math.pi) + (y + 0.5) * F.log(t) - t + F.log(total)


def log_beta_density(z: Column, a: Column, b: Column) -> Column:
    return (a - 1) * F.log(z) + (b - 1) * F.log(1 - z) - (log_gamma(a) + log_gamma(b) - log_gamma(a + b))


def register(spark: SparkSession) -> None:
    """SQL names of the vector functions, as SQL functions that Catalyst inlines."""
    fold = "aggregate(zip_with(a, b, (x, y) -> {}), 0D, (s, x) -> s + x)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {fold.format('x * y')}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vec_l2(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt({fold.format('(x - y) * (x - y)')})")
