"""Joins that Spark has no word for: on keys that may be null on both sides, and on keys of which one holds a large part of the rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def null_safe(left: DataFrame, right: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    """An equi-join on which null keys agree with null keys; the keys come from the left side."""
    other = right.select(*[F.col(k).alias(f"_{k}") for k in keys], *[c for c in right.columns if c not in keys])
    on = reduce(lambda a, b: a & b, [F.col(k).eqNullSafe(F.col(f"_{k}")) for k in keys])
    return left.join(other, on, how).drop(*[f"_{k}" for k in keys])


def salted(left: DataFrame, right: DataFrame, key: str, parts: int = 16, hot: float = 0.01) -> DataFrame:
    """An inner equi-join of a large left side with a right one. Keys with over a share of the left rows are hot: their
    left rows are dealt to parts, and their right rows copied to each. There are 1 / hot of them at most, so they are broadcast."""
    total = left.count()
    counts = left.groupBy(key).agg(F.count("*").alias("_n"))
    heavy = counts.filter(F.col("_n") > hot * total).select(F.col(key).alias("_hot"))
    deal = F.when(F.col("_hot").isNotNull(), F.floor(F.rand(42) * parts)).otherwise(0).cast("int")
    copies = F.explode(F.when(F.col("_hot").isNotNull(), F.sequence(F.lit(0), F.lit(parts - 1))).otherwise(F.array(F.lit(0))))
    a = left.join(F.broadcast(heavy), F.col(key) == F.col("_hot"), "left").withColumn("_salt", deal).drop("_hot")
    b = right.join(F.broadcast(heavy), F.col(key) == F.col("_hot"), "left").withColumn("_salt", copies).drop("_hot")
    return a.join(b, [key, "_salt"]).drop("_salt")
