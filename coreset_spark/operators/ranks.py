"""Global row numbers and exact quantiles without one task that sees all rows."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import cut

BUCKETS = 4096


def row_numbers(rows: DataFrame, *order: Column | str, name: str = "row_number") -> DataFrame:
    """rows with their place, from 1, in a global order: a range-partitioned sort, and what the partitions before hold, a number each."""
    placed = cut(rows.orderBy(*order).withColumn("_at", F.monotonically_increasing_id()))
    part = F.call_function("shiftright", F.col("_at"), F.lit(33))
    held = sorted((r["p"], r["n"]) for r in placed.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    before, starts = 0, []
    for p, n in held:
        starts.append((int(p), before))
        before += n
    start = F.broadcast(rows.sparkSession.createDataFrame(starts, "_p long, _before long"))  # a row a partition
    joined = placed.withColumn("_p", part).join(start, "_p")
    return joined.withColumn(name, F.col("_before") + F.col("_at").bitwiseAND((1 << 33) - 1) + 1).drop("_at", "_p", "_before")


def tiles(rows: DataFrame, n: int, *order: Column | str, name: str = "tile") -> DataFrame:
    """rows with the number, from 1, of the one of n even parts of a global order that they lie in; the first ones are larger by a row."""
    total = rows.count()
    size, more = divmod(total, n)
    at = F.col("_k") - 1
    large = F.lit(more * (size + 1))
    tile = F.when(at < large, F.floor(at / (size + 1))).otherwise(more + F.floor((at - large) / max(1, size))) + 1
    return row_numbers(rows, *order, name="_k").withColumn(name, tile.cast("int")).drop("_k")


def ranks(rows: DataFrame, column: str, name: str = "rank") -> DataFrame:
    """rows with the rank of a value in ascending order; equal values share the least."""
    counts = rows.groupBy(column).agg(F.count("*").alias("_n"))
    numbered = row_numbers(counts, column, name="_i")
    return rows.join(_running(numbered).select(F.col(column).alias("_v"), (F.col("_sum") - F.col("_n") + 1).alias(name)), F.col(column).eqNullSafe(F.col("_v"))).drop("_v")


def _running(numbered: DataFrame) -> DataFrame:
    """Running sums of _n in the order of _i: within runs of rows, and over the sums of the runs."""
    from pyspark.sql import Window

    runs = numbered.withColumn("_run", F.floor((F.col("_i") - 1) / 100_000))
    own = runs.withColumn("_own", F.sum("_n").over(Window.partitionBy("_run").orderBy("_i")))
    totals = runs.groupBy("_run").agg(F.sum("_n").alias("_t"))
    base = totals.withColumn("_base", F.sum("_t").over(Window.partitionBy().orderBy("_run")) - F.col("_t")).drop("_t")  # a row for 100,000
    return own.join(base, "_run").withColumn("_sum", F.col("_own") + F.col("_base")).drop("_run", "_own", "_base")


def order_statistic(rows: DataFrame, column: str, k: int) -> float | None:
    """The value of place k, from 0, in ascending order. Each pass counts buckets between the bounds that are left, and the least and largest value of the one with the place are the next bounds."""
    values = rows.select(F.col(column).cast("double").alias("v")).filter(F.col("v").isNotNull())
    low, high, n = values.agg(F.min("v"), F.max("v"), F.count("*")).first()
    if not 0 <= k < n:
        return None
    while low < high:
        bucket = F.least(F.floor((F.col("v") - low) / ((high - low) / BUCKETS)), F.lit(BUCKETS - 1))
        found = values.filter(F.col("v").between(low, high)).groupBy(bucket.alias("b")).agg(F.count("*").alias("n"), F.min("v").alias("l"), F.max("v").alias("h")).collect()
        for _, n, l, h in sorted(map(tuple, found)):
            if k < n:
                break
            k -= n
        if (l, h) == (low, high):  # no room between the bounds for buckets
            counts = values.filter(F.col("v").between(low, high)).groupBy("v").count().collect()
            for v, n in sorted(map(tuple, counts)):
                if k < n:
                    return v
                k -= n
        low, high = l, h
    return low


def quantile(rows: DataFrame, column: str, q: float) -> float | None:
    """Exact, between two places by their distance."""
    n = rows.filter(F.col(column).isNotNull()).count()
    if not n:
        return None
    at = (n - 1) * q
    low = order_statistic(rows, column, math.floor(at))
    high = low if at == math.floor(at) else order_statistic(rows, column, math.floor(at) + 1)
    return low + (at - math.floor(at)) * (high - low)
