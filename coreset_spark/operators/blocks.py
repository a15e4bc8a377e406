"""Two tables that meet block by block, where every row of one has to see every row of the other."""

from __future__ import annotations

import math
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SIDE = 2048


def deal(n: Column | int) -> Column:
    return F.pmod(F.xxhash64("sample_id"), n if isinstance(n, Column) else F.lit(n)).cast("int")


def every(n: Column | int) -> Column:
    return F.explode(F.sequence(F.lit(0), (n if isinstance(n, Column) else F.lit(n)) - 1))


def together(left: DataFrame, right: DataFrame, keys: list[str], run: Callable[[pa.Table, pa.Table], pa.Table], schema: str) -> DataFrame:
    """Rows of equal keys, as Arrow tables of both sides."""
    right = right.select(*[F.col(c).alias(c) for c in right.columns])  # columns of their own, where both are one table
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, schema)


def meet(left: DataFrame, right: DataFrame, run: Callable[[pa.Table, pa.Table], pa.Table], schema: str, side: int | None = None) -> DataFrame:
    """Every block of the one with every block of the other, of about so many rows each; both have a sample_id."""
    side = side or SIDE
    n, m = (max(1, math.ceil(x.count() / side)) for x in (left, right))
    left = left.withColumn("_i", deal(n)).withColumn("_j", every(m))
    right = right.withColumn("_j", deal(m)).withColumn("_i", every(n))
    return together(left, right, ["_i", "_j"], run, schema)
