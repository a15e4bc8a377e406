"""Connected components of a distributed list of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


#: Links that one task takes. A turn runs in as many tasks as its links fill, so that short lists do not cost a file for every shuffle partition.
LINKS_A_TASK = 100_000


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _toward_least(edges: DataFrame, larger: bool, tasks: int) -> DataFrame:
    """Links of neighbours to the least one around: of larger neighbours (first half) or of smaller ones (second half)."""
    pairs = _both(edges) if larger else edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    joined = pairs.join(least, "u")
    if larger:
        out = joined.filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return out.filter("u <> v").coalesce(tasks).distinct().coalesce(tasks)


def components(edges: DataFrame, most: int = 50) -> DataFrame:
    """(node, root) of every node of links (u, v), all longs; root is the least node that links reach.

    Alternates between pointing larger and smaller neighbours to the least one around, so that
    every component shrinks to a star around its least node in about log(size) turns. Each turn
    is checkpointed. links should be cheap to read: they are counted first. No group is ever gathered: minima are pre-aggregated and joined back.
    """
    tasks = max(1, -(-edges.count() // LINKS_A_TASK))
    edges = edges.coalesce(tasks).filter("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    edges = cut(edges.distinct().coalesce(tasks))
    told = None
    for _ in range(most):
        edges = cut(_toward_least(_toward_least(edges, True, tasks), False, tasks))
        sums = edges.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))"), F.expr("bit_xor(xxhash64(v, u))")).first()
        if tuple(sums) == told:
            break
        told = tuple(sums)
    else:
        raise RuntimeError("components did not settle")
    stars = edges.select(F.greatest("u", "v").alias("node"), F.least("u", "v").alias("root"))
    return stars.union(stars.select(F.col("root").alias("node"), "root").distinct())
