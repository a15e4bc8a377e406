"""Exact top-k search by inner product: a ball tree per shard, branch and bound, and a shared k-th score.

Vectors become integers, so scores are exact. Rows are dealt to shards by their id. Every query
first searches the shard it lies in, whose k-th score is a bound that all other shards share:
there, nodes are tried in order of the largest inner product that their ball allows, and a node
below the query's current k-th score is left with all that is under it. A task holds one shard
with its tree, built once, and queries stream past it, so its memory grows with neither side.

Defined results: vectors that are null or hold a null or a component that is not finite take no
part; vectors are compared with those of their own length; rows with the query's vec_id are its
own and never its answers; rows that repeat a vec_id and a vector ask once, and answer as often
as they occur; ties go to the smaller vec_id; scores beyond 64 bits stop at the largest 64-bit
number; an empty table gives an empty one; only vec_id and embedding are read, whatever other columns are called.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut

LARGEST = 2**63 - 1


@dataclass(frozen=True)
class Search:
    """k: answers per query. scale: what a component is multiplied by. shard_numbers: components of a shard's vectors, about."""

    k: int = 10
    scale: float = 1024.0
    leaf: int = 256
    shard_numbers: int = 4_000_000


@dataclass
class _Node:
    centre: np.ndarray
    radius: float
    rows: np.ndarray | None = None
    below: list[_Node] = field(default_factory=list)


class BallTree:
    """Splits rows at the median of their spread along the widest line of two far rows."""

    def __init__(self, vectors: np.ndarray, leaf: int) -> None:
        self.x = vectors.astype(np.float64)
        self.root = self._build(np.arange(len(vectors)), leaf)

    def _build(self, rows: np.ndarray, leaf: int) -> _Node:
        part = self.x[rows]
        centre = part.mean(0) if len(rows) else np.zeros(self.x.shape[1])
        away = np.sqrt(((part - centre) ** 2).sum(1))
        node = _Node(centre, float(away.max(initial=0.0)))
        if len(rows) <= leaf or node.radius == 0:
            node.rows = rows
            return node
        far = part[away.argmax()]
        line = part[((part - far) ** 2).sum(1).argmax()] - far
        order = np.argsort(part @ line, kind="stable")
        half = len(rows) // 2
        node.below = [self._build(rows[order[:half]], leaf), self._build(rows[order[half:]], leaf)]
        return node


def integers(vectors: np.ndarray, scale: float) -> np.ndarray:
    """floor(scale * x), as doubles."""
    return np.floor(vectors.astype(np.float64) * scale)


def wide(x: np.ndarray) -> np.ndarray:
    """The same as Python numbers, whose products are exact at any size."""
    return np.array([[int(v) for v in row] for row in x], dtype=object).reshape(x.shape)


def exact_as_doubles(x: np.ndarray, y: np.ndarray) -> bool:
    """Whether every inner product of a row of x and one of y is exact in a double."""
    return np.abs(x).max(initial=0.0) * np.abs(y).max(initial=0.0) * max(1, x.shape[1]) < 2**53


def search_block(ids: np.ndarray, rows: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, floor: np.ndarray, s: Search, tree: BallTree | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Of each query, the k best rows of the shard with a score of at least its floor: (query's place, ids, scores).

    A leaf's scores are one product of its rows with the query. A bound is raised by a little
    more than a double's error, so that no node with a tied score is left out.
    """
    tree = tree or BallTree(rows, s.leaf)
    for q in range(len(query_ids)):
        v, own = queries[q], query_ids[q]
        vf = v.astype(np.float64)
        norm = float(np.sqrt(vf @ vf))
        kept_ids, kept = np.zeros(0, ids.dtype), np.zeros(0, rows.dtype)
        least = float(floor[q])
        bound = lambda n: (float(vf @ n.centre) + norm * n.radius) * 1.0 + 1e-6 * (1.0 + abs(float(vf @ n.centre)) + norm * n.radius)  # noqa: B023, E731
        heap, turn = [(-bound(tree.root), 0, tree.root)], 1
        while heap and -heap[0][0] >= least:
            node = heapq.heappop(heap)[2]
            if node.rows is None:
                for child in node.below:
                    heapq.heappush(heap, (-bound(child), turn, child))
                    turn += 1
                continue
            scores = rows[node.rows] @ v
            ok = (ids[node.rows] != own) & (scores >= least)
            if not ok.any():
                continue
            kept_ids, kept = np.concatenate([kept_ids, ids[node.rows][ok]]), np.concatenate([kept, scores[ok]])
            if len(kept) > s.k:
                best = np.lexsort((kept_ids, -kept))[: s.k]
                kept_ids, kept = kept_ids[best], kept[best]
            if len(kept) >= s.k:
                least = max(least, float(kept.min()))
        if len(kept):
            yield q, kept_ids, kept


def _usable(rows: DataFrame) -> DataFrame:
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    v = F.transform("embedding", lambda x: x.cast("double"))
    return rows.select("vec_id", v.alias("v")).filter(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & ~F.exists("v", bad))


def _matrix(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_list()).astype(np.float64) if len(column) else np.zeros((0, 0))


def _found(s: Search, pairs) -> pd.DataFrame:
    out = [(int(qid), h, int(i), max(-LARGEST, min(LARGEST, int(x)))) for qid, h, ids, scores in pairs for i, x in zip(ids, scores, strict=True)]
    return pd.DataFrame(out, columns=["query_id", "h", "vec_id", "score"])


def _searched(s: Search):
    """Of rows sorted by (dim, shard, asks): the shard's tree is built from the rows that do not ask, and those that do stream past it."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        key, parts, ids, rows, objects, tree = None, [], None, None, None, None
        for batch in batches:
            for at, some in batch.groupby(["dim", "shard"], sort=False):
                if at != key:
                    key, parts, rows, objects, tree = at, [], None, None, None
                shard, asking = some[~some["asks"]], some[some["asks"]]
                if len(shard):
                    parts.append((shard["vec_id"].to_numpy(), _matrix(shard["v"])))
                if not len(asking) or not parts:
                    continue
                if rows is None:
                    ids, rows = np.concatenate([p[0] for p in parts]), integers(np.concatenate([p[1] for p in parts]), s.scale)
                    tree = BallTree(rows, s.leaf)
                q = integers(_matrix(asking["v"]), s.scale)
                x = rows
                if not exact_as_doubles(rows, q):
                    objects = wide(rows) if objects is None else objects
                    x, q = objects, wide(q)
                qid, h = asking["vec_id"].to_numpy(), asking["h"].to_numpy()
                floor = asking["floor"].fillna(-np.inf).to_numpy()
                yield _found(s, ((qid[i], h[i], found, scores) for i, found, scores in search_block(ids, x, qid, q, floor, s, tree)))

    return run


def _ranked(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id", "h").orderBy(F.col("score").desc(), F.col("vec_id"))
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def top_k(rows: DataFrame, is_query: Column, s: Search = Search()) -> DataFrame:
    """query_id, rank, vec_id, score of each query's k best rows among all others.

    Two passes over the shards: the home shard gives each query a floor, and
    then every other shard searches above it.
    """
    live = _usable(rows).withColumn("h", F.xxhash64("v")).withColumn("dim", F.size("v"))
    asking = live.filter(is_query).dropDuplicates(["vec_id", "h"])
    shards = max(1, -(-(live.agg(F.sum("dim")).first()[0] or 0) // s.shard_numbers))
    shard = F.pmod(F.xxhash64("vec_id", "h"), F.lit(shards)).cast("int")
    columns = ["vec_id", "v", "h", "dim", "shard", "asks", "floor"]
    none = F.lit(None).cast("double")
    base = live.select("vec_id", "v", "h", "dim", shard.alias("shard"), F.lit(False).alias("asks"), none.alias("floor"))
    home = asking.select("vec_id", "v", "h", "dim", shard.alias("shard"), F.lit(True).alias("asks"), none.alias("floor"))

    def searched(questions: DataFrame) -> DataFrame:
        met = base.unionByName(questions).repartition(shards, "dim", "shard").sortWithinPartitions("dim", "shard", "asks")
        return met.select(*columns).mapInPandas(_searched(s), "query_id long, h long, vec_id long, score long")

    first = cut(searched(home))
    if shards > 1:
        kth = first.groupBy("query_id", "h").agg(F.count("*").alias("n"), F.min("score").alias("least"))
        floor = kth.select(F.col("query_id").alias("vec_id"), "h", F.when(F.col("n") >= s.k, F.col("least").cast("double")).alias("floor"))
        away = home.drop("floor").join(floor, ["vec_id", "h"], "left").withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))).filter("other <> shard")
        first = first.unionByName(searched(away.drop("shard").withColumnRenamed("other", "shard").select(*columns)))
    return _ranked(first, s.k).select("query_id", "rank", "vec_id", "score")
