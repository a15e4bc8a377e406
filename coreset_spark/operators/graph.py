"""Mutual nearest-neighbour graph: exact and hashed search, mutual filter, edge weights, local repair.

Both searches are products of matrices of bounded blocks, of which each row sends its k nearest on; pairs are never
listed. The hashed one looks only into the buckets of random hyperplanes that a row's own signs name, and into those
that its least certain signs might have named; how many of them are needed is measured on a sample of rows against
an exact search, and a setting that looks at no fewer pairs than there are gives way to the exact search itself.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import KNN
from ..sources.tables import draw_pool
from .blocks import SIDE, deal, every, meet, together
from .proxy import matrix
from .ranks import quantile
from .storage import cut

PLACES = 12  # distances are compared to so many decimals, then by id
FEW = 100_000  # rows of two numbers that are broadcast


@dataclass(frozen=True)
class Hashing:
    """tables: of hyperplanes. bits: hyperplanes of each. loose: a question's least certain bits, of which all signs are looked up. No bits are one bucket, which is the exact search."""

    tables: int = 1
    bits: int = 0
    loose: int = 0
    seed: int = 42

    def share(self) -> float:
        """Of all pairs, those that a search looks at where buckets are even."""
        return self.tables * 2.0 ** (self.loose - self.bits)


EVERY = Hashing()


def _vectors(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_list()) if len(column) else np.zeros((0, 0))


def _apart(x: np.ndarray, y: np.ndarray, metric: str) -> np.ndarray:
    if metric == "cosine":
        x, y = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300) for v in (x, y))
        return 1 - x @ y.T
    return np.maximum((x**2).sum(1)[:, None] + (y**2).sum(1)[None, :] - 2 * x @ y.T, 0)


def nearest(d: np.ndarray, k: int) -> np.ndarray:
    """Mask of each row's k least distances to PLACES decimals, ties to the first columns; infinite ones are none."""
    d = np.round(d, PLACES)
    if d.shape[1] <= k:
        return np.isfinite(d)
    kth = np.partition(d, k - 1, axis=1)[:, k - 1 : k]
    less, tie = d < kth, d == kth
    return (less | tie & (np.cumsum(tie, axis=1) <= k - less.sum(1, keepdims=True))) & np.isfinite(d)


#: Rows of a tile and its most columns, and candidates of a row in a tile that are looked at one by one.
TALL, ACROSS, ALONE = 1024, 2048, 64


def _sieve(x: np.ndarray, y: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, float, float] | None:
    """What finds candidates in single precision: (left, right, own, size, slack), so that a distance is no less than
    size * (left @ right + own - slack); None where that would not hold."""
    if metric == "cosine":
        size, a, b, own = 1.0, x, np.vstack([-y.T, np.ones(len(y))]), np.zeros(len(x))
    else:
        high = math.sqrt(max((x**2).sum(1).max(), (y**2).sum(1).max()))
        if not 1e-100 < high < 1e100:
            return None
        size, a, c = high**2, x / high, y / high
        b, own = np.vstack([-2 * c.T, (c**2).sum(1)]), (a**2).sum(1)
    left = np.hstack([a, np.ones((len(x), 1))]).astype(np.float32)
    return left, b.astype(np.float32), own, size, 8 * (x.shape[1] + 32) * 2.0**-24


def closest(x: np.ndarray, y: np.ndarray, src: np.ndarray, dst: np.ndarray, k: int, metric: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, distance) of each x's k nearest y but those of its own id, to PLACES decimals, ties to the first columns.

    Single precision tells which pairs may be nearer than the k nearest of the columns before; these alone are measured.
    """
    if metric == "cosine":
        x, y = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300) for v in (x, y))
    sieve = _sieve(x, y, metric) if k and len(x) * len(y) > TALL * ACROSS else None
    xx, yy = (x**2).sum(1), (y**2).sum(1)
    out = []
    for i in range(0, len(x), TALL):
        u, ids, sums = x[i : i + TALL], src[i : i + TALL], xx[i : i + TALL]
        dist, at = np.full((len(u), k), np.inf), np.zeros((len(u), k), np.int64)  # in order of distance and column

        def add(rows: np.ndarray, d: np.ndarray, cols: np.ndarray) -> None:
            """d: distances of some rows, to columns in ascending order."""
            d, c = np.concatenate([dist[rows], d], 1), np.concatenate([at[rows], cols], 1)  # noqa: B023
            place = np.argsort(np.round(d, PLACES), axis=1, kind="stable")[:, :k]
            dist[rows], at[rows] = np.take_along_axis(d, place, 1), np.take_along_axis(c, place, 1)  # noqa: B023

        def all_of(rows: np.ndarray, j: int, stop: int) -> None:
            """Every column from j on: their k nearest first, as a place or two are not worth an order of all."""
            for a in range(0, len(rows), 256):
                part = rows[a : a + 256]
                d = 1 - u[part] @ y[j:stop].T if metric == "cosine" else np.maximum(sums[part][:, None] + yy[None, j:stop] - 2 * u[part] @ y[j:stop].T, 0)  # noqa: B023
                d[ids[part][:, None] == dst[None, j:stop]] = np.inf  # noqa: B023
                r, c = np.nonzero(nearest(d, k))
                add(part, *_padded(len(part), r, d[r, c], c + j))

        j, wide = 0, ACROSS if sieve is None else min(256, ACROSS)
        while j < len(y):
            stop = min(len(y), j + wide)
            if sieve is None or j == 0:
                all_of(np.arange(len(u)), j, stop)
            else:
                left, right, own, size, slack = sieve
                limit = np.minimum((dist[:, -1] + 2 * 10.0**-PLACES) / size - own[i : i + TALL] + slack, 3e38) if metric == "l2" else dist[:, -1] + 2 * 10.0**-PLACES + slack
                limit = np.nextafter(limit.astype(np.float32), np.float32(np.inf))
                r, c = np.divmod(np.flatnonzero(left[i : i + TALL] @ right[:, j:stop] <= limit[:, None]), stop - j)
                n = np.bincount(r, minlength=len(u))
                many = np.flatnonzero(n > ALONE)
                if len(many):
                    all_of(many, j, stop)
                    few = n[r] <= ALONE
                    r, c = r[few], c[few]
                c += j
                dots = np.einsum("ij,ij->i", u[r], y[c])
                d = 1 - dots if metric == "cosine" else np.maximum(sums[r] + yy[c] - 2 * dots, 0)
                near = (np.round(d, PLACES) < np.round(dist[r, -1], PLACES)) & (ids[r] != dst[c])
                rows, r = np.unique(r[near], return_inverse=True)
                if len(rows):
                    add(rows, *_padded(len(rows), r, d[near], c[near]))
            j, wide = stop, min(ACROSS, 2 * wide)
        r, c = np.nonzero(np.isfinite(dist))
        out.append((r + i, at[r, c], dist[r, c]))
    return tuple(np.concatenate(v) for v in zip(*out, strict=True))


def _padded(rows: int, r: np.ndarray, d: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values and columns of pairs sorted by row, a line a row, with infinite distances behind them."""
    n = np.bincount(r, minlength=rows)
    place = np.arange(len(r)) - np.repeat(np.cumsum(n) - n, n)
    dist, at = np.full((rows, n.max(initial=0)), np.inf), np.zeros((rows, n.max(initial=0)), np.int64)
    dist[r, place], at[r, place] = d, c
    return dist, at


def _near(k: int, metric: str, radius: bool = False):
    """Of a block of askers and one of rows: each asker's k nearest rows; with a radius, also each row's nearest askers within its own."""
    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        empty = pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "d2": pa.array([], pa.float64())})
        if not a.num_rows or not b.num_rows:
            return empty
        a, b = a.sort_by("sample_id").combine_chunks(), b.sort_by("sample_id").combine_chunks()
        vec = lambda t: matrix(t["vec"].combine_chunks())
        src, dst = (t["sample_id"].to_numpy() for t in (a, b))
        if not radius:
            i, j, d = closest(vec(a), vec(b), src, dst, k, metric)
            return pa.table({"src": src[i], "dst": dst[j], "d2": d})
        d = _apart(vec(a), vec(b), metric)
        d[src[:, None] == dst[None, :]] = np.inf
        i, j = np.nonzero(nearest(d, k))
        out = [(src[i], dst[j], d[i, j])]
        i, j = np.nonzero(nearest(d.T, k) & (np.round(d.T, PLACES) <= b["radius"].to_numpy()[:, None]))
        out.append((dst[i], src[j], d[j, i]))
        s, t, v = (np.concatenate(x) for x in zip(*out, strict=True))
        return pa.table({"src": s, "dst": t, "d2": v})

    return run


FOUND = "src long, dst long, d2 double"


#: Rows of a block of the exact search at most, and the blocks that are made of fewer rows, for as many tasks as their pairs.
LARGE, BLOCKS = 32_768, 8


def knn_exact(rows: DataFrame, k: int = 10, metric: str = "l2", block: int = SIDE) -> DataFrame:
    """(src, dst, d2, rank) of each row's k nearest others, ties to the smaller id, by pairs of blocks. A pair is one task for
    both directions, and blocks are as large as a task takes, as every row is shuffled, and tells its nearest, once a block."""
    rows, near = rows.select("sample_id", "vec"), _near(k, metric)
    n = rows.count()
    blocks = max(1, math.ceil(n / LARGE), min(BLOCKS, math.ceil(n / block)))

    def run(key: tuple, both: pa.Table) -> pa.Table:
        i, j = (int(x.as_py()) for x in key)
        if i == j:
            return near(both, both)
        at = both["_b"].to_numpy()
        a, b = (both.filter(pa.array(at == x)).select(["sample_id", "vec"]) for x in (i, j))
        return pa.concat_tables([near(a, b), near(b, a)])

    dealt = rows.withColumn("_b", deal(blocks)).withColumn("_o", every(blocks))
    dealt = dealt.select("sample_id", "vec", "_b", F.least("_b", "_o").alias("_i"), F.greatest("_b", "_o").alias("_j"))
    return top(dealt.groupBy("_i", "_j").applyInArrow(run, FOUND), k)


def near_rows(askers: DataFrame, rows: DataFrame, k: int, slack: float = 1e-9) -> DataFrame:
    """(src, dst) of each block's rows that are among an asker's k nearest there, or no farther than the last of them by more than a slack for what products of matrices round."""
    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64())})
        src, dst = a["sample_id"].to_numpy(), b["sample_id"].to_numpy()
        d = _apart(matrix(a["vec"].combine_chunks()), matrix(b["vec"].combine_chunks()), "l2")
        d[src[:, None] == dst[None, :]] = np.inf
        kth = np.partition(d, k - 1, axis=1)[:, k - 1 : k] if d.shape[1] > k else np.inf
        i, j = np.nonzero((d <= kth + slack) & np.isfinite(d))
        return pa.table({"src": src[i], "dst": dst[j]})

    return meet(askers.select("sample_id", "vec"), rows.select("sample_id", "vec"), run, "src long, dst long")


def top(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("src").orderBy(F.round("d2", PLACES), "dst")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def _planes(how: Hashing, dims: int) -> np.ndarray:
    return np.random.default_rng(how.seed).normal(size=(how.tables, how.bits, dims))


def _signs(x: np.ndarray, how: Hashing) -> tuple[np.ndarray, np.ndarray]:
    """(rows, tables, bits): distances from the hyperplanes, and which side."""
    away = np.einsum("nd,tbd->ntb", x, _planes(how, x.shape[1]))
    return away, away > 0


def codes(rows: DataFrame, how: Hashing, asking: bool = False) -> DataFrame:
    """rows with code, once for each bucket that a row lies in, or that it asks."""
    loose = how.loose if asking else 0

    @F.pandas_udf("array<long>")
    def buckets(vec: pd.Series) -> pd.Series:
        away, sign = _signs(_vectors(vec), how)
        weight = 1 << np.arange(how.bits, dtype=np.int64)
        own = (sign * weight).sum(2) + (np.arange(how.tables, dtype=np.int64) << how.bits)[None, :]
        least = weight[np.argsort(np.abs(away), axis=2, kind="stable")[:, :, :loose]]
        turned = np.stack([(least * ((c >> np.arange(loose)) & 1)).sum(2) for c in range(1 << loose)], 2)  # of different bits: sums are as good as or
        return pd.Series(list((own[:, :, None] ^ turned).reshape(len(vec), -1)))

    if how.bits == 0:
        return rows.withColumn("code", F.lit(0).cast("long"))
    return rows.withColumn("code", F.explode(buckets("vec")))


def _search(askers: DataFrame, rows: DataFrame, k: int, how: Hashing, block: int = SIDE, radius: bool = False) -> DataFrame:
    """(src, dst, d2) of every bucket's near pairs; buckets of more than a block are split on both sides."""
    left, right = codes(askers.select("sample_id", "vec"), how, True), codes(rows, how)
    count = lambda x, n: x.groupBy("code").agg(F.ceil(F.count("*") / block).cast("int").alias(n)).filter(F.col(n) > 1)
    large = cut(count(left.drop("vec"), "a").join(count(right.drop("vec"), "b"), "code", "full"))  # a number for each block at most
    large = F.broadcast(large) if large.count() <= FEW else large
    one = lambda n: F.coalesce(n, F.lit(1))
    left = left.join(large, "code", "left").withColumn("i", deal(one("a"))).withColumn("j", every(one("b"))).drop("a", "b")
    right = right.join(large, "code", "left").withColumn("j", deal(one("b"))).withColumn("i", every(one("a"))).drop("a", "b")
    found = together(left, right, ["code", "i", "j"], _near(k, "l2", radius), FOUND)
    return found.groupBy("src", "dst").agg(F.min("d2").alias("d2"))


def calibrate(rows: DataFrame, k: int = 10, recall: float = 0.95, sample: int = 200, seed: int = 42, tables: tuple[int, ...] = (1, 2, 4, 8, 16), bucket: int = 64) -> Hashing:
    """The cheapest setting whose recall on a hash-drawn sample of rows reaches a bound; EVERY where none is cheaper than all pairs.

    Buckets hold ``bucket`` rows or more, so bits grow with the rows. The sample's true neighbours come from one exact
    search against all rows; which least certain bits a table needs to reach each of them is read off their vectors.
    """
    n = rows.count()
    if n <= bucket:
        return EVERY
    asked = cut(draw_pool(rows.select("sample_id", "vec"), sample, seed))
    true = top(_search(asked, rows.select("sample_id", "vec"), k, EVERY), k).select("src", "dst")
    v = rows.select(F.col("sample_id").alias("dst"), F.col("vec").alias("y"))
    both = v.join(F.broadcast(true), "dst").join(F.broadcast(asked.select(F.col("sample_id").alias("src"), "vec")), "src").select("vec", "y").toPandas()  # sample times k pairs
    x, y = _vectors(both["vec"]), _vectors(both["y"])
    best = EVERY
    for bits in range(1, max(1, int(math.log2(n / bucket))) + 1):
        how = Hashing(max(tables), bits, 0, seed)
        (away, a), (_, b) = _signs(x, how), _signs(y, how)
        place = np.argsort(np.argsort(np.abs(away), axis=2, kind="stable"), axis=2)
        need = np.where(a != b, place + 1, 0).max(2)  # least certain bits that a table has to turn
        for some in tables:
            for loose in range(bits + 1):
                found = Hashing(some, bits, loose, seed)
                if found.share() < best.share() and (need[:, :some].min(1) <= loose).mean() >= recall:
                    best = found
    # the planes of fewer tables are the first of those of more
    return best


def knn_lsh(rows: DataFrame, k: int = 10, how: Hashing | None = None, askers: DataFrame | None = None, block: int = SIDE) -> DataFrame:
    """Nearest among the rows of the buckets that a row asks; of some rows only where askers are given. how: calibrated where none is given."""
    rows = rows.select("sample_id", "vec")
    asking = rows if askers is None else rows.join(askers.select("sample_id"), "sample_id", "left_semi")
    return top(_search(asking, rows, k, how or calibrate(rows, k), block), k)


@F.pandas_udf(T.DoubleType())
def _d2(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series(((_vectors(a) - _vectors(b)) ** 2).sum(1)) if len(a) else pd.Series([], dtype=float)


def distances(pairs: DataFrame, rows: DataFrame) -> DataFrame:
    """Squared distances of (src, dst)."""
    a = rows.select(F.col("sample_id").alias("src"), F.col("vec").alias("x"))
    b = rows.select(F.col("sample_id").alias("dst"), F.col("vec").alias("y"))
    return pairs.join(a, "src").join(b, "dst").select("src", "dst", _d2("x", "y").alias("d2"))


def mutual_edges(knn: DataFrame) -> DataFrame:
    """Both directions of the pairs that have each other in their lists."""
    back = knn.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return knn.select("src", "dst", "d2").join(back, ["src", "dst"], "left_semi")


def weight_edges(edges: DataFrame, bandwidth: float | str = 100.0) -> DataFrame:
    """exp(-d2 / bandwidth); 'median' takes the median squared length of the edges."""
    if bandwidth == "median":
        return edges.withColumn("w", F.exp(-F.col("d2") / F.lit(quantile(edges, "d2", 0.5))))
    return edges.withColumn("w", F.exp(-F.col("d2") / float(bandwidth)))


def knn(rows: DataFrame, k: int = 10, how: Hashing | None = None) -> DataFrame:
    """Lists by the hashed search, or by all pairs where there is no setting."""
    return knn_exact(rows, k) if how is None else knn_lsh(rows, k, how)


def build_graph(rows: DataFrame, k: int = 10, bandwidth: float | str = 100.0, metric: str = "l2", how: Hashing | None = None) -> DataFrame:
    """Weighted edges (src, dst, d2, w) in both directions; degrees never exceed k. how: a setting of the hashed search."""
    if how is not None and metric != "l2":
        raise ValueError("the hashed search measures squared distances")
    lists = knn_exact(rows, k, metric) if how is None else knn_lsh(rows, k, how)
    # both directions, and a median's several passes, must not search anew
    edges = mutual_edges(cut(lists))
    return weight_edges(edges if bandwidth != "median" else cut(edges), bandwidth)


def repair_graph(rows: DataFrame, lists: DataFrame, changed: DataFrame, k: int = 10, how: Hashing | None = None, bandwidth: float | str = 100.0) -> tuple[DataFrame, DataFrame]:
    """Lists and edges after some vectors changed; rows have the new ones.

    Searched anew are the lists of changed rows and of rows that had one in their list. To all other lists those changed
    rows are added that now lie within their reach. Without a setting candidates are all rows, and the lists are those
    of a new build; with one they are as near to them as its recall.
    """
    rows, how = rows.select("sample_id", "vec"), how or EVERY
    ids = cut(changed.select("sample_id").distinct())
    listed = lists.join(ids.withColumnRenamed("sample_id", "dst"), "dst", "left_semi").select(F.col("src").alias("sample_id"))
    touched = cut(ids.union(listed).distinct())
    reach = lists.groupBy(F.col("src").alias("sample_id")).agg(F.when(F.count("*") >= k, F.round(F.max("d2"), PLACES)).otherwise(float("inf")).alias("radius"))
    others = rows.join(touched, "sample_id", "left_anti").join(reach, "sample_id", "left").withColumn("radius", F.coalesce("radius", F.lit(float("inf"))))
    moved = rows.join(ids, "sample_id", "left_semi")
    asked = touched.withColumnRenamed("sample_id", "src")
    entering = _search(moved, others, k, how, radius=True).join(asked, "src", "left_anti")
    stay = lists.join(asked, "src", "left_anti").select("src", "dst", "d2").unionByName(entering)
    again = _search(rows.join(touched, "sample_id", "left_semi"), rows, k, how)
    fresh = cut(top(stay.unionByName(again), k).to(T.StructType.fromDDL(KNN)))
    return fresh, weight_edges(mutual_edges(fresh), bandwidth)


def knn_recall(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    hit = approximate.select("src", "dst").join(exact.select("src", "dst"), ["src", "dst"], "left_semi").agg(F.count("*").alias("hits"))
    return hit.crossJoin(exact.agg(F.count("*").alias("total"))).select((F.col("hits") / F.col("total")).alias("recall"))  # one row each
