"""Drift check and selective update: staleness, uniqueness, priority, anchors, affinity, propagation, and what they cost in accuracy."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import cut


def score_drift(history: DataFrame, at: int | None = None, decay_rate: float = 0.99, decay: str = "recent") -> DataFrame:
    """(sample_id, drift): decayed mean change of a row's readings against the current one, relative to it.

    history: (sample_id, step, score). The current reading is the last, or that at a step. A current score of 0 gives 0
    where all readings agree, and null, which means leave out, where they do not.
    """
    w = Window.partitionBy("sample_id")
    rows = history if at is None else history.filter(F.col("step") <= at)
    rows = rows.withColumn("_last", F.max("step").over(w))
    now = rows.groupBy("sample_id").agg(F.max_by("score", "step").alias("_now"))
    rows = rows.join(now, "sample_id")
    away = F.col("_last") - F.col("step")
    weight = F.pow(F.lit(decay_rate), away if decay == "recent" else -away)
    sums = rows.groupBy("sample_id").agg(F.sum(weight * F.abs(F.col("score") - F.col("_now"))).alias("_change"), F.sum(weight * F.col("_now")).alias("_base"), F.max(F.abs("_now")).alias("_size"))
    small = F.col("_size") <= 1e-12
    return sums.select("sample_id", F.when(small & (F.col("_change") <= 1e-12), 0.0).when(~small, F.col("_change") / F.col("_base")).alias("drift"))


def fleet_drift(drift: DataFrame) -> float:
    return float(drift.agg(F.avg("drift")).first()[0] or 0.0)


def should_update(drift: float, delta: float) -> bool:
    return drift > delta


def staleness(nodes: DataFrame, step: int) -> DataFrame:
    return nodes.withColumn("staleness", F.lit(step) - F.col("last_step"))


def uniqueness(nodes: DataFrame, edges: DataFrame, isolated: str = "zero") -> DataFrame:
    """Distance of a row's score from the weighted mean of its neighbours'; isolated rows get 0, or their distance from the mean of all."""
    other = nodes.select(F.col("sample_id").alias("dst"), F.col("score").alias("_s"))
    mean = edges.select("src", "dst", "w").join(other, "dst").groupBy("src").agg((F.sum(F.col("w") * F.col("_s")) / F.sum("w")).alias("_m"))
    out = nodes.join(mean.withColumnRenamed("src", "sample_id"), "sample_id", "left")
    if isolated == "mean":
        out = out.crossJoin(F.broadcast(nodes.agg(F.avg("score").alias("_all")))).withColumn("_m", F.coalesce("_m", "_all")).drop("_all")  # one row
    return out.withColumn("uniqueness", F.coalesce(F.abs(F.col("score") - F.col("_m")), F.lit(0.0))).drop("_m")


def priority(nodes: DataFrame, edges: DataFrame, step: int, min_staleness: int = 1, isolated: str = "zero") -> DataFrame:
    rows = uniqueness(staleness(nodes, step), edges, isolated)
    value = F.when(F.col("staleness") >= min_staleness, F.col("staleness") * F.col("uniqueness")).otherwise(0.0)
    return rows.withColumn("priority", value)


#: Undecided rows that the sequential rule takes into one task.
ONE_TASK_ROWS = 20_000


def choose_anchors(ranked: DataFrame, edges: DataFrame, budget: int) -> DataFrame:
    """(sample_id, priority) of the greedy independent set in order of priority, ties by id, up to a budget.

    Rounds of local maxima: an undecided row that beats all undecided neighbours is what the sequential order would
    take, and its neighbours are out. They go on until the budget's last anchor beats every undecided row, or so few
    are left that one task applies the rule itself; each round decides one row at least. Rows without priority never become anchors.
    """
    live = cut(ranked.select("sample_id", F.round("priority", 9).alias("priority")).filter("priority > 0"))
    links = cut(edges.select("src", "dst").join(live.select(F.col("sample_id").alias("src")), "src", "left_semi").join(live.select(F.col("sample_id").alias("dst")), "dst", "left_semi"))
    order = [F.col("priority").desc(), F.col("sample_id")]
    taken = live.limit(0)
    rank = F.struct("priority", (-F.col("sample_id")).alias("n"))
    while live.count() > ONE_TASK_ROWS:
        ranks = live.select("sample_id", rank.alias("r"))
        around = links.join(ranks.withColumnRenamed("sample_id", "dst"), "dst").groupBy("src").agg(F.max("r").alias("m"))
        new = cut(ranks.join(around.withColumnRenamed("src", "sample_id"), "sample_id", "left").filter(F.col("m").isNull() | (F.col("r") > F.col("m"))).select("sample_id", "r.priority"))
        taken = cut(taken.unionByName(new))
        out = links.join(new.select(F.col("sample_id").alias("src")), "src", "left_semi").select(F.col("dst").alias("sample_id")).union(new.select("sample_id")).distinct()
        live = cut(live.join(out, "sample_id", "left_anti"))
        last = taken.orderBy(*order).limit(budget).agg(F.count("*"), F.min(rank)).first()
        if last[0] == budget and (not budget or live.agg(F.max(rank)).first()[0] is None or live.agg(F.max(rank)).first()[0] < last[1]):
            return taken.orderBy(*order).limit(budget)

    def run(key: tuple, rows: pd.DataFrame, pairs: pd.DataFrame) -> pd.DataFrame:
        near: dict[int, set[int]] = {}
        for a, b in zip(pairs["src"], pairs["dst"], strict=True):
            near.setdefault(int(a), set()).add(int(b))
        chosen = set(choose_anchors_sequential(list(zip(rows["sample_id"].tolist(), rows["priority"].tolist(), strict=True)), near, budget))
        return rows[rows["sample_id"].isin(chosen)][["sample_id", "priority"]]

    one, few = F.lit(1).alias("one"), live.select("sample_id")
    pairs = links.join(few.withColumnRenamed("sample_id", "src"), "src", "left_semi").join(few.withColumnRenamed("sample_id", "dst"), "dst", "left_semi")
    rest = live.select("*", one).groupBy("one").cogroup(pairs.select("*", one).groupBy("one")).applyInPandas(run, "sample_id long, priority double")
    return taken.unionByName(rest).orderBy(*order).limit(budget)


def choose_anchors_sequential(ranked: list[tuple[int, float]], neighbours: dict[int, set[int]], budget: int) -> list[int]:
    """The rule itself, for small inputs and tests."""
    out: list[int] = []
    beside: set[int] = set()
    for i, p in sorted(ranked, key=lambda x: (-x[1], x[0])):
        if len(out) == budget:
            break
        if p > 0 and i not in beside:
            out.append(i)
            beside |= neighbours.get(i, set())
    return out


def affinity(edges: DataFrame, nodes: DataFrame, scale: float = 0.1) -> DataFrame:
    """Edges with affinity: weight, less for old scores that differ."""
    a = nodes.select(F.col("sample_id").alias("src"), F.col("score").alias("_a"))
    b = nodes.select(F.col("sample_id").alias("dst"), F.col("score").alias("_b"))
    return edges.join(a, "src").join(b, "dst").withColumn("affinity", F.col("w") * F.exp(-scale * F.abs(F.col("_a") - F.col("_b")))).drop("_a", "_b")


def eligible(edges: DataFrame, affinity_min: float) -> DataFrame:
    return edges.filter(F.col("affinity") > affinity_min)


def _sources(nodes: DataFrame, anchors: DataFrame, anchors_from: str, step: int | None) -> DataFrame:
    """(dst, _new) of the rows whose values spread: re-extracted ones, also those just trained on, or all."""
    new = anchors.select(F.col("sample_id").alias("dst"), F.col("score_new").alias("_new"))
    if anchors_from == "recal":
        return new
    others = nodes.join(anchors.select("sample_id"), "sample_id", "left_anti")
    if anchors_from == "recal+recent":
        others = others.filter(F.col("last_step") >= step - 1)
    return new.unionByName(others.select(F.col("sample_id").alias("dst"), F.col("score").alias("_new")))


def propagate_scores(nodes: DataFrame, edges: DataFrame, anchors: DataFrame, momentum: float = 0.5, blend: str = "half", anchors_from: str = "recal", affinity_min: float = 0.5, scale: float = 0.1, step: int | None = None) -> DataFrame:
    """nodes with score_new: anchors exact; rows with eligible neighbours blended with their weighted mean; others unchanged. One hop."""
    good = eligible(affinity(edges, nodes, scale), affinity_min).join(_sources(nodes, anchors, anchors_from, step), "dst")
    sums = good.groupBy("src").agg(F.sum(F.col("w") * F.col("_new")).alias("_ws"), F.sum("w").alias("_w"))
    out = nodes.join(sums.withColumnRenamed("src", "sample_id"), "sample_id", "left")
    out = out.join(anchors.select("sample_id", F.col("score_new").alias("_exact")), "sample_id", "left")
    mixed = momentum * F.col("score") + (1 - momentum) * F.col("_ws") / F.col("_w") if blend == "half" else (F.col("score") + F.col("_ws")) / (1 + F.col("_w"))
    return out.withColumn("score_new", F.coalesce("_exact", mixed, "score")).drop("_ws", "_w", "_exact")


def energy(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """Value of the quadratic energy: squared change of rows, and weighted squared differences to neighbours."""
    other = nodes.select(F.col("sample_id").alias("dst"), F.col("score_new").alias("_o"))
    pull = edges.join(nodes.select(F.col("sample_id").alias("src"), "score_new"), "src").join(other, "dst").agg(F.sum(F.col("w") * (F.col("score_new") - F.col("_o")) ** 2).alias("smoothness"))
    stay = nodes.agg(F.sum((F.col("score_new") - F.col("score")) ** 2).alias("fidelity"))
    return stay.crossJoin(pull)  # one row each


def embedding_shift(anchors: DataFrame) -> DataFrame:
    """Mean distance between (vec, vec_new)."""
    gap = F.sqrt(F.aggregate(F.zip_with("vec", "vec_new", lambda x, y: (x - y) ** 2), F.lit(0.0), lambda s, x: s + x))
    return anchors.agg(F.avg(gap).alias("shift"))


def propagate_vectors(nodes: DataFrame, edges: DataFrame, anchors: DataFrame, momentum: float = 0.5, affinity_min: float = 0.5, scale: float = 0.1) -> DataFrame:
    """(sample_id, vec_new) by the rule of the scores, component by component."""
    good = eligible(affinity(edges, nodes, scale), affinity_min).select("src", "dst", "w")
    parts = good.join(anchors.select(F.col("sample_id").alias("dst"), F.posexplode("vec_new").alias("j", "x")), "dst")
    means = parts.groupBy("src", "j").agg((F.sum(F.col("w") * F.col("x")) / F.sum("w")).alias("m")).groupBy("src").agg(F.array_sort(F.collect_list(F.struct("j", "m"))).alias("ms"))
    out = nodes.join(means.withColumnRenamed("src", "sample_id"), "sample_id", "left").join(anchors.select("sample_id", F.col("vec_new").alias("_exact")), "sample_id", "left")
    mixed = F.zip_with("vec", F.transform("ms", lambda p: p["m"]), lambda a, b: momentum * a + (1 - momentum) * b)
    return out.select("sample_id", F.coalesce("_exact", mixed, "vec").alias("vec_new"))


def change_bound(nodes: DataFrame, anchors: DataFrame) -> DataFrame:
    """Largest change of rows that are no anchors, and the bound: half the largest gap between a spread value and an old one."""
    rest = nodes.join(anchors.select("sample_id"), "sample_id", "left_anti").agg(F.max(F.abs(F.col("score_new") - F.col("score"))).alias("largest_change"))
    old = nodes.agg(F.min("score").alias("_lo"), F.max("score").alias("_hi"))
    new = anchors.agg(F.min("score_new").alias("_l"), F.max("score_new").alias("_h"))
    gap = F.greatest(F.col("_h") - F.col("_lo"), F.col("_hi") - F.col("_l"))
    return rest.crossJoin(old).crossJoin(new).select("largest_change", (gap / 2).alias("bound"))  # one row each


def selective_error(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """Largest, mean and root mean squared difference of (sample_id, score_new) from (sample_id, score_exact)."""
    d = F.col("score_new") - F.col("score_exact")
    return approximate.join(exact, "sample_id").agg(F.max(F.abs(d)).alias("max_error"), F.avg(F.abs(d)).alias("mean_error"), F.sqrt(F.avg(d * d)).alias("rmse"), F.corr("score_new", "score_exact").alias("correlation"))
