"""The training loop: draw a pool, select, train an interval, check for drift, update the graph where it pays.

Only control decisions and model parameters are on the driver. Nodes, edges and readings are
checkpointed each interval, so lineage never grows.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import SelectorConfig
from ..operators import graph, scores, select, update
from ..operators.proxy import SoftmaxProxy, lr_at
from ..operators.storage import cut
from ..sources.tables import draw_pool


class History:
    """Score readings, only ever added to: runs of about equal length are merged, so that a reading is written again as often as the number of runs doubles."""

    def __init__(self) -> None:
        self.runs: list[tuple[int, DataFrame]] = []  # level, readings

    def add(self, readings: DataFrame) -> None:
        self.runs.append((0, cut(readings.select("sample_id", "step", "score"))))
        while len(self.runs) > 1 and self.runs[-1][0] == self.runs[-2][0]:
            (_, b), (level, a) = self.runs.pop(), self.runs.pop()
            self.runs.append((level + 1, cut(a.unionByName(b))))

    def frame(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [rows for _, rows in self.runs])


LOG = "interval int, picks long, checked long, drift double, fired boolean, anchors long, propagated long, shift double, repaired boolean, edges_changed long"


@dataclass
class RunResult:
    model: SoftmaxProxy
    picks: DataFrame
    nodes: DataFrame
    edges: DataFrame
    seen: DataFrame
    log: list[dict] = field(default_factory=list)
    seconds: dict = field(default_factory=dict)

    def frame(self, spark) -> DataFrame:
        names = [x.split()[0] for x in LOG.split(", ")]
        return spark.createDataFrame([tuple(x[n] for n in names) for x in self.log], LOG)


class Clock:
    """Seconds by stage; each call closes the stage that ran since the last."""

    def __init__(self) -> None:
        self.seconds: dict[str, float] = {}
        self.at = time.time()

    def close(self, stage: str) -> None:
        now = time.time()
        self.seconds[stage] = self.seconds.get(stage, 0.0) + now - self.at
        self.at = now


def _searched(nodes: DataFrame, cfg: SelectorConfig) -> tuple[DataFrame, DataFrame, graph.Hashing | None]:
    """Lists, edges, and the setting of the hashed search, if the run uses it."""
    rows = nodes.select("sample_id", "vec")
    how = graph.calibrate(rows, cfg.k, cfg.recall, seed=cfg.seed) if cfg.search == "hashed" else None
    lists = cut(graph.knn(rows, cfg.k, how))
    return lists, cut(graph.weight_edges(graph.mutual_edges(lists), cfg.bandwidth)), how


def _difference(a: DataFrame, b: DataFrame) -> int:
    """Undirected edges in one of the two graphs only."""
    a, b = (x.filter("src < dst").select("src", "dst") for x in (a, b))
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def check_and_update(nodes: DataFrame, edges: DataFrame, knn: DataFrame, rows: DataFrame, model: SoftmaxProxy, subset: DataFrame, history: DataFrame, step: int, cfg: SelectorConfig, how: graph.Hashing | None = None) -> tuple[DataFrame, DataFrame, DataFrame, dict]:
    """One round: probe, drift, and if it fires: anchors, exact re-extraction, propagation of scores and vectors, local repair. how: the setting of a hashed search."""
    probe = draw_pool(subset, cfg.probe_size, cfg.seed, step)
    now = model.extract(rows.join(probe.select("sample_id"), "sample_id", "left_semi")).select("sample_id", F.lit(step).cast("long").alias("step"), "score")
    past = history.join(probe.select("sample_id"), "sample_id", "left_semi")
    drift = update.fleet_drift(update.score_drift(past.unionByName(now), None, cfg.decay_rate, cfg.decay))
    note = {"checked": probe.count(), "drift": round(drift, 6), "fired": False, "anchors": 0, "propagated": 0, "shift": 0.0, "repaired": False, "edges_changed": 0}
    always = cfg.update_policy == "always"
    if cfg.update_policy in ("never", "frozen_subset") or not (always or update.should_update(drift, cfg.delta)):
        return nodes, edges, knn, note
    chosen = cut(update.choose_anchors(update.priority(nodes, edges, step, cfg.min_staleness), edges, cfg.recompute_budget))
    exact = cut(model.extract(rows.join(chosen.select("sample_id"), "sample_id", "left_semi")).select("sample_id", F.col("score").alias("score_new"), F.col("vec").alias("vec_new")))
    spread = cut(update.propagate_scores(nodes, edges, exact, cfg.momentum, cfg.blend, cfg.anchors_from, cfg.affinity_min, cfg.affinity_scale, step))
    shift = float(update.embedding_shift(exact.join(nodes.select("sample_id", "vec"), "sample_id")).first()[0] or 0.0)
    note |= {"fired": True, "anchors": exact.count(), "propagated": spread.filter(F.abs(F.col("score_new") - F.col("score")) > 0).count(), "shift": round(shift, 6)}
    fresh = exact.select("sample_id", F.lit(step).cast("long").alias("_step"))
    out = spread.join(fresh, "sample_id", "left").select("sample_id", "vec", F.col("score_new").alias("score"), F.coalesce("_step", "last_step").alias("last_step"))
    if shift > cfg.delta_h:
        moved = update.propagate_vectors(nodes, edges, exact, cfg.momentum, cfg.affinity_min, cfg.affinity_scale)
        out = cut(out.drop("vec").join(moved.withColumnRenamed("vec_new", "vec"), "sample_id").select("sample_id", "vec", "score", "last_step"))
        still = out.join(nodes.select("sample_id", F.col("vec").alias("_old")), "sample_id").filter(F.col("vec") != F.col("_old"))
        old = edges
        knn, edges = graph.repair_graph(out, knn, still, cfg.k, how, cfg.bandwidth)
        edges = cut(edges)
        note |= {"repaired": True, "edges_changed": _difference(old, edges)}
    return cut(out), edges, knn, note


def _batch(subset: DataFrame, cfg: SelectorConfig, budget: int, step: int) -> DataFrame:
    """The picks that a step trains on: all, or its share of this pass over them, dealt anew each pass."""
    if not cfg.batch or cfg.batch >= budget:
        return subset
    parts = math.ceil(budget / cfg.batch)
    turn, part = divmod(step, parts)
    return subset.filter(F.pmod(F.xxhash64("sample_id", F.lit(cfg.seed), F.lit(turn)), F.lit(parts)) == part)


def _selected(nodes: DataFrame, edges: DataFrame, pool_n: int, b: int, turn: int, cfg: SelectorConfig) -> DataFrame:
    """This interval's picks from a fresh pool, for what the configured universe is."""
    weighed = scores.weighted(nodes, cfg)
    pool = draw_pool(weighed, pool_n, cfg.seed, turn)
    if cfg.universe == "graph":
        engine = cfg.engine if cfg.engine in ("graph", "dominance") else "graph"
        return select.select_greedy(pool, None, b, cfg.lam, engine, edges=edges, balance=cfg.balance)
    universe = {"train": weighed, "pool": None, "sample": draw_pool(weighed, cfg.universe_sample, cfg.seed + 1, turn)}[cfg.universe]
    return select.select_greedy(pool, universe, b, cfg.lam, cfg.engine, cfg.sim_mode, seed=cfg.seed, edges=edges, balance=cfg.balance)


def run_adaptive(rows: DataFrame, cfg: SelectorConfig = SelectorConfig(), model: SoftmaxProxy | None = None) -> RunResult:
    """rows: (sample_id, vec, label). Trains from the initial parameters, on indicators of a warmed copy."""
    clock = Clock()
    first = model or SoftmaxProxy(lr=cfg.learning_rate)
    rows = cut(rows.select("sample_id", "vec", "label"))
    n = rows.count()
    pool_n, b = cfg.sizes(n)
    steps = cfg.steps(b)
    total = cfg.intervals * steps
    rate = lambda step: lr_at(step, total, first.lr) if cfg.schedule == "ramp" else first.lr
    warm = first.fit_steps(rows, max(1, round(cfg.warm_frac * total)))
    clock.close("warm_up")
    nodes = cut(warm.extract(rows).select("sample_id", "vec", "score", F.lit(0).cast("long").alias("last_step")))
    knn, edges, how = _searched(nodes, cfg)
    clock.close("extraction")
    at = warm if cfg.start == "warm" else first
    history, step, log, picks = History(), 0, [], None
    for turn in range(cfg.intervals):
        if picks is None or cfg.update_policy != "frozen_subset":
            picks = cut(_selected(nodes, edges, pool_n, b, turn, cfg))
        subset = cut(rows.join(picks.select("sample_id"), "sample_id", "left_semi"))
        clock.close("selection")
        for _ in range(steps):
            batch = _batch(subset, cfg, b, step)
            history.add(at.extract(batch).select("sample_id", F.lit(step).cast("long").alias("step"), "score"))
            at, step = at.fit_steps(batch, 1, lr=rate(step)), step + 1
        trained = picks.select("sample_id", F.lit(step).cast("long").alias("_t"))
        nodes = cut(nodes.join(trained, "sample_id", "left").withColumn("last_step", F.coalesce("_t", "last_step")).drop("_t"))
        clock.close("training")
        if cfg.update_policy == "full":
            old = edges
            nodes = cut(at.extract(rows).select("sample_id", "vec", "score", F.lit(step).cast("long").alias("last_step")))
            knn, edges, how = _searched(nodes, cfg)
            note = {"checked": 0, "drift": 0.0, "fired": True, "anchors": n, "propagated": 0, "shift": 0.0, "repaired": True, "edges_changed": _difference(old, edges)}
        else:
            past = history.frame()
            of = past.select("sample_id").distinct() if cfg.probe_from == "trained" else picks.select("sample_id")
            nodes, edges, knn, note = check_and_update(nodes, edges, knn, rows, at, of, past, step, cfg, how)
        log.append({"interval": turn, "picks": picks.count()} | note)
        clock.close("update")
    return RunResult(at, picks, nodes, edges, history.frame().select("sample_id").distinct(), log, clock.seconds)
