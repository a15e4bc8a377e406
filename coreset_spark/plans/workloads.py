"""The experiments on the given tables: language of documents, answers of conversations, ablations, time, noise, scale, streams."""

from __future__ import annotations

import hashlib
import time
from collections.abc import Callable, Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SelectorConfig
from ..functions.rouge import scored
from ..operators import baselines, graph, metrics, ngram, scores, select
from ..operators.proxy import SoftmaxProxy
from ..operators.ranks import tiles
from ..operators.storage import cut, new_folder
from ..sources import tables
from ..streaming import readings
from . import schedule
from .loop import check_and_update, run_adaptive
from .schedule import beside as _beside

LANGS = ["de", "en", "es", "fr"]


def _signs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Mean over a text's tokens of +1 or -1 by the 64 leading bits of each token's md5; a token's bits are found once per task."""
    known: dict[str, int] = {}
    bits = np.zeros((1 << 12, 64), np.int8)

    def learn(tokens: list[str]) -> None:
        nonlocal bits
        while len(bits) < len(known) + len(tokens):
            bits = np.concatenate([bits, np.zeros_like(bits)])
        leading = np.frombuffer(b"".join(hashlib.md5(w.encode()).digest()[:8] for w in tokens), np.uint8).reshape(-1, 8)
        bits[len(known) : len(known) + len(tokens)] = np.unpackbits(leading, axis=1).astype(np.int8) * 2 - 1
        known.update(zip(tokens, range(len(known), len(known) + len(tokens)), strict=True))

    for batch in batches:
        ids, labels, vecs = [], [], []
        for i, label, text in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
            tokens = [w for w in (text or "").lower().split(" ") if w]
            if not tokens:
                continue
            if len(known) > 200_000:
                known.clear()
            if new := [*set(tokens).difference(known)]:
                learn(new)
            total = bits[[*map(known.__getitem__, tokens)]].sum(0, dtype=np.int64)
            ids.append(i), labels.append(label), vecs.append(total / len(tokens))
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(labels, pa.int32()), pa.array(vecs, pa.list_(pa.float64()))], names=["sample_id", "vec_label", "vec"])


def doc_vectors(docs: DataFrame) -> DataFrame:
    """(sample_id, vec, label): mean of the tokens' sign vectors; the class is the language. Texts without tokens have none."""
    label = F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")).cast("int") - 1
    out = docs.select("doc_id", label.alias("label"), "text").mapInArrow(_signs, "sample_id long, vec_label int, vec array<double>")
    return out.select("sample_id", "vec", F.col("vec_label").alias("label"))


def w1_split(spark, d):
    return tables.domains(spark, d).groupBy("domain").agg(F.count("*").alias("n"))


def _w1(spark, d):
    docs = tables.domains(spark, d)
    return cut(doc_vectors(docs).join(docs.select(F.col("doc_id").alias("sample_id"), "domain"), "sample_id"))


def _accuracy(model, rows: DataFrame, name: str) -> DataFrame:
    test = rows.filter("domain <> 'train'").select("sample_id", "vec", "label", "domain")
    told = model.extract(test).join(test.select("sample_id", F.substring("domain", 1, 2).alias("side")), "sample_id")
    return cut(told.groupBy("side").agg(F.round(F.avg((F.col("predicted") == F.col("label")).cast("double")), 6).alias("accuracy"), F.count("*").alias("n")).select(F.lit(name).alias("selector"), "side", "accuracy", "n"))


PROXY = SoftmaxProxy(classes=len(LANGS), lr=20.0)
W1 = SelectorConfig(learning_rate=20.0, engine="lazy", pool_frac=1.0, delta=0.05)
EPOCHS = 3


def _training(rows: DataFrame) -> DataFrame:
    return cut(rows.filter("domain = 'train'").select("sample_id", "vec", "label"))


def _texts(spark, d, train: DataFrame) -> DataFrame:
    return tables.table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), F.col("text").alias("completion")).join(train.select("sample_id"), "sample_id", "left_semi")


def _w1_runs(spark: SparkSession, d: str, train_rows: DataFrame, shared: bool) -> list[tuple[str, Callable[[], tuple[object, dict[str, float]]]]]:
    """Every selector with its schedule, then one static choice by the objective and the adaptive run: name, and what trains a model and tells its seconds. shared: equal rankings are made once."""
    b = max(4, round(0.1 * train_rows.count()))
    began = time.time()
    warm = PROXY.fit_steps(train_rows, 1)
    warmed = time.time() - began
    of = schedule.selectors(train_rows, _texts(spark, d, train_rows), b, PROXY, warm, rankings=schedule.Rankings(b) if shared else None)
    of.append(schedule.Schedule("objective_once", lambda m, e: schedule.objective_picks(train_rows, m.extract(train_rows), b, W1)))

    def scheduled(s: schedule.Schedule) -> tuple[object, dict[str, float]]:
        model, _, seconds = schedule.train(s, train_rows, PROXY, warm, EPOCHS)
        return model, {"warm_up": warmed} | seconds

    def adaptive() -> tuple[object, dict[str, float]]:
        run = run_adaptive(train_rows, W1, PROXY)
        return run.model, run.seconds

    return [*((s.name, lambda s=s: scheduled(s)) for s in of), ("adaptive", adaptive)]


def w1_accuracy(spark: SparkSession, d: str) -> DataFrame:
    """Held-out accuracy in and out of domain of the same number of steps under each selector, static, anew each epoch, or adaptive."""
    rows = _w1(spark, d)
    runs = _w1_runs(spark, d, _training(rows), True)
    told = _beside(spark, lambda run: _accuracy(run[1]()[0], rows, run[0]), runs[::-1])  # the longest first
    return reduce(DataFrame.unionByName, told[::-1])


def w4_time_by_method(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of every selector's stages on the same corpus, each by itself."""
    runs = _w1_runs(spark, d, _training(_w1(spark, d)), False)
    return spark.createDataFrame([(name, stage, float(s)) for name, run in runs for stage, s in run()[1].items()], "selector string, stage string, seconds double")


VARIANTS = {"full": {}, "no_representation": {"lam": 0.0}, "no_importance": {"lam": 1.0}, "no_update": {"update_policy": "never"}, "frozen_subset": {"update_policy": "frozen_subset"}, "always_update": {"update_policy": "always"}}


def w7_ablation_log(spark, d):
    """Interval logs of the full method and its ablations."""
    rows = tables.vectors(spark, d)
    cfg = SelectorConfig(intervals=2)
    logs = _beside(spark, lambda change: run_adaptive(rows, replace(cfg, **change)).frame(spark), VARIANTS.values())
    return reduce(DataFrame.unionByName, [log.select(F.lit(name).alias("variant"), "*") for name, log in zip(VARIANTS, logs, strict=True)])


def _adaptive_accuracies(spark, d, runs: list[tuple[str, SelectorConfig]], what: str) -> DataFrame:
    """Accuracy in and out of domain, checks that fired and anchors of adaptive runs with different settings."""
    rows = _w1(spark, d)
    train_rows = _training(rows)

    def told(named: tuple[str, SelectorConfig]) -> DataFrame:
        name, cfg = named
        run = run_adaptive(train_rows, cfg, PROXY)
        fired, anchors = (sum(int(x[k]) for x in run.log) for k in ("fired", "anchors"))
        return _accuracy(run.model, rows, name).withColumnRenamed("selector", what).withColumns({"fired": F.lit(fired), "anchors": F.lit(anchors)})

    return reduce(DataFrame.unionByName, _beside(spark, told, runs))


def w7_ablation_accuracy(spark, d):
    """What the full method and its ablations reach."""
    return _adaptive_accuracies(spark, d, [(name, replace(W1, **change)) for name, change in VARIANTS.items()], "variant")


def w5_budget_accuracy(spark, d):
    return _adaptive_accuracies(spark, d, [(f"{share:.2f}", replace(W1, budget_frac=share)) for share in (0.02, 0.05, 0.10, 0.20, 0.30)], "budget")


def w6_lambda_accuracy(spark, d):
    return _adaptive_accuracies(spark, d, [(f"{lam:.1f}", replace(W1, lam=lam)) for lam in (0.0, 0.2, 0.4, 0.6, 0.8, 1.0)], "lam")


def w8_delta_accuracy(spark, d):
    """Low thresholds behave like updating always, high ones like never."""
    return _adaptive_accuracies(spark, d, [(f"{0.05 * i:.2f}", replace(W1, delta=round(0.05 * i, 2))) for i in range(8)], "delta")


def w9_interval_accuracy(spark, d):
    """An interval as a share of an epoch, which is also the pool's share of the corpus; eight steps in all."""
    return _adaptive_accuracies(spark, d, [(f"{share:.3f}", replace(W1, pool_frac=share, intervals=round(1 / share), interval_steps=round(8 * share))) for share in (0.125, 0.25, 0.5, 1.0)], "share")


def adaptive_run_log(spark, d):
    """With a hidden layer, whose states move, so that an update also moves vectors and repairs the graph."""
    return run_adaptive(tables.vectors(spark, d), SelectorConfig(intervals=3, delta=0.01, learning_rate=5.0), SoftmaxProxy(hidden=32, lr=5.0)).frame(spark)


def full_refresh_log(spark, d):
    return run_adaptive(tables.vectors(spark, d), SelectorConfig(intervals=2, update_policy="full")).frame(spark)


def check_update_round(spark, d):
    """One check-and-update after two steps of a hidden-layer model, on the graph of its first state: what was checked, moved and repaired, and the checksum of the new scores."""
    rows = cut(tables.vectors(spark, d))
    cfg = SelectorConfig(delta=0.0, learning_rate=5.0)
    first = SoftmaxProxy(hidden=32, lr=5.0).fit_steps(rows, 1)
    nodes = cut(first.extract(rows).select("sample_id", "vec", "score", F.lit(0).cast("long").alias("last_step")))
    lists = cut(graph.knn_exact(nodes, cfg.k))
    edges = cut(graph.weight_edges(graph.mutual_edges(lists), cfg.bandwidth))
    subset = cut(tables.draw_pool(rows, cfg.sizes(rows.count())[1], cfg.seed, 0))
    picks = rows.join(subset.select("sample_id"), "sample_id", "left_semi")
    history, at = first.extract(picks).select("sample_id", F.lit(0).cast("long").alias("step"), "score"), first.fit_steps(picks, 2)
    nodes, edges, _, note = check_and_update(nodes, edges, lists, rows, at, subset.select("sample_id"), history, 2, cfg)
    told = {k: v for k, v in note.items() if k not in ("drift", "shift")}
    return nodes.agg(F.round(F.sum("score"), 6).alias("scores"), F.sum("last_step").alias("freshness")).select(*[F.lit(v).alias(k) for k, v in told.items()], F.lit(round(note["drift"], 5)).alias("drift"), F.lit(round(note["shift"], 5)).alias("shift"), "scores", "freshness", F.lit(edges.count()).alias("edges"))


def w4_time_by_stage(spark, d):
    began = time.time()
    run = run_adaptive(tables.vectors(spark, d), SelectorConfig(intervals=2))
    rows = [*run.seconds.items(), ("total", time.time() - began)]
    return spark.createDataFrame([(k, float(v)) for k, v in rows], "stage string, seconds double")


def w10_backbones(spark, d):
    """Three backbones, linear, tanh layer and token counts, each untrained, and trained on uniform, objective and adaptive picks: accuracy in and out of domain."""
    rows = _w1(spark, d)
    train_rows = _training(rows)
    b = max(4, round(0.1 * train_rows.count()))
    texts = tables.table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), "text").join(rows.select("sample_id"), "sample_id", "left_semi")
    runs = []
    for backbone, first in (("linear", PROXY), ("tanh", SoftmaxProxy(classes=len(LANGS), hidden=32, lr=5.0)), ("ngram", ngram.NgramBackbone(texts, len(LANGS)))):
        warm = first.fit_steps(tables.draw_pool(train_rows, b, 42, 9), 1)  # of a tenth of the rows
        chosen = [
            schedule.Schedule("base", lambda m, e: train_rows, steps=0.0), schedule.Schedule("uniform", lambda m, e: baselines.uniform(train_rows, b)),
            schedule.Schedule("objective_once", lambda m, e: schedule.objective_picks(train_rows, m.extract(train_rows), b, W1)),
        ]
        runs += [(backbone, s.name, lambda s=s, first=first, warm=warm: schedule.train(s, train_rows, first, warm, EPOCHS)[0]) for s in chosen]
        runs.append((backbone, "adaptive", lambda first=first: run_adaptive(train_rows, W1, first).model))
    told = _beside(spark, lambda run: _accuracy(run[2](), rows, run[1]).select(F.lit(run[0]).alias("backbone"), "*"), runs[::-1])  # the longest first
    return reduce(DataFrame.unionByName, told[::-1])


def w2_pairs(spark, d):
    return tables.pairs(spark, d).agg(F.count("*").alias("n"), F.count_distinct("conv_id").alias("dialogues"))


def w3_dialogues(spark, d):
    return tables.dialogues(spark, d).select("conv_id", F.md5("history").alias("history"), F.md5("reference").alias("reference"))


BUDGETS = (0.10, 0.20, 0.30)


def _token_rows(rows: DataFrame, column: str) -> DataFrame:
    """(sample_id, vec): mean of a text's token signs."""
    return doc_vectors(rows.select(F.col("sample_id").alias("doc_id"), F.lit("en").alias("lang"), F.col(column).alias("text"))).select("sample_id", "vec")


def _chosen(train_rows: DataFrame, completions: DataFrame, classes: int, budgets: tuple[float, ...] = BUDGETS) -> DataFrame:
    """(budget, selector, sample_id): what each selector would train on. The model predicts the cluster of a prompt's completion from the prompt."""
    n, runs = train_rows.count(), []
    first = SoftmaxProxy(classes=classes, lr=20.0)
    warm = first.fit_steps(train_rows, 1)
    sizes = [max(1, round(share * n)) for share in budgets]
    rankings = schedule.Rankings(max(sizes))

    def scheduled(s: schedule.Schedule) -> DataFrame:
        return schedule.train(s, train_rows, first, warm, EPOCHS)[1] if s.every_epoch else s.choose(warm, 0)

    for share, b in zip(budgets, sizes, strict=True):
        of = schedule.selectors(train_rows, completions, b, first, warm, rankings=rankings)
        runs += [(share, s.name, lambda s=s: scheduled(s)) for s in of if s.name != "base"]
        runs.append((share, "adaptive", lambda share=share: run_adaptive(train_rows, replace(W1, budget_frac=share), first).seen))
    told = _beside(train_rows.sparkSession, lambda run: cut(run[2]().select(F.lit(run[0]).alias("budget"), F.lit(run[1]).alias("selector"), "sample_id")), runs[::-1])  # the longest first
    return cut(reduce(DataFrame.unionByName, told))


def _answers(rows: DataFrame, classes: int = 8) -> DataFrame:
    """ROUGE-L of each test prompt's answer: the completion of the chosen prompt that shares most of its tokens; per selector and budget. rows: (sample_id, prompt, completion, split)."""
    train, test = cut(rows.filter("split = 'train'")), cut(rows.filter("split = 'test'"))
    classes = max(1, min(classes, train.count()))
    label = baselines.kmeans(cut(_token_rows(train, "completion")), classes, 2).select("sample_id", F.col("cluster").alias("label"))
    train_rows = cut(_token_rows(train, "prompt").join(label, "sample_id").select("sample_id", "vec", "label"))
    chosen = _chosen(train_rows, train.select("sample_id", "completion"), classes)
    words = train.select("sample_id", F.explode(F.array_distinct(tables.tokens(F.col("prompt")))).alias("w"))
    asked = test.select(F.col("sample_id").alias("q"), F.explode(F.array_distinct(tables.tokens(F.col("prompt")))).alias("w"))
    near = cut(asked.join(words, "w").groupBy("q", "sample_id").agg(F.count("*").alias("n")))
    best = near.join(chosen, "sample_id").groupBy("budget", "selector", "q").agg(F.max_by("sample_id", F.struct("n", (-F.col("sample_id")).alias("m"))).alias("sample_id"))
    answers = best.join(train.select("sample_id", F.col("completion").alias("predicted")), "sample_id")
    every = chosen.select("budget", "selector").distinct().crossJoin(test.select(F.col("sample_id").alias("q"), F.col("completion").alias("reference")))  # selectors x test rows is the result's own size
    told = scored(every.join(answers, ["budget", "selector", "q"], "left"))
    return told.groupBy("budget", "selector").agg(F.round(F.avg("f1"), 6).alias("rouge_l"), F.count("*").alias("n"))


def w2_rouge(spark, d):
    return _answers(tables.pairs(spark, d).select((F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"), "prompt", "completion", "split"))


def w3_rouge(spark, d):
    return _answers(tables.dialogues(spark, d).select(F.col("conv_id").alias("sample_id"), F.col("history").alias("prompt"), F.col("reference").alias("completion"), "split"))


def ngram_token_probs(spark, d):
    docs = tables.table(spark, d, "documents").select("doc_id", "text")
    model = ngram.NgramProxy().fit(docs)
    return model.score(docs).select("doc_id", F.round("loss", 6).alias("loss"), "n_tokens")


def importance_tokens(spark, d):
    docs = tables.table(spark, d, "documents").select("doc_id", "text")
    return ngram.NgramProxy().fit(docs).importance(docs).select("doc_id", F.round("score", 5).alias("score"))


def importance_tokens_mean(spark, d):
    docs = tables.table(spark, d, "documents").select("doc_id", "text")
    return ngram.NgramProxy().fit(docs).importance(docs, norm="mean").select("doc_id", F.round("score", 6).alias("score"))


def doc_mean_vectors(spark, d):
    docs = tables.table(spark, d, "documents").select("doc_id", "text", "lang")
    return doc_vectors(docs).select("sample_id", F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), F.round(F.col("vec")[0], 6).alias("x0"), F.round(F.col("vec")[63], 6).alias("x63"))


def w11_noise_by_band(spark, d):
    """Share of labelled noise among the rows of most, of middling and of least importance under the n-gram model."""
    docs = tables.table(spark, d, "documents").select("doc_id", "text")
    s = ngram.NgramProxy().fit(docs).importance(docs, norm="mean").withColumn("s6", F.round("score", 6)).join(tables.table(spark, d, "labels"), "doc_id")
    s = tiles(s, 3, "s6", "doc_id", name="band")
    return s.groupBy("band").agg(F.count("*").alias("n"), F.round(F.avg((F.col("quality") == 0).cast("double")), 6).alias("noise"))


def w12_lineitem_importance(spark, d):
    """One step over four standardised columns; importance by class."""
    rows = tables.line_vectors(spark, d)
    e = SoftmaxProxy(classes=3, dims=4, lr=1.0).fit_steps(rows, 1).extract(rows)
    return e.groupBy("label").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("score"), F.round(F.avg("loss"), 6).alias("loss"))


def w12_partitioned_greedy(spark, d):
    """A pool of 2,000 rows, a universe of 5,000 drawn ones and a hundred picks, whatever the corpus: partitioned picks beside the exact ones on the same, and their objectives."""
    rows = cut(tables.line_vectors(spark, d).dropDuplicates(["sample_id"]))
    cfg = SelectorConfig(pool_size=2000, universe="sample", universe_sample=5000, budget_frac=0.05)
    e = cut(SoftmaxProxy(classes=3, dims=4, lr=1.0).fit_steps(rows, 1).extract(rows).select("sample_id", "vec", "score"))
    weighed = scores.weighted(e, cfg)
    pool, universe = cut(tables.draw_pool(weighed, cfg.pool_size, cfg.seed, 0)), cut(tables.draw_pool(weighed, cfg.universe_sample, cfg.seed + 1, 0))
    out = []
    for engine in ("partitioned", "lazy"):
        picks = select.select_greedy(pool, universe, cfg.sizes(cfg.pool_size)[1], 0.5, engine)
        chosen = cut(pool.join(picks.select("sample_id"), "sample_id", "left_semi"))
        out.append(select.objective(universe, chosen, 0.5, mode="shift").select(F.lit(engine).alias("engine"), "picks", F.round("objective", 5).alias("objective")))
    return reduce(DataFrame.unionByName, out)


def exact_match_by_domain(spark, d):
    """Nearest class mean, in and out of domain, with subtotals."""
    rows = _w1(spark, d)
    m = rows.filter("domain = 'train'").select("label", F.posexplode("vec").alias("j", "x")).groupBy("label", "j").agg(F.avg("x").alias("m"))
    test = rows.filter("domain <> 'train'").select("sample_id", "domain", F.col("label").alias("reference"), F.posexplode("vec").alias("j", "x"))
    dist = test.join(F.broadcast(m), "j").groupBy("sample_id", "domain", "reference", "label").agg(F.round(F.sum((F.col("x") - F.col("m")) ** 2), 9).alias("d2"))  # classes x dims rows
    best = dist.groupBy("sample_id", "domain", "reference").agg(F.min_by("label", F.struct("d2", "label")).alias("predicted")).withColumn("side", F.substring("domain", 1, 2))
    return metrics.exact_match(best, "side", "domain").select("side", "domain", F.round("accuracy", 6).alias("accuracy"), "n")


def stream_history_counts(spark, d):
    """Readings as a stream of files, counted by day; equals the batch query."""
    return readings.daily_counts(spark, f"{d}/events.parquet", new_folder(spark, "counts"))


QUERIES = [
    w1_split, w1_accuracy, w4_time_by_method, w5_budget_accuracy, w6_lambda_accuracy, w8_delta_accuracy, w9_interval_accuracy, w7_ablation_log, w7_ablation_accuracy, adaptive_run_log,
    full_refresh_log, check_update_round, w12_partitioned_greedy, w4_time_by_stage, w10_backbones, w2_pairs, w3_dialogues, w2_rouge, w3_rouge,
    ngram_token_probs, importance_tokens, importance_tokens_mean, doc_mean_vectors, w11_noise_by_band, w12_lineitem_importance, exact_match_by_domain, stream_history_counts,
]
