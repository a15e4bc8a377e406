"""Worked examples, equivalences and bounds of the selector's methods."""

import itertools
import math

import numpy as np
import pytest

from coreset_spark.config import SelectorConfig
from coreset_spark.functions.rouge import lcs, rouge_l_value
from coreset_spark.operators import graph, metrics, scores, select, update
from coreset_spark.operators.proxy import SoftmaxProxy, lr_at

RNG = np.random.default_rng(1)


def vectors(spark, n=40, d=6):
    x = RNG.normal(size=(n, d))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    return spark.createDataFrame([(i, x[i].tolist(), int(i % 3), float(RNG.random())) for i in range(n)], "sample_id long, vec array<double>, label int, warped double")


def test_square_has_a_ring(spark):
    rows = spark.createDataFrame([(i, v) for i, v in enumerate([[1.0, 0.0], [0.0, 1.0], [-1.0, 0.0], [0.0, -1.0]])], "sample_id long, vec array<double>")
    e = graph.build_graph(rows, 2).collect()
    assert len(e) == 8 and all(abs(x["w"] - math.exp(-0.02)) < 1e-12 for x in e)


def test_asymmetric_triple(spark):
    rows = spark.createDataFrame([(0, [0.0]), (1, [1.0]), (2, [3.0])], "sample_id long, vec array<double>")
    assert {(x["src"], x["dst"]) for x in graph.build_graph(rows, 1).collect()} == {(0, 1), (1, 0)}


def test_engines_agree_and_reach_the_bound():
    x = RNG.normal(size=(12, 4))
    sim, w, ids = select.block(x, x, "shift"), RNG.random(12), np.arange(12)
    for lam in (0.0, 0.5, 1.0):
        a = select.greedy(sim, w, ids, 4, lam)
        b, evaluated = select.lazy(sim, w, ids, 4, lam)
        assert a == b and evaluated <= 48
        value = lambda s: lam * sim[:, list(s)].max(1).sum() + (1 - lam) * w[list(s)].sum()  # noqa: B023, E731
        best = max(map(value, itertools.combinations(range(12), 4)))
        assert value([i for i, _ in a]) >= (1 - 1 / math.e) * best - 1e-9
        gains = [g for _, g in a]
        assert gains == sorted(gains, reverse=True)


def test_twins_and_loner():
    x = np.array([[1.0, 0.0], [1.0, 0.0], [0.0, 1.0]])
    for mode in ("shift", "clip"):
        picks = select.greedy(select.block(x, x, mode), np.zeros(3), np.arange(3), 3, 1.0)
        assert [i for i, _ in picks] == [0, 2, 1] and picks[2][1] == 0


def test_shift_makes_the_picks_of_the_printed_form():
    x = RNG.normal(size=(20, 5))
    a = select.greedy(select.block(x, x, "raw"), np.zeros(20), np.arange(20), 6, 1.0)
    b = select.greedy(select.block(x, x, "shift"), np.zeros(20), np.arange(20), 6, 1.0)
    assert [i for i, _ in a] == [i for i, _ in b]


def test_distributed_and_dominance_match(spark):
    rows = vectors(spark)
    a = select.select_greedy(rows, None, 5, 0.5).collect()
    b = select.select_greedy(rows, None, 5, 0.5, "distributed").collect()
    assert [(x["sample_id"], round(x["gain"], 6)) for x in a] == [(x["sample_id"], round(x["gain"], 6)) for x in b]
    e = graph.build_graph(rows.select("sample_id", "vec"), 4)
    c = select.select_greedy(rows, None, 5, 0.5, "graph", edges=e).collect()
    d = select.select_greedy(rows, None, 5, 0.5, "dominance", edges=e).collect()
    assert [x["sample_id"] for x in c] == [x["sample_id"] for x in d]


@pytest.mark.parametrize(("engine", "mode", "balance"), [(e, m, b) for e in ("exact", "lazy", "stochastic") for m, b in (("raw", "sum"), ("shift", "mean"), ("clip", "sum"))])
def test_large_inputs_keep_their_engine(spark, monkeypatch, engine, mode, balance):
    """Beyond one task's cells, picks and gains are those of the engine, mode and balance asked for."""
    rows = vectors(spark)
    run = lambda: [(x["sample_id"], round(x["gain"], 6)) for x in select.select_greedy(rows, None, 6, 0.7, engine, mode, seed=7, balance=balance).collect()]
    one = run()
    monkeypatch.setattr(select, "ONE_TASK_CELLS", 0)
    monkeypatch.setattr(select, "AT_ONCE", 4)
    monkeypatch.setattr(select, "IN_VIEW", 7)
    assert run() == one
    with pytest.raises(ValueError):
        select.select_greedy(rows, None, 6, 0.7, "lazy", balance="none")


def test_budget_edges(spark):
    rows = vectors(spark, 5)
    assert select.select_greedy(rows, None, 9, 0.5).count() == 5 and select.select_greedy(rows, None, 0, 0.5).count() == 0


def test_beta_shape(spark):
    rows = spark.createDataFrame([(i, i / 100) for i in range(101)], "sample_id long, z double")
    p = spark.createDataFrame([(2.5, 7.5)], "beta_a double, beta_b double")
    out = {x["sample_id"]: x["warped"] for x in scores.warp(rows, p).collect()}
    assert out[0] == out[100] == 0 and max(out, key=out.get) in (18, 19)
    flat = {x["warped"] for x in scores.warp(rows, p, 0).collect()}
    assert flat == {1.0}
    with pytest.raises(ValueError):
        SelectorConfig(C=2)


def test_constant_scores_rescale_to_half(spark):
    rows = spark.createDataFrame([(1, 3.0), (2, 3.0)], "sample_id long, score double")
    assert {x["z"] for x in scores.rescale(rows).collect()} == {0.5}


def test_two_readings(spark):
    h = spark.createDataFrame([(1, 0, 1.0), (1, 1, 2.0), (2, 0, 5.0), (2, 1, 5.0)], "sample_id long, step long, score double")
    recent = {x["sample_id"]: x["drift"] for x in update.score_drift(h).collect()}
    printed = {x["sample_id"]: x["drift"] for x in update.score_drift(h, decay="as_printed").collect()}
    assert abs(recent[1] - 0.248744) < 1e-6 and abs(printed[1] - 0.251256) < 1e-6 and recent[2] == 0


def test_chain_of_anchors(spark):
    ranked = spark.createDataFrame([(i, float(6 - i)) for i in range(1, 6)], "sample_id long, priority double")
    links = [(i, i + 1) for i in range(1, 5)]
    e = spark.createDataFrame(links + [(b, a) for a, b in links], "src long, dst long")
    assert [x["sample_id"] for x in update.choose_anchors(ranked, e, 9).collect()] == [1, 3, 5]
    assert [x["sample_id"] for x in update.choose_anchors(ranked, e, 2).collect()] == [1, 3]
    n = {i: {i - 1, i + 1} for i in range(1, 6)}
    assert update.choose_anchors_sequential([(i, 6.0 - i) for i in range(1, 6)], n, 9) == [1, 3, 5]


@pytest.mark.parametrize(("w", "blend", "expected"), [(0.5, "half", 0.5), (0.5, "energy", 0.5), (1.0, "half", 0.5), (1.0, "energy", 0.6)])
def test_blends(spark, w, blend, expected):
    nodes = spark.createDataFrame([(1, [0.0], 0.2, 0), (2, [0.0], 0.2, 0), (3, [0.0], 0.2, 0)], "sample_id long, vec array<double>, score double, last_step long")
    e = spark.createDataFrame([(1, 2, 0.0, w), (1, 3, 0.0, w)], "src long, dst long, d2 double, w double")
    a = spark.createDataFrame([(2, 0.6), (3, 1.0)], "sample_id long, score_new double")
    out = {x["sample_id"]: x["score_new"] for x in update.propagate_scores(nodes, e, a, blend=blend, affinity_min=0.0).collect()}
    assert abs(out[1] - expected) < 1e-12 and out[2] == 0.6


def test_gradient_is_the_derivative():
    m = SoftmaxProxy(3, 4, hidden=5)
    m.weights["out"] = RNG.normal(size=(3, 5))
    x, y = RNG.normal(size=(7, 4)), RNG.integers(0, 3, 7)
    g = m.gradients(x, y)
    loss = lambda: -np.log(m.forward(x)[np.arange(7), y]).sum()
    for name in g:
        w = m.weights[name]
        for i, j in [(0, 0), (2, 3)]:
            old, eps = w[i, j], 1e-6
            w[i, j] = old + eps
            up = loss()
            w[i, j] = old - eps
            down = loss()
            w[i, j] = old
            assert abs((up - down) / (2 * eps) - g[name][i, j]) < 1e-4


def test_rouge():
    assert rouge_l_value("a b c d", "a c d e") == (0.75, 0.75, 0.75)
    for _ in range(30):
        a, b = RNG.integers(0, 3, 8).tolist(), RNG.integers(0, 3, 6).tolist()
        t = np.zeros((9, 7), int)
        for i in range(8):
            for j in range(6):
                t[i + 1, j + 1] = t[i, j] + 1 if a[i] == b[j] else max(t[i, j + 1], t[i + 1, j])
        assert lcs(a, b) == t[8, 6]


def test_costs_and_schedule():
    assert metrics.cost_greedy(10, 2, 3) == 10 * 14 and metrics.cost_rebuild(3, 2) == 18
    assert metrics.cost_update_printed(2, 3, 4, 10, 1, 1, 1) != metrics.cost_update_sum(2, 3, 4, 10, 1, 1, 1)
    assert lr_at(0, 100, 1.0) < lr_at(2, 100, 1.0) and lr_at(99, 100, 1.0) < 0.1


def test_maximum_coverage_instance():
    sets = [{0, 1, 2}, {2, 3}, {3, 4, 5}, {0, 5}, {6}, {6, 7}]
    sim = np.array([[1.0 if u in s else 0.0 for s in sets] for u in range(8)])
    picks = [i for i, _ in select.greedy(sim, np.zeros(6), np.arange(6), 3, 1.0)]
    assert len(set().union(*(sets[i] for i in picks))) == 8


def test_empty_frames(spark):
    none = spark.createDataFrame([], "sample_id long, vec array<double>, label int, warped double")
    assert graph.knn_exact(none, 3).count() == 0 and select.select_greedy(none, None, 3, 0.5).count() == 0
