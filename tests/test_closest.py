"""The exact search in blocks of many rows: what it finds, what it measures, and how often a row is shuffled."""

import numpy as np
import pytest

from coreset_spark.operators import graph

RNG = np.random.default_rng(8)


def brute(x, y, src, dst, k, metric):
    d = graph._apart(x, y, metric)
    d[src[:, None] == dst[None, :]] = np.inf
    i, j = np.nonzero(graph.nearest(d, k))
    return d, set(zip(i.tolist(), j.tolist(), strict=True))


@pytest.mark.parametrize("metric", ["l2", "cosine"])
@pytest.mark.parametrize("kind", ["spread", "copies", "one", "near", "far", "tiny", "zero"])
def test_closest_is_brute_force(monkeypatch, metric, kind):
    monkeypatch.setattr(graph, "TALL", 64)
    monkeypatch.setattr(graph, "ACROSS", 128)
    monkeypatch.setattr(graph, "ALONE", 12)
    n, m = 150, 700
    x, y = RNG.normal(size=(n, 6)), RNG.normal(size=(m, 6))
    if kind == "copies":
        y[300:] = y[RNG.integers(0, 25, 400)]
        x[:60] = y[RNG.integers(0, 25, 60)]
    if kind == "one":
        x[:], y[:] = y[0], y[0]
    if kind == "near":
        y = y[RNG.integers(0, 3, m)] + 1e-5 * y
        x = y[:n] + 1e-7
    if kind in ("far", "tiny"):
        x, y = (v * (1e25 if kind == "far" else 1e-25) for v in (x, y))
        y[5] *= 1e-3
    if kind == "zero":
        x[:], y[:] = 0, 0
    src, dst = np.arange(n) + 3, np.arange(m)
    for k in (1, 10):
        d, want = brute(x, y, src, dst, k, metric)
        i, j, v = graph.closest(x, y, src, dst, k, metric)
        got = set(zip(i.tolist(), j.tolist(), strict=True))
        assert len(got) == len(i) == n * k
        tol = 1e-11 * max(1.0, np.abs(d[np.isfinite(d)]).max())
        assert np.allclose(v, d[i, j], rtol=1e-9, atol=tol)
        if kind != "far":  # where 12 decimals are more than a number has, brute force rounds at random
            assert got == want


def test_few_distances_are_measured(monkeypatch):
    x, measured = RNG.normal(size=(6000, 16)), []
    dots = np.einsum
    monkeypatch.setattr(graph, "nearest", lambda d, k, f=graph.nearest: measured.append(d.size) or f(d, k))
    monkeypatch.setattr(np, "einsum", lambda how, a, b: measured.append(len(a)) or dots(how, a, b))
    graph.closest(x, x, np.arange(6000), np.arange(6000), 10, "l2")
    assert sum(measured) < 0.12 * len(x) ** 2


def test_a_row_is_shuffled_once_a_block_and_blocks_grow(spark, monkeypatch):
    x = RNG.normal(size=(400, 4))
    rows = spark.createDataFrame([(3 * i - 90, v.tolist()) for i, v in enumerate(x)], "sample_id long, vec array<double>")
    want = {(3 * i - 90, 3 * j - 90) for i, j in brute(x, x, np.arange(400), np.arange(400), 5, "l2")[1]}
    sent = spark.sparkContext.accumulator(0)
    near = graph._near

    def counted(k, metric, radius=False):
        run = near(k, metric, radius)
        return lambda a, b: sent.add(a.num_rows) or run(a, b)

    monkeypatch.setattr(graph, "_near", counted)
    got = {(r["src"], r["dst"]) for r in graph.knn_exact(rows, 5, block=10).collect()}
    assert got == want and sent.value == 400 * graph.BLOCKS  # each row asks once a block: forty blocks of ten before


def test_edges_search_once(spark, monkeypatch):
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(RNG.normal(size=(60, 4)))], "sample_id long, vec array<double>")
    runs, near = spark.sparkContext.accumulator(0), graph._near
    monkeypatch.setattr(graph, "_near", lambda *a: lambda x, y, run=near(*a): runs.add(1) or run(x, y))
    assert graph.build_graph(rows, 5).count() and runs.value == 1
