"""The training loop and its check-and-update against a plain program on a few rows, and each of its options."""

import hashlib
import math

import numpy as np
import pytest

from coreset_spark.config import SelectorConfig
from coreset_spark.operators import graph, update
from coreset_spark.operators.proxy import SoftmaxProxy, lr_at
from coreset_spark.plans import loop, schedule

N, D, K = 60, 5, 3


@pytest.fixture(scope="module")
def data():
    r = np.random.default_rng(11)
    x = r.normal(size=(N, D))
    return x / np.linalg.norm(x, axis=1, keepdims=True), r.integers(0, K, N)


@pytest.fixture(scope="module")
def rows(spark, data):
    x, y = data
    return spark.createDataFrame([(i, x[i].tolist(), int(y[i])) for i in range(N)], "sample_id long, vec array<double>, label int")


def draw(ids, n, seed, turn):
    return sorted(ids, key=lambda i: hashlib.md5(f"{seed}:{turn}:{i}".encode()).hexdigest())[:n]


def near(v, k):
    d = ((v[:, None] - v[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    lists = [sorted(range(N), key=lambda j: (round(d[i, j], 12), j))[:k] for i in range(N)]  # noqa: B023
    return {(i, j): math.exp(-d[i, j] / 100) for i in range(N) for j in lists[i] if i in lists[j]}


class Plain:
    """The loop in numpy, one row after the other, without any of the engine's code but the derivative of the proxy."""

    def __init__(self, data, cfg, model):
        self.x, self.y, self.cfg, self.model, self.log = *data, cfg, model.copy(), []

    def told(self, m, ids):
        p = m.forward(self.x[ids])
        p[np.arange(len(ids)), self.y[ids]] -= 1
        return m.states(self.x[ids]), np.sqrt((p**2).sum(1))

    def step(self, m, ids, lr):
        g = m.gradients(self.x[ids], self.y[ids])
        for name, v in m.weights.items():
            v -= lr * g[name] / len(ids)

    def weights(self, s, c):
        z = (s - s.min()) / (s.max() - s.min())
        a = 1 + c.C * z.mean() ** c.q * c.budget_frac**c.r
        ln = math.lgamma(a) + math.lgamma(c.C - a) - math.lgamma(c.C)
        inside = (z > 0) & (z < 1)
        out = np.zeros(N)
        out[inside] = np.exp(((a - 1) * np.log(z[inside]) + (c.C - a - 1) * np.log(1 - z[inside]) - ln) * c.temperature)
        return out

    def picks(self, v, w, pool, b, lam):
        u = v / np.linalg.norm(v, axis=1, keepdims=True)
        sim, best, out = 1 + u @ u.T, np.zeros(N), []
        for _ in range(b):
            gain = {i: round(lam * np.maximum(sim[:, i] - best, 0).sum() + (1 - lam) * w[i], 9) for i in pool if i not in out}
            out.append(min(gain, key=lambda i: (-gain[i], i)))  # noqa: B023
            best = np.maximum(best, sim[:, out[-1]])
        return out

    def run(self):
        c, everyone = self.cfg, np.arange(N)
        pool_n, b = c.sizes(N)
        warm = self.model.copy()
        total = c.intervals * c.steps(b)
        for _ in range(max(1, round(c.warm_frac * total))):
            self.step(warm, everyone, warm.lr)
        v, s = self.told(warm, everyone)
        e = near(v, c.k)
        last, history, t = np.zeros(N, int), {}, 0
        for turn in range(c.intervals):
            chosen = self.picks(v, self.weights(s, c), draw(everyone, pool_n, c.seed, turn), b, c.lam)
            for _ in range(c.steps(b)):
                for i, x in zip(chosen, self.told(self.model, chosen)[1], strict=True):
                    history.setdefault(i, []).append((t, x))
                self.step(self.model, chosen, lr_at(t, total, self.model.lr) if c.schedule == "ramp" else self.model.lr)
                t += 1
            last[chosen] = t
            probe = draw(chosen, c.probe_size, c.seed, t)
            drifts = []
            for i, now in zip(probe, self.told(self.model, probe)[1], strict=True):
                weigh = [(c.decay_rate ** (t - at), x) for at, x in [*history[i], (t, now)]]
                drifts.append(sum(q * abs(x - now) for q, x in weigh) / sum(q * now for q, _ in weigh))
            note = {"drift": float(np.mean(drifts)), "fired": np.mean(drifts) > c.delta, "anchors": 0, "repaired": False}
            if note["fired"]:
                mean = {i: sum(w * s[j] for (a, j), w in e.items() if a == i) / sum(w for (a, j), w in e.items() if a == i) for i in {a for a, _ in e}}
                pri = [((t - last[i]) * abs(s[i] - mean.get(i, s[i])) if t - last[i] >= c.min_staleness else 0, i) for i in range(N)]
                anchors = []
                for p, i in sorted(((-round(p, 9), i) for p, i in pri)):
                    if p < 0 and len(anchors) < c.recompute_budget and not any((i, a) in e for a in anchors):
                        anchors.append(i)
                nv, ns = self.told(self.model, anchors)
                new, vec = dict(zip(anchors, ns, strict=True)), dict(zip(anchors, nv, strict=True))
                shift = np.mean([np.linalg.norm(vec[i] - v[i]) for i in anchors])
                s2, v2 = s.copy(), v.copy()
                for i in range(N):
                    good = [(j, w) for (a, j), w in e.items() if a == i and j in new and w * math.exp(-c.affinity_scale * abs(s[i] - s[j])) > c.affinity_min]
                    if i in new:
                        s2[i], v2[i] = new[i], vec[i]
                    elif good:
                        mass = sum(w for _, w in good)
                        s2[i] = 0.5 * s[i] + 0.5 * sum(w * new[j] for j, w in good) / mass
                        v2[i] = 0.5 * v[i] + 0.5 * sum(w * vec[j] for j, w in good) / mass
                s, last[anchors] = s2, t
                if shift > c.delta_h:
                    v, e = v2, near(v2, c.k)
                    note["repaired"] = True
                note["anchors"] = len(anchors)
            self.log.append(note)
        self.nodes = s
        self.edges = e
        return self


CASES = {
    "linear": (SoftmaxProxy(K, D, lr=5.0), {}),
    "tanh": (SoftmaxProxy(K, D, hidden=6, lr=2.0), {"delta": 0.0}),
    "never fires": (SoftmaxProxy(K, D, lr=5.0), {"delta": 9.0}),
    "ramp": (SoftmaxProxy(K, D, lr=5.0), {"schedule": "ramp", "interval_steps": 2, "intervals": 2}),
}


@pytest.mark.parametrize("case", CASES)
def test_loop_equals_the_plain_program(rows, data, case):
    model, options = CASES[case]
    cfg = SelectorConfig(**{"k": 4, "delta": 0.01, "delta_h": 0.001, "recompute_budget": 8, "probe_size": 2, "intervals": 3} | options)
    plain = Plain(data, cfg, model).run()
    run = loop.run_adaptive(rows, cfg, model)
    for name, w in run.model.weights.items():
        assert np.allclose(w, plain.model.weights[name], atol=1e-8)
    for a, b in zip(run.log, plain.log, strict=True):
        assert abs(a["drift"] - b["drift"]) < 1e-5 and (a["fired"], a["anchors"], a["repaired"]) == (b["fired"], b["anchors"], b["repaired"])
    assert np.allclose([x["score"] for x in run.nodes.orderBy("sample_id").collect()], plain.nodes, atol=1e-8)
    assert {(x["src"], x["dst"]) for x in run.edges.collect()} == set(plain.edges)
    assert any(x["repaired"] for x in run.log) == (case == "tanh") and any(x["fired"] for x in run.log) == (case != "never fires")
    assert set(run.seconds) == {"warm_up", "extraction", "selection", "training", "update"} and run.frame(rows.sparkSession).count() == cfg.intervals


def test_options_change_what_they_name(rows):
    model = SoftmaxProxy(K, D, lr=5.0)
    run = lambda **o: loop.run_adaptive(rows, SelectorConfig(**{"k": 4, "intervals": 2, "pool_frac": 0.5, "budget_frac": 0.2} | o), model)
    ids = lambda r: sorted(x["sample_id"] for x in r.picks.collect())
    picks = {name: ids(run(universe=name, universe_sample=10, lam=0.9)) for name in ("train", "pool", "graph", "sample")}
    assert all(len(p) == 6 for p in picks.values()) and len({tuple(p) for p in picks.values()}) > 2
    frozen = run(update_policy="frozen_subset")
    assert ids(frozen) == ids(run(update_policy="frozen_subset", intervals=1)) and not any(x["fired"] for x in frozen.log)
    assert all(x["fired"] for x in run(update_policy="always").log) and not any(x["fired"] for x in run(update_policy="never").log)
    full = run(update_policy="full")
    assert [x["anchors"] for x in full.log] == [N, N]
    batched = run(batch=2)
    assert SelectorConfig(batch=2).steps(6) == 3 and not np.allclose(batched.model.weights["out"], run().model.weights["out"])
    assert run(search="hashed").frame(rows.sparkSession).count() == 2
    with pytest.raises(ValueError):
        SelectorConfig(universe="nothing")


def test_history_is_only_added_to(spark):
    h = loop.History()
    for step in range(11):
        h.add(spark.createDataFrame([(i, step, float(step * i)) for i in range(3)], "sample_id long, step long, score double"))
    assert h.frame().count() == 33 and len(h.runs) <= 4
    assert update.score_drift(h.frame()).count() == 3


def test_schedules_train_what_they_choose(rows):
    first = SoftmaxProxy(K, D, lr=5.0)
    warm = first.fit_steps(rows, 1)
    lengths = rows.selectExpr("sample_id", "repeat('x ', cast(sample_id as int)) as completion")
    told = {s.name: schedule.train(s, rows, first, warm, epochs=2) for s in schedule.selectors(rows, lengths, 5, first, warm, clusters=3)}
    assert len(told) == 14
    assert (told["base"][0].weights["out"] == 0).all() and told["base"][1].count() == 0 and told["full"][1].count() == N
    assert sorted(x["sample_id"] for x in told["longest_completion"][1].collect()) == list(range(55, 60))
    for name, (_, seen, seconds) in told.items():
        if name not in ("base", "full"):
            assert 5 <= seen.count() <= 10 and set(seconds) == {"selection", "training"}
    assert told["uniform_epochs"][1].count() > 5


def test_repair_equals_a_new_build(spark, data):
    x, _ = data
    r = np.random.default_rng(3)
    old = spark.createDataFrame([(i, x[i].tolist()) for i in range(N)], "sample_id long, vec array<double>")
    moved = x.copy()
    moved[::7] += r.normal(size=moved[::7].shape) * 0.7
    new = spark.createDataFrame([(i, moved[i].tolist()) for i in range(N)], "sample_id long, vec array<double>")
    changed = spark.createDataFrame([(i,) for i in range(0, N, 7)], "sample_id long")
    lists, edges = graph.repair_graph(new, graph.knn_exact(old, 4), changed, 4)
    assert {(a["src"], a["dst"], a["rank"]) for a in lists.collect()} == {(a["src"], a["dst"], a["rank"]) for a in graph.knn_exact(new, 4).collect()}
    assert {(a["src"], a["dst"]) for a in edges.collect()} == {(a["src"], a["dst"]) for a in graph.build_graph(new, 4).collect()}
