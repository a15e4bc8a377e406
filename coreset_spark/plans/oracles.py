"""DuckDB SQL of the registered queries, written from the definitions: named steps, of which each oracle takes what it needs.

Sequential methods are chains of one step per round. Nothing here is derived from the engine's plans.
"""

from __future__ import annotations

import re

K, T = 10, 40  # classes; the step at which staleness is read

STEPS: dict[str, str] = {
    "n": "SELECT count(*) AS n FROM embeddings",
    "v": "SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v, label FROM embeddings",
    "e": "SELECT id, label, unnest(range(0, len(v))) AS j, unnest(v) AS x FROM v",
    "k": f"SELECT unnest(range({K})) AS k",
    "w0": "SELECT k, j, 0.0 AS w FROM k, (SELECT DISTINCT j FROM e)",
    "pool": "SELECT id FROM v ORDER BY md5('42:0:' || id), id LIMIT (SELECT CAST(round(0.4 * n) AS BIGINT) FROM n)",
    "bud": "SELECT CAST(round(0.1 * round(0.4 * n)) AS BIGINT) AS picks FROM n",
    "ten": "SELECT id FROM v ORDER BY md5('42:0:' || id), id LIMIT 10",
    "r": "SELECT id, s, CASE WHEN max(s) OVER () > min(s) OVER () THEN (s - min(s) OVER ()) / (max(s) OVER () - min(s) OVER ()) ELSE 0.5 END AS z FROM i1",
    "near": "SELECT a.id AS src, b.id AS dst, list_sum(list_transform(list_zip(a.v, b.v), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS d2 FROM v a JOIN v b ON a.id <> b.id",
    "edges": "SELECT a.src, a.dst, a.d2, exp(-a.d2 / 100) AS w FROM knn a JOIN knn b ON a.src = b.dst AND a.dst = b.src",
    "u": "SELECT user_id, count(*) AS n FROM events GROUP BY user_id",
    "nodes": "SELECT i1.id, i1.s, coalesce(u.n, 0) % 40 AS last FROM i1 LEFT JOIN u ON u.user_id = i1.id % (SELECT max(user_id) + 1 FROM u)",
    "uq": "SELECT n.id, n.s, n.last, coalesce(abs(n.s - m.m), 0) AS uq FROM nodes n LEFT JOIN (SELECT e.src, sum(e.w * o.s) / sum(e.w) AS m FROM edges e JOIN nodes o ON o.id = e.dst GROUP BY e.src) m ON m.src = n.id",
    "pri": f"SELECT id, CASE WHEN {T} - last >= 1 THEN ({T} - last) * uq ELSE 0 END AS p FROM uq",
    "new": "SELECT a.id, i2.s AS sn FROM anchors a JOIN i2 USING (id)",
    "moved": "SELECT a.id, a.v, list_transform(list_zip(a.v, b.v), lambda p: p[1] + 0.05 * p[2]) AS m FROM v a JOIN v b ON b.id = (a.id + 1) % (SELECT max(id) + 1 FROM v) WHERE a.id IN (SELECT id FROM anchors)",
    "vnew": "SELECT id, v, list_transform(m, lambda x: x / sqrt(list_dot_product(m, m))) AS vn FROM moved",
    "aff": "SELECT e.src, e.dst, e.w, e.w * exp(-0.1 * abs(a.s - b.s)) AS af FROM edges e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst",
    "h": "SELECT user_id AS id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS step, avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s, ts FROM events",
    "hn": "SELECT id, max(step) AS top, arg_max(s, step) AS now FROM h GROUP BY id",
    "g": "SELECT p1.id, p1.k, e.j, (p1.p - CASE WHEN p1.k = p1.label THEN 1 ELSE 0 END) * e.x AS g FROM p1 JOIN e USING (id)",
    "pairs": "SELECT * FROM (SELECT conv_id, turn, role, text AS prompt, lead(role) OVER w AS nr, lead(text) OVER w AS completion FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND nr = 'assistant'",
}


def _train(step: int, rows: str = "") -> None:
    """Steps w, z, p, i of a proxy after so many full-batch steps; i: importance s and loss."""
    if step:
        b = f"{step - 1}{rows}"
        STEPS[f"w{step}{rows}"] = f"SELECT w.k, e.j, any_value(w.w) - 200.0 * avg((p.p - CASE WHEN w.k = e.label THEN 1 ELSE 0 END) * e.x) AS w FROM e JOIN p{step - 1} p ON p.id = e.id JOIN w{step - 1} w ON w.k = p.k AND w.j = e.j" + (f" WHERE e.id IN (SELECT id FROM {rows})" if rows else "") + " GROUP BY w.k, e.j"
        del b
    if not rows:
        STEPS[f"z{step}"] = f"SELECT e.id, e.label, w.k, sum(e.x * w.w) AS z FROM e JOIN w{step} w ON w.j = e.j GROUP BY e.id, e.label, w.k"
        STEPS[f"y{step}"] = f"SELECT id, label, k, exp(z - max(z) OVER (PARTITION BY id)) AS y FROM z{step}"
        STEPS[f"p{step}"] = f"SELECT id, label, k, y / sum(y) OVER (PARTITION BY id) AS p FROM y{step}"
        STEPS[f"i{step}"] = f"SELECT id, label, sqrt(sum(power(p - CASE WHEN k = label THEN 1 ELSE 0 END, 2))) AS s, -ln(sum(CASE WHEN k = label THEN p ELSE 0 END)) AS loss, arg_max(k, p) AS guess FROM p{step} GROUP BY id, label"


for _s in range(4):
    _train(_s)
_train(1, "ten")


def _warp(share: float, name: str) -> None:
    STEPS[f"beta{name}"] = f"SELECT avg(z) AS mean, 1 + 10 * avg(z) * power({share}, 0.5) AS a FROM r"
    STEPS[f"x{name}"] = f"SELECT r.id, CASE WHEN z > 0 AND z < 1 THEN exp((a - 1) * ln(z) + (10 - a - 1) * ln(1 - z) - (lgamma(a) + lgamma(10 - a) - lgamma(10))) ELSE 0 END AS x FROM r, beta{name}"


_warp(0.10, "")
for _c in (2, 5, 10, 20, 30):
    _warp(_c / 100, f"_{_c}")


def _knn(name: str, k: int, d: str = "d2") -> None:
    STEPS[name] = f"SELECT src, dst, d2, rank FROM (SELECT src, dst, {d} AS d2, row_number() OVER (PARTITION BY src ORDER BY round({d}, 12), dst) AS rank FROM near) WHERE rank <= {k}"


STEPS["vc"] = "SELECT a.id, b.v FROM v a JOIN v b ON b.id = a.id - a.id % 25"
STEPS["nearc"] = STEPS["near"].replace("FROM v a JOIN v b", "FROM vc a JOIN vc b")
_knn("knn", 10)
_knn("knnc", 10)
STEPS["knnc"] = STEPS["knnc"].replace("FROM near", "FROM nearc")
_knn("knn5", 5)
STEPS["edges5"] = STEPS["edges"].replace("knn", "knn5")


def _chain(name: str, cells: str, weights: str, b: int, lam: float) -> None:
    """Greedy picks name1 .. nameB: cells (c, u, s) say how far a candidate covers a row."""
    for t in range(1, b + 1):
        taken = " UNION ALL ".join(f"SELECT c FROM {name}{i}" for i in range(1, t))
        best = f"{name}m{t - 1}"
        if t == 1:
            gains = f"SELECT c, sum(s) AS g FROM {cells} GROUP BY c"
        else:
            gains = f"SELECT x.c, sum(greatest(x.s - coalesce(m.m, 0), 0)) AS g FROM {cells} x LEFT JOIN {best} m USING (u) WHERE x.c NOT IN ({taken}) GROUP BY x.c"
        STEPS[f"{name}{t}"] = f"SELECT {t} AS round, q.c, round({lam} * q.g + {1 - lam} * x.x, 9) AS gain FROM ({gains}) q JOIN {weights} x ON x.id = q.c ORDER BY gain DESC, q.c LIMIT 1"
        new = f"SELECT u, s FROM {cells} WHERE c = (SELECT c FROM {name}{t})"
        STEPS[f"{name}m{t}"] = f"SELECT u, max(s) AS m FROM (({new})" + (f" UNION ALL (SELECT u, m FROM {best})" if t > 1 else "") + ") GROUP BY u"


def _union(name: str, b: int) -> str:
    return " UNION ALL ".join(f"SELECT * FROM {name}{t}" for t in range(1, b + 1))


STEPS["sim"] = "SELECT p.id AS c, o.id AS u, 1 + list_cosine_similarity(p.v, o.v) AS s FROM v p, v o WHERE p.id IN (SELECT id FROM pool)"
STEPS["simclip"] = "SELECT c, u, greatest(s - 1, 0) AS s FROM sim"
STEPS["simall"] = "SELECT p.id AS c, o.id AS u, 1 + list_cosine_similarity(p.v, o.v) AS s FROM v p, v o"
STEPS["cells"] = "SELECT src AS c, dst AS u, greatest(1 - d2 / 2, 0) AS s FROM edges UNION ALL SELECT id, id, 1.0 FROM v"
STEPS["none"] = "SELECT id, 0.0 AS x FROM v"
# A tenth, or another share, of a pool of 0.4 of the 500 vectors that the two smaller table sizes have.
PICKS = 20
_chain("ga", "sim", "x", PICKS, 0.5)
_chain("gb", "sim", "x", PICKS, 1.0)
_chain("gc", "simclip", "x", PICKS, 0.5)
_chain("gg", "cells", "x", PICKS, 0.5)
_chain("gf", "simall", "none", PICKS, 1.0)
for _l in (2, 4, 6, 8):
    _chain(f"gl{_l}q", "sim", "x", PICKS, _l / 10)
for _c in (2, 5, 10, 20, 30):
    _chain(f"gh{_c}q", "sim", f"x_{_c}", 2 * _c, 0.5)

STEPS["rank0"] = "SELECT id, round(p, 9) AS p FROM pri WHERE p > 0"
for _t in range(1, 21):
    _before = " UNION ALL ".join(f"SELECT id FROM an{i}" for i in range(1, _t))
    _free = f" WHERE id NOT IN ({_before}) AND id NOT IN (SELECT dst FROM edges WHERE src IN ({_before}))" if _before else ""
    STEPS[f"an{_t}"] = f"SELECT id, p FROM rank0{_free} ORDER BY p DESC, id LIMIT 1"
STEPS["anchors"] = " UNION ALL ".join(f"SELECT id, p FROM an{t}" for t in range(1, 21))

_names = re.compile(r"\b(" + "|".join(sorted(STEPS, key=len, reverse=True)) + r")\b")


def sql(select: str) -> str:
    """The statement, with the steps it reads, directly or not, before it."""
    need: dict[str, None] = {}

    def visit(text: str) -> None:
        for name in re.findall(r"(?:FROM|JOIN|,)\s+\(?([a-z_][a-z0-9_]*)\b", text):
            if name in STEPS and name not in need:
                visit(STEPS[name])
                need.setdefault(name)

    visit(select)
    steps = ",\n".join(f"{n} AS MATERIALIZED ({STEPS[n]})" for n in need)
    return f"WITH {steps}\n{select}" if need else select


def _propagated(sources: str, mixed: str) -> str:
    return f"""SELECT n.id AS sample_id, round(coalesce(a.sn, {mixed}, n.s), 6) AS score_new FROM nodes n LEFT JOIN new a ON a.id = n.id
    LEFT JOIN (SELECT f.src, sum(f.w * o.sn) AS ws, sum(f.w) AS w FROM aff f JOIN ({sources}) o ON o.id = f.dst WHERE f.af > 0.5 GROUP BY f.src) m ON m.src = n.id"""


HALF, FULL = "0.5 * n.s + 0.5 * m.ws / m.w", "(n.s + m.ws) / (1 + m.w)"
REST = "SELECT id, s AS sn FROM nodes WHERE id NOT IN (SELECT id FROM anchors)"
STEPS["prop"] = _propagated("SELECT id, sn FROM new", HALF).replace("round(coalesce(a.sn, 0.5 * n.s + 0.5 * m.ws / m.w, n.s), 6)", "n.s AS s, coalesce(a.sn, 0.5 * n.s + 0.5 * m.ws / m.w, n.s)")


def _drift(power: str) -> str:
    return f"SELECT h.id AS sample_id, sum(power(0.99, {power}) * abs(h.s - hn.now)) / sum(power(0.99, {power}) * hn.now) AS drift FROM h JOIN hn ON hn.id = h.id GROUP BY h.id"


STEPS["dr"] = _drift("hn.top - h.step")
STEPS["med"] = "SELECT id, loss, round(abs(loss - quantile_cont(loss, 0.5) OVER ()), 9) AS d FROM i1"
STEPS["med2"] = "SELECT id, loss, round(abs(loss - quantile_cont(loss, 0.5) OVER ()), 9) AS d FROM i2"


def _top(source: str, order: str, b: int = 50) -> str:
    return f"SELECT id AS sample_id, CAST(row_number() OVER (ORDER BY {order}, id) AS INTEGER) AS rank FROM {source} ORDER BY {order}, id LIMIT {b}"


for _t in range(0, 3):
    STEPS[f"km{_t}"] = (
        "SELECT CAST(row_number() OVER (ORDER BY id) - 1 AS INTEGER) AS cl, v AS c FROM (SELECT id, v FROM v ORDER BY id LIMIT 5)" if _t == 0
        else f"SELECT cl, list(x ORDER BY j) AS c FROM (SELECT a.cl, e.j, avg(e.x) AS x FROM ka{_t - 1} a JOIN e ON e.id = a.id GROUP BY a.cl, e.j) GROUP BY cl"
    )
    STEPS[f"ka{_t}"] = f"SELECT v.id, arg_min(m.cl, struct_pack(d := round(list_sum(list_transform(list_zip(v.v, m.c), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), 9), c := m.cl)) AS cl FROM v, km{_t} m GROUP BY v.id"
STEPS["kq"] = "SELECT cl, n, floor(round(50.0 * n / sum(n) OVER (), 9)) AS f, 50.0 * n / sum(n) OVER () AS q FROM (SELECT cl, count(*) AS n FROM ka2 GROUP BY cl)"
STEPS["kr"] = "SELECT cl, f + CASE WHEN row_number() OVER (ORDER BY round(q - f, 9) DESC, cl) <= 50 - sum(f) OVER () THEN 1 ELSE 0 END AS quota FROM kq"
STEPS["gn"] = "SELECT i1.id, round(i1.s * sqrt(list_dot_product(v.v, v.v)), 9) AS g FROM i1 JOIN v USING (id)"
STEPS["gsum"] = "SELECT k, j, sum(g) AS t FROM g GROUP BY k, j"
STEPS["nearest"] = "SELECT id, arg_min(rep, struct_pack(d := round(d, 9), r := rep)) AS rep, min(d) AS d FROM (SELECT v.id, p.id AS rep, sqrt(list_sum(list_transform(list_zip(v.v, p.v), lambda q: (q[1] - q[2]) * (q[1] - q[2])))) AS d FROM v, v p WHERE p.id IN (SELECT id FROM ten)) GROUP BY id"
STEPS["drop1"] = "SELECT i1.id, round(i0.loss - i1.loss, 9) AS d FROM i0 JOIN i1 USING (id)"
STEPS["lc"] = "SELECT conv_id * 1000 + turn AS id, len(list_filter(regexp_split_to_array(completion, '\\s+'), lambda x: x <> '')) AS n FROM pairs"
STEPS["od"] = "SELECT g.id, round(sum(g.g * t.t), 9) AS c FROM g JOIN gsum t ON t.k = g.k AND t.j = g.j GROUP BY g.id"
STEPS["half"] = "SELECT h.id, arg_max(h.s, h.step) FILTER (h.step <= hn.top // 2) AS mid, any_value(hn.now) AS fin FROM h JOIN hn ON hn.id = h.id GROUP BY h.id"
STEPS["err1"] = "SELECT id, list(p - CASE WHEN k = label THEN 1 ELSE 0 END ORDER BY k) AS er FROM p1 GROUP BY id"
STEPS["gv"] = "SELECT id, list(g ORDER BY k, j) AS gr FROM g GROUP BY id"
STEPS["bt"] = "SELECT a.id, list_distance(a.gr, b.gr) AS gd, list_distance(va.v, vb.v) AS vd, list_distance(ea.er, eb.er) AS ed FROM gv a JOIN gv b ON b.id = a.id + 1 JOIN v va ON va.id = a.id JOIN v vb ON vb.id = b.id JOIN err1 ea ON ea.id = a.id JOIN err1 eb ON eb.id = b.id"


def oracles() -> dict[str, str]:
    greedy = lambda name, b=PICKS: f"SELECT round, c AS sample_id, round(gain, 6) AS gain FROM ({_union(name, b)})"
    top_x = "SELECT CAST(row_number() OVER (ORDER BY round(x, 9) DESC, id) AS INTEGER) AS round, id AS sample_id, round(x, 6) AS gain FROM x WHERE id IN (SELECT id FROM pool) ORDER BY round(x, 9) DESC, id LIMIT (SELECT picks FROM bud)"
    parts = " UNION ALL ".join(
        f"SELECT {p} AS parts, part, round(avg(d), 6) AS drift FROM (SELECT id, part, sum(power(0.99, top - step) * abs(s - now)) / sum(power(0.99, top - step) * now) AS d FROM (SELECT id, step, s, part, max(step) OVER q AS top, last_value(s) OVER (PARTITION BY id, part ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS now FROM (SELECT id, step, s, CAST(floor(step * {p} / count(*) OVER (PARTITION BY id)) AS INTEGER) AS part FROM h) WINDOW q AS (PARTITION BY id, part)) GROUP BY id, part) GROUP BY part"
        for p in (8, 4, 2, 1)
    )
    weigh = lambda total: f"SELECT round(sqrt(sum(t * t)), 6) AS gap FROM (SELECT k, j, sum(g * (1 - coalesce(w, 0))) AS t FROM g LEFT JOIN ({total}) q USING (id) GROUP BY k, j)"
    epochs = lambda f, span: " UNION ALL ".join(f"SELECT {i} AS epoch, * FROM ({f(i)})" for i in span)
    uniform = lambda i: f"SELECT id AS sample_id FROM v ORDER BY md5('42:{i}:' || id), id LIMIT 50"
    facility = f"SELECT c AS sample_id, round AS rank FROM ({_union('gf', PICKS)})"
    out = {
        "warmup_params": "SELECT CAST(k AS INTEGER) AS label, CAST(j AS INTEGER) AS dim, round(w, 6) AS value FROM w1",
        "importance_softmax": "SELECT id AS sample_id, round(s, 6) AS score, round(loss, 6) AS loss FROM i1",
        "importance_native": "SELECT id AS sample_id, round(s, 6) AS score FROM i1",
        "importance_rescaled": "SELECT id AS sample_id, round(z, 6) AS z FROM r",
        "importance_rescaled_by_source": "SELECT id AS sample_id, label, round((s - min(s) OVER q) / (max(s) OVER q - min(s) OVER q), 6) AS z FROM i1 WINDOW q AS (PARTITION BY label)",
        "beta_params": "SELECT round(mean, 6) AS mean, round(a, 6) AS beta_a, round(10 - a, 6) AS beta_b, round((a - 1) / 8, 6) AS mode, false AS clamped FROM beta",
        "importance_warped": "SELECT id AS sample_id, round(x, 6) AS warped FROM x",
        "warp_mode_by_budget": " UNION ALL ".join(f"SELECT {c / 100} :: DOUBLE AS budget, round((a - 1) / 8, 6) AS mode FROM beta_{c}" for c in (2, 5, 10, 20, 30)),
        "warmup_eval": "SELECT round(avg(CASE WHEN guess = label THEN 1.0 ELSE 0.0 END), 6) AS accuracy, round(avg(loss), 6) AS loss FROM i1",
        "eval_base": "SELECT round(avg(loss), 6) AS loss, round(avg(s), 6) AS score FROM i0",
        "eval_full": "SELECT round(avg(loss), 6) AS loss, round(avg(s), 6) AS score FROM i3",
        "interval_train_params": "SELECT CAST(k AS INTEGER) AS label, CAST(j AS INTEGER) AS dim, round(w, 6) AS value FROM w1ten",
        "coverage_of_set": "SELECT o.id AS sample_id, round(max(list_cosine_similarity(p.v, o.v)), 6) AS best FROM v o, v p WHERE p.id IN (SELECT id FROM ten) GROUP BY o.id",
        "objective_of_set": "SELECT round(c, 6) AS coverage, round(i, 6) AS importance, round(0.5 * c + 0.5 * i, 6) AS objective, CAST(10 AS BIGINT) AS picks FROM (SELECT (SELECT sum(b) FROM (SELECT max(list_cosine_similarity(p.v, o.v)) AS b FROM v o, v p WHERE p.id IN (SELECT id FROM ten) GROUP BY o.id)) AS c, (SELECT sum(x) FROM x WHERE id IN (SELECT id FROM ten)) AS i)",
        "first_round_gains": greedy("ga", 1), "greedy_select": greedy("ga"), "greedy_lazy": greedy("ga"), "greedy_distributed": greedy("ga"), "greedy_clip": greedy("gc"),
        "select_importance_only": top_x, "select_representation_only": greedy("gb"), "greedy_graph": greedy("gg"), "greedy_dominance": greedy("gg"),
        "cumulative_coverage": f"SELECT round, round(sum(gain) OVER (ORDER BY round), 5) AS so_far, round(sum(gain) OVER (ORDER BY round) / sum(gain) OVER (), 5) AS share FROM ({greedy('ga')})",
        "candidate_pool": "SELECT id AS sample_id FROM pool",
        "knn_exact": "SELECT src, dst, CAST(rank AS INTEGER) AS rank, round(d2, 6) AS d2 FROM knn",
        "knn_with_copies": "SELECT src, dst, CAST(rank AS INTEGER) AS rank FROM knnc",
        "knn_cosine": "SELECT src, dst, CAST(rank AS INTEGER) AS rank, round(d, 6) AS d2 FROM (SELECT a.id AS src, b.id AS dst, 1 - list_cosine_similarity(a.v, b.v) AS d, row_number() OVER (PARTITION BY a.id ORDER BY round(1 - list_cosine_similarity(a.v, b.v), 12), b.id) AS rank FROM v a JOIN v b ON a.id <> b.id) WHERE rank <= 10",
        "mutual_knn_edges": "SELECT src, dst FROM edges WHERE src < dst",
        "edge_weights": "SELECT src, dst, round(w, 6) AS w FROM edges WHERE src < dst",
        "edge_weights_median": "SELECT src, dst, round(exp(-d2 / (SELECT quantile_cont(d2, 0.5) FROM edges)), 6) AS w FROM edges WHERE src < dst",
        "graph_degree_stats": "SELECT degree, count(*) AS n FROM (SELECT v.id, count(e.dst) AS degree FROM v LEFT JOIN edges e ON e.src = v.id GROUP BY v.id) GROUP BY degree",
        "adjacency_lists": "SELECT src, count(*) AS degree, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS neighbours FROM edges GROUP BY src",
        "graph_diff": "SELECT kind, count(*) AS n FROM (SELECT CASE WHEN a.src IS NULL THEN 'added' WHEN b.src IS NULL THEN 'removed' ELSE 'kept' END AS kind FROM (SELECT src, dst FROM edges WHERE src < dst) a FULL JOIN (SELECT src, dst FROM edges5 WHERE src < dst) b ON a.src = b.src AND a.dst = b.dst) GROUP BY kind",
        "history_latest": "SELECT id AS sample_id, top AS step, round(now, 9) AS score FROM hn",
        "drift_statistic": "SELECT sample_id, round(drift, 6) AS drift FROM dr",
        "drift_statistic_as_printed": f"SELECT sample_id, round(drift, 6) AS drift FROM ({_drift('h.step - hn.top')})",
        "drift_by_threshold": "SELECT round(i * 0.05, 2) :: DOUBLE AS delta, CAST(sum(CASE WHEN drift > round(i * 0.05, 2) THEN 1 ELSE 0 END) AS BIGINT) AS fired, round(avg(CASE WHEN drift > round(i * 0.05, 2) THEN 1.0 ELSE 0.0 END), 6) AS share FROM dr, (SELECT unnest(range(8)) AS i) GROUP BY i",
        "w9_interval_sweep": parts,
        "staleness": f"SELECT id AS sample_id, {T} - last AS staleness FROM nodes",
        "uniqueness": "SELECT id AS sample_id, round(uq, 6) AS uniqueness FROM uq",
        "update_priority": "SELECT id AS sample_id, round(p, 6) AS priority FROM pri",
        "anchor_choice": "SELECT id AS sample_id, round(p, 6) AS priority FROM anchors",
        "edge_affinity": "SELECT src, dst, round(af, 6) AS affinity FROM aff WHERE src < dst",
        "propagated_scores": _propagated("SELECT id, sn FROM new", HALF),
        "propagated_scores_energy": _propagated("SELECT id, sn FROM new", FULL),
        "propagated_scores_with_recent": _propagated(f"SELECT id, sn FROM new UNION ALL {REST} AND last >= {T - 1}", HALF),
        "propagated_scores_all": _propagated(f"SELECT id, sn FROM new UNION ALL {REST}", HALF),
        "propagation_energy": "SELECT round((SELECT sum(power(score_new - s, 2)) FROM prop), 6) AS fidelity, round((SELECT sum(e.w * power(a.score_new - b.score_new, 2)) FROM edges e JOIN prop a ON a.sample_id = e.src JOIN prop b ON b.sample_id = e.dst), 6) AS smoothness",
        "embedding_shift": "SELECT round(avg(list_distance(v, vn)), 6) AS shift FROM vnew",
        "propagated_vectors": "SELECT v.id AS sample_id, CAST(i - 1 AS INTEGER) AS dim, round(coalesce(a.vn[i], 0.5 * v.v[i] + 0.5 * m.m, v.v[i]), 6) AS value FROM v CROSS JOIN (SELECT unnest(range(1, 65)) AS i) LEFT JOIN vnew a ON a.id = v.id LEFT JOIN (SELECT f.src, t.i AS q, sum(f.w * o.vn[t.i]) / sum(f.w) AS m FROM aff f JOIN vnew o ON o.id = f.dst, (SELECT unnest(range(1, 65)) AS i) t WHERE f.af > 0.5 GROUP BY f.src, t.i) m ON m.src = v.id AND m.q = i",
        "update_change_bound": "SELECT round(l, 6) AS largest_change, round(greatest(nh - ol, oh - nl) / 2, 6) AS bound, l <= greatest(nh - ol, oh - nl) / 2 + 1e-12 AS holds FROM (SELECT (SELECT max(abs(score_new - s)) FROM prop WHERE sample_id NOT IN (SELECT id FROM anchors)) AS l, (SELECT min(s) FROM nodes) AS ol, (SELECT max(s) FROM nodes) AS oh, (SELECT min(sn) FROM new) AS nl, (SELECT max(sn) FROM new) AS nh)",
        "selective_update_error": "SELECT round(max(abs(d)), 6) AS max_error, round(avg(abs(d)), 6) AS mean_error, round(sqrt(avg(d * d)), 6) AS rmse FROM (SELECT p.score_new - i2.s AS d FROM prop p JOIN i2 ON i2.id = p.sample_id)",
        "gradient_gap": weigh("SELECT id, 1.0 AS w FROM ten"),
        "gradient_gap_weighted": weigh("SELECT rep AS id, count(*) AS w FROM nearest GROUP BY rep"),
        "nearest_gradient_bound": "SELECT round(sum(d), 6) AS bound FROM (SELECT a.id, min(list_distance(a.gr, b.gr)) AS d FROM gv a, gv b WHERE b.id IN (SELECT id FROM ten) GROUP BY a.id)",
        "representative_assignment": "SELECT id AS sample_id, rep AS rep_id, round(d, 6) AS dist FROM nearest",
        "representative_weights": "SELECT rep AS rep_id, count(*) AS weight FROM nearest GROUP BY rep",
        "bound_terms": "SELECT id AS sample_id, round(gd, 6) AS gradient_diff, round(vd, 6) AS vector_diff, round(ed, 6) AS error_diff, gd <= (SELECT max(sqrt(list_dot_product(er, er))) FROM err1) * vd + (SELECT max(sqrt(list_dot_product(v, v))) FROM v) * ed + 1e-9 AS holds FROM bt",
        "subset_overlap": "SELECT c AS common, 200 - c AS together, round(c / (200.0 - c), 6) AS jaccard FROM (SELECT count(*) AS c FROM (SELECT id FROM v ORDER BY md5('42:0:' || id), id LIMIT 100) a JOIN (SELECT id FROM v ORDER BY md5('42:1:' || id), id LIMIT 100) b USING (id))",
        "subset_mix": "SELECT label, n AS n_corpus, coalesce(m, 0) AS n_picks, round(n / sum(n) OVER (), 6) AS share_corpus, round(coalesce(m, 0) / sum(m) OVER (), 6) AS share_picks FROM (SELECT label, count(*) AS n FROM v GROUP BY label) LEFT JOIN (SELECT label, count(*) AS m FROM v WHERE id IN (SELECT id FROM v ORDER BY md5('42:0:' || id), id LIMIT 50) GROUP BY label) USING (label)",
        "rank_stability": "SELECT round(corr(a, b), 6) AS correlation FROM (SELECT CAST(rank() OVER (ORDER BY mid) AS DOUBLE) AS a, CAST(rank() OVER (ORDER BY fin) AS DOUBLE) AS b FROM half)",
        "score_summary": "SELECT count(*) AS n, round(avg(s), 6) AS mean, round(stddev_samp(s), 6) AS deviation, round(min(s), 6) AS least, round(max(s), 6) AS most, round(corr(s, loss), 6) AS corr_loss FROM i1",
        "difficulty_deciles": "SELECT CAST(decile AS INTEGER) AS decile, count(*) AS n, round(min(s), 6) AS low, round(max(s), 6) AS high FROM (SELECT s, ntile(10) OVER (ORDER BY round(s, 9), id) AS decile FROM i1) GROUP BY decile",
        "base_uniform": uniform(0), "base_uniform_epochs": epochs(uniform, range(3)),
        "base_median_loss": _top("med", "d"), "base_median_loss_epochs": epochs(lambda i: _top("med" if i == 1 else "med2", "d"), (1, 2)),
        "base_facility_location": facility, "base_facility_location_epochs": epochs(lambda i: facility, (1, 2)),
        "base_loss_drop": _top("drop1", "d DESC"), "base_longest_completion": _top("lc", "n DESC", 20), "base_grad_norm": _top("gn", "g DESC"),
        "base_least_confidence": _top("(SELECT id, round(-loss, 9) AS c FROM i1)", "c"),
        "base_omp_first_picks": "SELECT CAST(1 AS INTEGER) AS round, id AS sample_id FROM od ORDER BY c DESC, id LIMIT 1",
        "kmeans_assign": "SELECT id AS sample_id, cl AS cluster FROM ka2",
        "cluster_quota_draw": "SELECT id AS sample_id, cl AS cluster FROM (SELECT id, cl, row_number() OVER (PARTITION BY cl ORDER BY md5('42:0:' || id)) AS k FROM ka2) JOIN kr USING (cl) WHERE k <= quota",
        "w6_lambda_sweep": " UNION ALL ".join([f"SELECT 0.0 :: DOUBLE AS lam, round(sum(gain), 5) AS objective FROM ({top_x})", *(f"SELECT {i / 10} :: DOUBLE AS lam, round(sum(gain), 5) AS objective FROM ({_union(f'gl{i}q', PICKS)})" for i in (2, 4, 6, 8)), f"SELECT 1.0 :: DOUBLE AS lam, round(sum(gain), 5) AS objective FROM ({_union('gb', PICKS)})"]),
        "w5_budget_sweep": " UNION ALL ".join(f"SELECT {c / 100} :: DOUBLE AS budget, count(*) AS picks, round(sum(gain), 5) AS objective FROM ({_union(f'gh{c}q', 2 * c)})" for c in (2, 5, 10, 20, 30)),
    }
    from . import relational_sql

    return {k: sql(x) for k, x in out.items()} | relational_sql.oracles()
