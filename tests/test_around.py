"""The operators around the methods: joins, sketches, ranks, sources, sinks, streams and counters."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from coreset_spark.operators import baselines, blocks, counters, graph, joins, metrics, ranks, select, sketches, update
from coreset_spark.plans import relational
from coreset_spark.sinks import tables as sinks
from coreset_spark.sources import paged
from coreset_spark.streaming import readings

RNG = np.random.default_rng(5)


def frame(spark, x, **more):
    return spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "sample_id long, vec array<double>")


def test_ties_go_by_id(spark):
    x = np.repeat(RNG.normal(size=(3, 4)), 20, 0)
    got = {}
    for r in graph.knn_exact(frame(spark, x), 3, block=7).collect():
        got.setdefault(r["src"], []).append(r["dst"])
    for i in range(60):
        group = [j for j in range(i // 20 * 20, i // 20 * 20 + 20) if j != i][:3]
        assert sorted(got[i]) == group


def test_hashed_search_is_exact_where_every_sign_is_looked_up(spark):
    rows = frame(spark, RNG.normal(size=(90, 6)))
    want = {(r["src"], r["dst"], r["rank"]) for r in graph.knn_exact(rows, 5).collect()}
    for how in (graph.EVERY, graph.Hashing(2, 3, 3)):
        assert {(r["src"], r["dst"], r["rank"]) for r in graph.knn_lsh(rows, 5, how, block=16).collect()} == want


def test_hashed_search_reaches_its_recall_on_a_part_of_the_pairs(spark):
    """Rows in groups, as real vectors are: few buckets tell nearly all neighbours."""
    centres = RNG.normal(size=(40, 12)) * 4
    x = np.concatenate([c + RNG.normal(size=(40, 12)) * 0.3 for c in centres])
    rows = frame(spark, x)
    how = graph.calibrate(rows, 5, 0.95, sample=100)
    recall = graph.knn_recall(graph.knn_lsh(rows, 5, how), graph.knn_exact(rows, 5)).first()[0]
    assert recall >= 0.9 and how.share() < 0.35


def test_hashed_repair_keeps_its_recall(spark):
    x = np.concatenate([c + RNG.normal(size=(30, 8)) * 0.3 for c in RNG.normal(size=(20, 8)) * 4])
    y = x.copy()
    y[::9] = x[(np.arange(len(x)) * 7 % len(x))[::9]] + 0.01
    old, new, ids = frame(spark, x), frame(spark, y), spark.createDataFrame([(i,) for i in range(0, len(x), 9)], "sample_id long")
    how = graph.calibrate(old, 5, 0.95, sample=100)
    lists, _ = graph.repair_graph(new, graph.knn_lsh(old, 5, how), ids, 5, how)
    assert graph.knn_recall(lists, graph.knn_exact(new, 5)).first()[0] >= 0.9


@pytest.mark.parametrize("rows", [300])
def test_long_chains_have_no_cap(spark, rows, monkeypatch):
    ranked = spark.createDataFrame([(i, float(rows + 1 - i)) for i in range(1, rows + 1)], "sample_id long, priority double")
    links = [(i, i + 1) for i in range(1, rows)]
    e = spark.createDataFrame(links + [(b, a) for a, b in links], "src long, dst long")
    assert [r["sample_id"] for r in update.choose_anchors(ranked, e, rows).collect()] == list(range(1, rows + 1, 2))
    monkeypatch.setattr(update, "ONE_TASK_ROWS", rows - 12)  # some rounds before one task takes the rest
    assert [r["sample_id"] for r in update.choose_anchors(ranked, e, rows).collect()] == list(range(1, rows + 1, 2))
    monkeypatch.setattr(update, "ONE_TASK_ROWS", 0)
    assert [r["sample_id"] for r in update.choose_anchors(ranked, e, 4).collect()] == [1, 3, 5, 7]


def test_dominance_takes_as_many_sweeps_as_it_needs(spark, monkeypatch):
    n = 24
    pool = spark.createDataFrame([(i, [1.0], float(n - i)) for i in range(n)], "sample_id long, vec array<double>, warped double")
    links = [(i, i + 1) for i in range(n - 1)]
    e = spark.createDataFrame([(a, b, 1.0) for x, y in links for a, b in ((x, y), (y, x))], "src long, dst long, d2 double")
    for balance in ("sum", "mean"):
        one = [(r["sample_id"], round(r["gain"], 7)) for r in select.select_greedy(pool, None, 10, 0.5, "graph", edges=e, balance=balance).collect()]
        two = [(r["sample_id"], round(r["gain"], 7)) for r in select.select_greedy(pool, None, 10, 0.5, "dominance", edges=e, balance=balance).collect()]
        assert one == two and len(one) == 10
    monkeypatch.setattr(select, "ONE_TASK_PAIRS", 0)
    assert [(r["sample_id"], round(r["gain"], 7)) for r in select.select_greedy(pool, None, 10, 0.5, "graph", edges=e, balance="mean").collect()] == two


def test_lazy_is_exact_greedy_also_as_printed():
    for seed in range(40):
        r = np.random.default_rng(seed)
        x = r.normal(size=(15, 3))
        sim, ids = select.block(x, x, "raw"), np.arange(15)
        w = r.random(15) * (seed % 2)
        for scale in ((1.0, 1.0), (1 / 15, 1 / 6)):
            assert select.lazy(sim, w, ids, 6, 0.8, scale)[0] == select.greedy(sim, w, ids, 6, 0.8, scale)


def test_stochastic_bound_and_parts(spark):
    """In the mean over draws no less than 1 - 1/e - eps of what greedy reaches; parts reach nearly all of it."""
    x = RNG.normal(size=(80, 5))
    sim, w, ids = select.block(x, x, "shift"), np.zeros(80), np.arange(80)
    value = lambda picks: sim[:, [i for i, _ in picks]].max(1).sum()
    best = value(select.greedy(sim, w, ids, 8, 1.0))
    assert np.mean([value(select.stochastic(sim, w, ids, 8, 1.0, seed=s)) for s in range(20)]) >= (1 - 1 / np.e - 0.1) * best
    rows = frame(spark, x).withColumn("warped", F.lit(0.0))
    told = [(r["sample_id"], r["gain"]) for r in select.select_greedy(rows, None, 8, 1.0, "partitioned").collect()]
    assert len(told) == 8 and value(told) >= 0.9 * best


def test_more_picks_than_are_broadcast(spark, monkeypatch):
    rows, picks = frame(spark, RNG.normal(size=(50, 4))), frame(spark, RNG.normal(size=(12, 4)))
    best = lambda: {r["sample_id"]: round(r["best"], 9) for r in select.best_similarity(rows, picks).collect()}
    near = lambda: {r["sample_id"]: (r["rep_id"], round(r["dist"], 9)) for r in metrics.assign_representatives(rows, picks).collect()}
    want = best(), near()
    monkeypatch.setattr(select, "FEW_PICKS", 3)
    monkeypatch.setattr(blocks, "SIDE", 5)
    assert (best(), near()) == want


def test_matching_pursuit_in_one_task_and_in_rounds(spark, monkeypatch):
    a = RNG.normal(size=(40, 6))
    g = spark.createDataFrame([(i, int(i % 2), v.tolist()) for i, v in enumerate(a)], "sample_id long, label int, grad array<double>")
    told = lambda **o: [(r["round"], r["sample_id"], round(r["weight"], 6)) for r in baselines.omp_select(g, 5, **o).collect()]
    by_part = lambda: sorted((r["sample_id"], round(r["weight"], 6)) for r in baselines.omp_per_cluster(g, 5).collect())
    want = told(), told(nonneg=True), by_part()
    residual, full, chosen = a.sum(0), a.sum(0), []
    for _ in range(5):
        c = a @ residual
        c[chosen] = -np.inf
        chosen.append(int(c.argmax()))
        w = np.linalg.lstsq(a[chosen].T, full, rcond=None)[0]
        residual = full - w @ a[chosen]
    assert [x[1] for x in want[0]] == chosen and np.allclose([x[2] for x in want[0]], w, atol=1e-5)
    assert all(x[2] >= 0 for x in want[1]) and len(want[2]) == 5
    monkeypatch.setattr(baselines, "ONE_TASK_NUMBERS", 0)
    assert (told(), told(nonneg=True), by_part()) == want


def test_weights_of_at_least_zero():
    for seed in range(30):
        r = np.random.default_rng(seed)
        a, y = r.normal(size=(12, 6)), r.normal(size=12)
        w = baselines.nnls(a.T @ a, a.T @ y)
        slope = a.T @ (a @ w - y)
        assert (w >= 0).all() and (slope >= -1e-8).all() and abs(slope @ w) < 1e-8  # what such a minimum has to meet


def test_ranks_and_quantiles(spark):
    values = [float(v) for v in RNG.integers(0, 40, 200)] + [1e9, -1e9]
    rows = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "sample_id long, v double").repartition(7)
    got = {r["sample_id"]: r["row_number"] for r in ranks.row_numbers(rows, "v", "sample_id").collect()}
    order = sorted(range(len(values)), key=lambda i: (values[i], i))
    assert [got[i] for i in order] == list(range(1, len(values) + 1))
    tiles = {r["sample_id"]: r["tile"] for r in ranks.tiles(rows, 7, "v", "sample_id").collect()}
    assert [tiles[i] for i in order] == [k + 1 for k, part in enumerate(np.array_split(order, 7)) for _ in part]
    told = {r["sample_id"]: r["rank"] for r in ranks.ranks(rows, "v").collect()}
    assert all(told[i] == 1 + sum(x < v for x in values) for i, v in enumerate(values))
    for q in (0.0, 0.1, 0.5, 0.73, 1.0):
        assert abs(ranks.quantile(rows, "v", q) - np.quantile(values, q)) < 1e-9
    assert ranks.quantile(rows.limit(0), "v", 0.5) is None and ranks.order_statistic(rows, "v", 9999) is None


def test_null_safe_and_salted_joins(spark):
    a = spark.createDataFrame([(1, "x"), (None, "y"), (3, "z")], "k long, a string")
    b = spark.createDataFrame([(1, "p"), (None, "q")], "k long, b string")
    assert sorted((str(r["k"]), r["a"], str(r["b"])) for r in joins.null_safe(a, b, ["k"], "left").collect()) == [("1", "x", "p"), ("3", "z", "None"), ("None", "y", "q")]
    left = spark.createDataFrame([(7 if i < 300 else i, i) for i in range(400)], "k long, i long")
    right = spark.createDataFrame([(k, k * 10) for k in [7, 7, *range(300, 390)]], "k long, v long")
    want = sorted(map(tuple, left.join(right, "k").collect()))
    got = joins.salted(left, right, "k", parts=4)
    assert sorted(map(tuple, got.collect())) == want


def test_sketches_keep_their_bounds(spark):
    words = spark.createDataFrame([(f"w{int(v)}",) for v in RNG.zipf(1.6, 4000) % 500], "w string")
    numbers = spark.createDataFrame([(float(v),) for v in RNG.normal(size=3000)], "x double")
    assert all(r["holds"] for r in sketches.errors(words, numbers).collect())


def test_passages_of_any_length_are_found(spark):
    docs = ["a b c d e f g h", "xa b c d e f gx", "one two", "tone twos", "long a b c d e f end", "", None]
    d = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    passages = ["a b c d e f g", "e t", "one two", "b c", "zz"]
    p = spark.createDataFrame([(x,) for x in passages], "passage string")
    want = {i for i, t in enumerate(docs) if t and any(x in t for x in passages)}
    assert {r["doc_id"] for r in relational.leaks(d, p).collect()} == want


def test_pages_as_a_table_and_as_a_stream(spark, tmp_path):
    spark.dataSource.register(paged.CandidatePages)
    options = {"rows": 25, "page": 10}
    table = spark.read.format("candidate_pages").options(**options).load()
    assert table.count() == 25 and table.rdd.getNumPartitions() == 3
    q = spark.readStream.format("candidate_pages").options(**options).load().writeStream.format("memory").queryName("pages").option("checkpointLocation", str(tmp_path)).start()
    try:
        q.processAllAvailable()
        assert sorted(map(tuple, spark.table("pages").collect())) == sorted(map(tuple, table.collect()))
    finally:
        q.stop()


def test_sinks(spark, tmp_path):
    rows = spark.createDataFrame([(i, "a" if i % 3 else "b", i % 2) for i in range(60)], "id long, source string, x int")
    sinks.by_columns(rows, str(tmp_path / "p"), ["source"], per_file=10)
    assert (tmp_path / "p" / "source=a").is_dir() and spark.read.parquet(str(tmp_path / "p")).filter("source = 'b'").count() == 20
    name = "edges_in_buckets"
    sinks.in_buckets(rows, name, "id", 4, str(tmp_path / "b"), "overwrite")
    try:
        a = spark.table(name)
        plan = a.hint("merge").join(spark.table(name).withColumnRenamed("x", "y"), "id")._jdf.queryExecution().executedPlan().toString()
        assert a.count() == 60 and "Exchange hashpartitioning" not in plan
    finally:
        spark.sql(f"DROP TABLE {name}")


def test_counters_tell_the_join(spark):
    a = spark.range(1000).withColumnRenamed("id", "k").repartition(3)
    told = counters.plan_metrics(a.hint("merge").join(spark.range(500).withColumnRenamed("id", "k"), "k"))
    assert counters.largest(told, node="Join") == 500 and counters.total(told, "shuffle bytes written") > 0


# --- streams ----------------------------------------------------------------------------------

DAY = dt.datetime(2024, 1, 1)


def events(spark, tmp_path, rows, name="in"):
    """Files of (event_id, hours, user, value), each file one micro-batch."""
    at = tmp_path / name
    for k, part in enumerate(rows):
        out = [(i, DAY + dt.timedelta(hours=h), u, "x", float(v), "{}") for i, h, u, v in part]
        spark.createDataFrame(out, readings.EVENTS.replace("timestamp_ntz", "timestamp")).select("event_id", F.col("ts").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value", "props").coalesce(1).write.parquet(str(at / f"{k}"))
        for f in (at / f"{k}").glob("part-*.parquet"):
            f.rename(at / f"{k:03d}.parquet")
    return readings.source(spark, str(at), per_trigger=1)


def told(stream, tmp_path, mode, name):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / f"cp-{name}")).trigger(availableNow=True).start()
    q.awaitTermination()
    return q, stream.sparkSession.table(name).collect()


def test_late_readings_are_dropped_and_counted(spark, tmp_path):
    rows = [[(1, 1, 7, 1)], [(2, 100, 7, 2)], [(6, 101, 7, 2)], [(3, 2, 7, 9), (4, 102, 7, 3)], [(5, 200, 7, 1)]]  # a batch judges by the watermark of the one before the last
    q, out = told(readings.daily(events(spark, tmp_path, rows)), tmp_path, "append", "late")
    days = {r["window"].start.replace(tzinfo=None): r["n"] for r in out}
    assert days[DAY] == 1 and days[DAY + dt.timedelta(days=4)] == 3
    dropped = sum(s["numRowsDroppedByWatermark"] for p in q.recentProgress for s in p["stateOperators"])
    assert dropped >= 1
    sliding = readings.daily(events(spark, tmp_path, rows, "again"), slide="12 hours")
    assert len(told(sliding, tmp_path, "complete", "slid")[1]) > len(out)


def test_replays_are_dropped(spark, tmp_path):
    rows = [[(1, 1, 7, 1), (2, 2, 7, 1)], [(1, 1, 7, 1), (3, 3, 7, 1)]]
    assert sorted(r["event_id"] for r in told(readings.once(events(spark, tmp_path, rows)), tmp_path, "append", "once")[1]) == [1, 2, 3]


def readings_of(stream):
    return stream.select(F.col("user_id").alias("sample_id"), "ts", F.col("event_id").alias("step"), F.col("value").alias("score"))


def test_drift_by_state_is_the_batch_statistic(spark, tmp_path):
    rows = [[(1, 1, 7, 1), (2, 2, 8, 4)], [(3, 3, 7, 2)], [(4, 4, 7, 1.5), (5, 5, 8, 5)]]
    out = told(readings.drifts(readings_of(events(spark, tmp_path, rows)).drop("ts")), tmp_path, "update", "drifts")[1]
    flat = spark.createDataFrame([(u, i, float(v)) for part in rows for i, _, u, v in part], "sample_id long, step long, score double")
    last = {r["sample_id"]: (n, r["drift"]) for n, r in sorted((r["n"], r) for r in out)}
    # steps of a row are its own order in the stream, and 0, 1, 2 in the batch
    order = flat.selectExpr("sample_id", "row_number() over (partition by sample_id order by step) - 1 as step", "score")
    batch = {r["sample_id"]: r["drift"] for r in update.score_drift(order.selectExpr("sample_id", "cast(step as long) as step", "score")).collect()}
    assert {k: round(v, 9) for k, (_, v) in last.items()} == {k: round(v, 9) for k, v in batch.items()} and {k: n for k, (n, _) in last.items()} == {7: 3, 8: 2}


def test_closed_intervals_time_out(spark, tmp_path):
    """A row's interval is told once event time has left it behind; the last one stays open."""
    rows = [[(1, 1, 7, 1), (2, 2, 7, 2)], [(3, 80, 8, 1)], [(4, 200, 8, 1)], [(5, 400, 9, 1)]]
    out = told(readings.intervals(readings_of(events(spark, tmp_path, rows))), tmp_path, "append", "closed")[1]
    by = {}
    for r in out:
        by.setdefault(r["sample_id"], []).append(r["n"])
    assert by[7] == [2] and abs(next(r["drift"] for r in out if r["sample_id"] == 7) - readings.drift_of([1.0, 2.0])) < 1e-12
    assert 9 not in by and sum(by.get(8, [])) in (1, 2)


def test_stream_meets_a_table_and_another_stream(spark, tmp_path):
    nodes = spark.createDataFrame([(7, 0.5)], "sample_id long, node_score double")
    out = told(readings.with_nodes(readings_of(events(spark, tmp_path, [[(1, 1, 7, 1), (2, 2, 8, 1)]])), nodes), tmp_path, "append", "static")[1]
    assert {r["sample_id"]: r["node_score"] for r in out} == {7: 0.5, 8: None}
    a = readings_of(events(spark, tmp_path, [[(1, 1, 7, 1), (2, 2, 8, 1)]], "a"))
    b = events(spark, tmp_path, [[(9, 1.5, 7, 3), (10, 4, 8, 3)]], "b").select(F.col("user_id").alias("sample_id"), "ts", F.col("value").alias("score_new"))
    both = told(readings.with_extractions(a, b), tmp_path, "append", "two")[1]
    assert [(r["sample_id"], r["score_new"]) for r in both] == [(7, 3.0)]


def test_every_batch_can_act(spark, tmp_path):
    seen = []
    q = readings.on_batch(readings_of(events(spark, tmp_path, [[(1, 1, 7, 1)], [(2, 2, 7, 2)]])), lambda batch, n: seen.append((n, batch.count())), str(tmp_path / "acts"))
    q.awaitTermination()
    assert sum(n for _, n in seen) == 2 and len(seen) == 2
