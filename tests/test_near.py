"""Lateral search, pages of the table's own ids, and edges that a median does not search for again."""

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from coreset_spark.operators import graph


def gaps(path, copies):
    con = duckdb.connect()
    con.execute(f"COPY (SELECT 5000 * i + 3 * vec_id - 90 AS vec_id, * EXCLUDE (vec_id, i) FROM '/root/testdata/sf0.001/embeddings.parquet', range({copies}) t(i)) TO '{path}/embeddings.parquet'")
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{path}/embeddings.parquet'")
    return con


def test_paged_candidates_are_ids_of_the_table(spark, tmp_path):
    """Ids with gaps, below 0 and far from it."""
    con = gaps(tmp_path, 2)
    got = {r[0] for r in entry.queries()["paged_candidates"](spark, str(tmp_path)).collect()}
    assert got == {r[0] for r in con.execute("SELECT vec_id FROM embeddings ORDER BY md5('42:0:' || vec_id), vec_id LIMIT 100").fetchall()}


def test_lateral_topk_sorts_no_pair_of_all_rows(spark, tmp_path):
    con = gaps(tmp_path, 2)  # each row has a copy at distance 0
    df, done = entry.queries()["lateral_topk"](spark, str(tmp_path)), con.execute(entry.oracle_sql()["lateral_topk"])
    want = sorted(done.fetchall())
    got = sorted((r["src"], r["dst"], r["dist"]) for r in df.collect())
    assert [x[:2] for x in got] == [x[:2] for x in want] and np.allclose([x[2] for x in got], [x[2] for x in want], atol=1.5e-6)
    rows = spark.read.parquet(f"{tmp_path}/embeddings.parquet").selectExpr("vec_id AS sample_id", "cast(embedding AS array<double>) AS vec")
    asked = rows.filter("sample_id % 50 = 0")
    assert graph.near_rows(asked, rows, 3).count() < 10 * asked.count() < asked.count() * rows.count()
    assert df._jdf.queryExecution().optimizedPlan().toString().count("Generate") == 2  # the blocks' sides


def test_median_of_edges_searches_once(spark, monkeypatch):
    x = np.random.default_rng(3).normal(size=(60, 4))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "sample_id long, vec array<double>")
    runs = spark.sparkContext.accumulator(0)
    near = graph._near

    def counted(k, metric, radius=False):
        run = near(k, metric, radius)

        def told(a, b):
            runs.add(1)
            return run(a, b)

        return told

    monkeypatch.setattr(graph, "_near", counted)
    e = graph.build_graph(rows, 5, "median").toPandas()
    assert runs.value == 1
    assert e["w"].to_numpy() == pytest.approx(np.exp(-e["d2"] / np.median(e["d2"])))
