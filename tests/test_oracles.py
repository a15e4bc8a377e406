"""Registered queries against their DuckDB oracles on the smallest tables; the driver compares all of them at a larger size."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
NAMES = ["importance_warped", "greedy_select", "drift_by_threshold", "mutual_knn_edges", "base_median_loss", "win_session", "stratified_quota", "representative_weights"]


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the driver's tables")
@pytest.mark.parametrize("name", NAMES)
def test_query_equals_oracle(spark, name):
    con = duckdb.connect()
    for t in "embeddings documents events conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = entry.queries()[name](spark, SF)
    done = con.execute(entry.oracle_sql()[name])
    names = [x[0] for x in done.description]
    tidy = lambda rows, cols: sorted(tuple(round(v, 5) if isinstance(v, float) else v for _, v in sorted(zip(cols, r, strict=True))) for r in rows)
    assert sorted(df.columns) == sorted(names)
    assert tidy([tuple(r) for r in df.collect()], df.columns) == tidy(done.fetchall(), names)


def test_entry_and_registry():
    assert set(entry.oracle_sql()) <= set(entry.queries())
