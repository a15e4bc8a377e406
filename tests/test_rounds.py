"""Greedy queries on a corpus whose share is not the rounds of their SQL."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the driver's tables")
def test_greedy_queries_take_the_rounds_of_their_sql(spark, tmp_path):
    con = duckdb.connect()
    con.execute(f"COPY (SELECT vec_id + 500 * i AS vec_id, * EXCLUDE (vec_id, i) FROM '{SF}/embeddings.parquet', range(2) t(i) WHERE i = 0 OR vec_id < 250) TO '{tmp_path}/embeddings.parquet'")
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet'")
    for name in ("greedy_select", "base_facility_location", "w6_lambda_sweep"):
        df, done = entry.queries()[name](spark, str(tmp_path)), con.execute(entry.oracle_sql()[name])
        names = [x[0] for x in done.description]
        want = sorted(tuple(dict(zip(names, r, strict=True))[c] for c in df.columns) for r in done.fetchall())
        got = sorted(map(tuple, df.collect()))
        assert len(got) == len(want) and all(x == pytest.approx(y, abs=1.5e-5) for x, y in zip(got, want, strict=True)), name
