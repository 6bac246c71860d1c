"""Mutual neighbours in blocks against the registered SQL, with copies, zeros and nulls."""

import duckdb
import numpy as np

import __spark_entry__ as entry
from stringweave import graphs


def test_neighbours_in_blocks_equal_sql_and_pass_on_no_pairs(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(graphs, "BLOCK", 40)
    rng = np.random.default_rng(11)
    e = rng.normal(size=(400, 6)).astype(np.float32)
    e[50:120] = e[50]  # copies
    e[200:230] = e[170:200] * 2
    rows = [(1000 - i, None if i == 399 else int(i % 2), x.tolist()) for i, x in enumerate(e)]
    spark.createDataFrame(rows, "vec_id long, label int, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.sql(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    df = entry.queries()["knn_graph"](spark, str(tmp_path))
    assert "CoGroup" in df._jdf.queryExecution().toString()
    assert sorted(map(tuple, df.collect())) == sorted(con.sql(entry.oracle_sql()["knn_graph"]).fetchall())


def test_neighbours_with_zero_and_null_vectors(spark):
    rows = [(1, 0, [1.0, 0.0]), (2, 0, [1.0, 0.1]), (3, 0, None), (4, 0, [0.5, 0.5]), (5, 1, [1.0, 1.0]), (6, 1, None), (7, 2, [1.0, 2.0]), (8, 3, [0.0, 0.0]), (9, 3, [1.0, 0.0])]
    got = {(r.u, r.v): r.sim for r in graphs.neighbours(spark.createDataFrame(rows, "vec_id long, label int, embedding array<float>")).collect()}
    assert set(got) == {(1, 2), (1, 4), (2, 4), (5, 6), (8, 9)}
    assert got[5, 6] is None and np.isnan(got[8, 9])
