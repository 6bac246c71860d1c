"""Operators whose cost must follow their rows, and tables of other shapes."""

import time

import numpy as np
from pyspark.sql import functions as F

from stringweave import assembly
from stringweave.functions import dna
from stringweave.operators import contigs, matrix, overlap
from stringweave.sources import reads as R


def test_compressed_columns_of_a_long_chain_in_linear_time(spark):
    n = 300_000
    one = spark.range(n - 1).select(F.lit(3).alias("owner"), F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    e = one.unionByName(one.select("owner", F.col("v").alias("u"), F.col("u").alias("v")))
    outside = spark.createDataFrame([(3, 5, n + 9), (4, 7, 7)], "owner int, u long, v long")
    began = time.time()
    got = {r.owner: r for r in contigs.csc(e.unionByName(outside)).collect()}
    assert time.time() - began < 40
    jc, ir = np.array(got[3].jc), np.array(got[3].ir)
    assert got[4].jc == [0, 1] and got[4].ir == [0] and len(jc) == n + 1 and jc[-1] == len(ir) == 2 * n - 2
    assert ir[:3].tolist() == [1, 0, 2] and ir[jc[1000] : jc[1001]].tolist() == [999, 1001]


def test_streams_read_tables_that_are_folders(spark, data, tmp_path):
    from stringweave.streaming import flows

    rows = {}
    for name in ("documents", "benchmark"):
        table = spark.read.parquet(f"{data}/{name}.parquet")
        table.repartition(3).write.parquet(f"{tmp_path}/{name}.parquet")
        rows[name] = table.count()
    assert flows.drain(flows.stream(spark, str(tmp_path), "documents").select("doc_id"), "append").count() == rows["documents"]
    whole, parts = (sorted(map(tuple, flows.static_candidates(spark, d).collect())) for d in (data, str(tmp_path)))
    assert whole == parts and whole


def test_overlaps_by_a_repeat_that_both_ends_beat_go(spark):
    rng = np.random.default_rng(5)
    cut = lambda n: "".join(rng.choice(list("ACGT"), n))
    rows = []
    for n in (45, 84):  # shared by the end of a passage's read 300-400 and the beginning of another one's read 250-350
        shared = cut(n)
        rows += [cut(400 - n) + shared + cut(140), cut(250) + shared + cut(250 - n)]
    g = spark.createDataFrame([(i, s, len(s)) for i, s in enumerate(rows)], "chrom long, seq string, len int")
    c = assembly.assemble(R.shotgun(g, 100, 25)).contigs.select(dna.canonical("seq").alias("seq"))
    assert sorted(r.seq for r in c.collect()) == sorted(r.seq for r in g.select(dna.canonical("seq").alias("seq")).collect())


def test_ties_and_edges_best_at_one_end_stay(spark):
    both = lambda u, v, s: [(u, v, 1, 0, s), (v, u, 0, 1, s)]
    rows = both(1, 2, 90) + both(3, 4, 80) + both(1, 4, 50) + both(5, 6, 70) + both(5, 7, 70) + both(1, 8, 40)
    e = spark.createDataFrame(rows, "u long, v long, u_end int, v_end int, score int")
    left = {(r.u, r.v) for r in overlap.drop_weaker(e).collect()}
    assert left == {(u, v) for u, v, *_ in rows} - {(1, 4), (4, 1)}


def test_products_in_tiles_equal_joined_ones_and_shuffle_no_product(spark, monkeypatch):
    monkeypatch.setattr(matrix, "TILE", 64)
    rng = np.random.default_rng(3)
    e = [(int(r), int(k), int(v)) for r, k, v in zip(rng.integers(0, 200, 3000), rng.integers(0, 9, 3000), rng.integers(-9, 9, 3000))]
    a = spark.createDataFrame([*e, (7, None, 3)], "row long, col long, val long")
    dense = a.groupBy("row", "col").agg(F.max("val").alias("val"))
    for m in (a, dense):  # elements given more than once, and once
        for sr in (matrix.PLUS_TIMES, matrix.MIN_PLUS, matrix.MAX_TIMES, matrix.COUNT, matrix.OR_AND):
            one = matrix.apply(m, lambda v: v > 3) if sr is matrix.OR_AND else m
            x, y = one.select("row", F.col("col").alias("k"), F.col("val").alias("x")), one.select(F.col("col").alias("k"), F.col("row").alias("col"), F.col("val").alias("y"))
            for upper in (False, True):
                got = matrix.spgemm(one, matrix.transpose(one), sr, upper)
                assert "CoGroup" in got._jdf.queryExecution().toString()
                assert got.dtypes == matrix._joined(x, y, sr, upper).dtypes
                assert sorted(map(tuple, got.collect())) == sorted(map(tuple, matrix._joined(x, y, sr, upper).collect()))
    lone = a.withColumn("val", F.when(F.col("val") > 0, F.col("val")))
    assert "CoGroup" not in matrix.spgemm(lone, matrix.transpose(lone))._jdf.queryExecution().toString()


def test_example_tree_over_orders_of_a_customer(spark, tmp_path):
    from stringweave.plans import registry

    rows = [(i, 5) for i in range(1, 9)] + [(i, 6) for i in range(11, 17)] + [(20, 7)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    got = sorted(map(tuple, registry.QUERIES["branch_example"](spark, str(tmp_path)).collect()))
    assert got == [(1, 1), (2, 1), (4, 4), (5, 4), (6, 4), (7, 7), (8, 7)] + [(i, 11) for i in range(11, 17)]


def test_first_order_of_a_customer_does_not_hang_on_the_order_of_shuffled_rows(spark, data):
    import re

    import duckdb

    import __spark_entry__ as entry

    got = entry.queries()["join_lateral_top1"](spark, data)
    windows = re.findall(r"row_number\(\) windowspecdefinition\(([^)]*)", got._jdf.queryExecution().optimizedPlan().toString())
    assert windows and all("o_totalprice" in w and "o_orderkey" in w for w in windows)
    con = duckdb.connect()
    for name in ("customer", "orders"):
        con.sql(f"create view {name} as select * from '{data}/{name}.parquet'")
    assert sorted(map(tuple, got.collect())) == sorted(con.sql(entry.oracle_sql()["join_lateral_top1"]).fetchall())
