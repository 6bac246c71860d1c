"""The workloads of the survey: their reads and depths, and what they find."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from stringweave.operators import overlap
from stringweave.plans import workloads
from stringweave.sources import reads as R

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name, depth", [("w01", 40), ("w02", 30), ("w03", 10)])
def test_reads_cover_every_text_at_the_depth(spark, name, depth):
    assert {f"{x}_{name}" for x in ("reads", "candidates", "assemble")} <= set(entry.queries())
    genome, length, stride, error, p = workloads.WORKLOADS[name]
    g, r = genome(spark, SMALL), workloads.workload_reads(spark, SMALL, name)
    assert length / stride == depth and (error, p.k, p.x) == ((0.15, 17, 7) if name == "w03" else (0.005, 31, 15))
    whole = g.select("chrom", "len").join(r.groupBy("chrom").agg(F.min("start").alias("a"), F.max("end").alias("b")), "chrom", "left")
    assert whole.where("a is null or a > 0 or b is null or b <> len").count() == 0
    assert g.count() == g.select("chrom").distinct().count()


@pytest.mark.parametrize("name", ["reads_shotgun_documents", "kmer_count_documents_k31"])
def test_documents_against_sql(spark, name):
    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{SMALL}/documents.parquet'")
    sums = {"reads_shotgun_documents": "count(*), sum(read_id), sum(length(seq)), count(distinct seq)", "kmer_count_documents_k31": "count(*), sum(n), max(n), count(distinct kmer)"}[name]
    want = con.sql(f"select {sums} from ({entry.oracle_sql()[name]})").fetchall()[0]
    entry.queries()[name](spark, SMALL).createOrReplaceTempView("sw_test")
    assert tuple(spark.sql(f"select {sums} from sw_test").first()) == tuple(want)


@pytest.mark.parametrize("by_diagonal", [False, True])
def test_ends_of_runs_give_the_candidates_of_all_shared_kmers(spark, by_diagonal):
    repeat = "ACGTTGCATTGACCAGTACCATG"
    texts = [repeat * 4 + "GGATCCATTAGACCATNNACGTAGACCATTA", "TTGACCAGATTACA" + repeat * 2, "A" * 40, "T" * 30 + "GATTACA", "CATGGTACTGGTCAATGCAACGT" * 3, "NNNN", "AC", repeat * 4]
    rows = [(i, s, len(s)) for i, s in enumerate(texts)]
    g = spark.createDataFrame([(1, "ACGTACCATTGACCAGATTACAGGCATCGAT" * 9, 279)], "chrom long, seq string, len int")
    r = spark.createDataFrame(rows, "read_id long, seq string, len int").unionByName(R.shotgun(g, 60, 7, error=0.02).select("read_id", "seq", "len"))
    for k in (5, 11):
        assert overlap.can_chain(k, 2, None) and not overlap.can_chain(k + 1, 2, None) and not overlap.can_chain(k, 2, 9)
        both = []
        for beside in (False, True):
            km = overlap.kmers(r, k, beside=beside)
            c = overlap.candidates(overlap.build_a(km, overlap.reliable(overlap.count_kmers(km), 2, None)), r, k, by_diagonal=by_diagonal)
            both.append(sorted(map(tuple, c.collect())))
        assert both[0] == both[1] and len(both[0]) > 100


def test_numbers_are_ranks(spark):
    rows = [(i * 7919 % 1000, i % 3, None if i % 5 == 0 else "x") for i in range(500)]
    got = R.numbered(spark.createDataFrame(rows, "a long, b long, c string").repartition(7), ["b", "a"], "n").collect()
    assert sorted(r.n for r in got) == list(range(500)) and [(r.b, r.a) for r in sorted(got, key=lambda r: r.n)] == sorted((b, a) for a, b, _ in rows)
    assert R.numbered(spark.createDataFrame([], "a long"), ["a"], "n").count() == 0


def test_reads_of_a_workload_have_numbers_of_their_own(spark):
    r = workloads.workload_reads(spark, SMALL, "w01").select("read_id").collect()
    assert len({x.read_id for x in r}) == len(r) and all(x.read_id >= 0 for x in r)
