"""Descriptors of a data set: sizes of reads and genome, bases touched, depth and errors."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from stringweave.functions.dna import revcomp
from stringweave.sources import reads as R

SMALL = "/root/testdata/sf0.001"


def by_hand(reads, genomes):
    under = {(r.chrom, i) for r in reads for i in range(r.start, r.end)}
    size, bases = sum(len(s) for s in genomes.values()), sum(len(r.seq) for r in reads)
    wrong = sum(a != b for r in reads for a, b in zip(r.fore, genomes[r.chrom][r.start : r.end], strict=True))
    return len(reads), bases / len(reads), bases, len({r.chrom for r in reads}), min(len(r.seq) for r in reads), max(len(r.seq) for r in reads), size, len(under), bases / size, wrong / bases


@pytest.mark.parametrize("error", [0.0, 0.15])
def test_depth_touched_bases_and_errors_are_counted(spark, error):
    genomes = {1: "ACGTACCATTGACCAGATTACAGGCATCGAT" * 20, 2: "GGATCCATTAGAC", 3: "TTGACCAGATTACA" * 30}
    g = spark.createDataFrame([(c, s, len(s)) for c, s in genomes.items()], "chrom long, seq string, len int")
    r = R.shotgun(g, 60, 7, error=error).where("chrom <> 3 and (start < 100 or start > 200)")  # bases without a read, and a chromosome
    want = by_hand(r.withColumn("fore", F.when(F.col("rev"), revcomp("seq")).otherwise(F.col("seq"))).collect(), genomes)
    got = R.profile(r, g)
    assert got.columns == ["n_reads", "mean_len", "bases", "chroms", "min_len", "max_len", "genome_bases", "touched", "depth", "error"]
    assert tuple(got.first()) == pytest.approx(want) and got.first().touched < got.first().genome_bases
    assert (want[-1] > 0.1) if error else want[-1] == 0


def test_no_reads_have_no_depth(spark):
    got = R.profile(R.shotgun(spark.createDataFrame([], "chrom long, seq string, len int"), 60, 7), spark.createDataFrame([], "chrom long, seq string, len int")).first()
    assert got.n_reads == 0 and got.depth is None and got.error is None


def test_profile_against_sql(spark):
    con = duckdb.connect()
    con.sql(f"create view benchmark as select * from '{SMALL}/benchmark.parquet'")
    want = con.sql(entry.oracle_sql()["dataset_profile"])
    got = entry.queries()["dataset_profile"](spark, SMALL)
    assert got.columns == want.columns and tuple(got.first()) == tuple(want.fetchall()[0]) and got.first().depth > 1
