"""Reads with errors, cut in Python, against the same reads as Column expressions."""

import pytest
from pyspark.sql import functions as F

from stringweave.functions.dna import revcomp
from stringweave.sources import reads as R


@pytest.mark.parametrize("length, stride, flip, error", [(50, 7, True, 0.15), (390, 13, False, 0.005), (40, 60, True, 0.02)])
def test_damaged_reads_equal_expressions_over_every_base(spark, length, stride, flip, error):
    base = "ACGTTGCATTGACCANGTACCATGGATTACA"
    g = spark.createDataFrame([(i, (base * (1 + i))[i:], len(base) * (1 + i) - i) for i in (0, 1, 2, 9, 77)] + [(5, "", 0), (6_000_000_007, "ACG", 3)], "chrom long, seq string, len int")
    whole = R.shotgun(g, length, stride, flip)  # without errors, from expressions
    fore = F.when(F.col("rev"), revcomp("seq")).otherwise(F.col("seq"))
    hit = lambda b, i: F.when(F.pmod(F.xxhash64("read_id", i), F.lit(65536)) < int(error * 65536), F.translate(b, "ACGT", "CGTA")).otherwise(b)
    hurt = F.array_join(F.transform(F.split(fore, ""), hit), "")
    want = whole.withColumn("seq", hurt).withColumn("seq", F.when(F.col("rev"), revcomp("seq")).otherwise(F.col("seq")))
    got = R.shotgun(g, length, stride, flip, error)
    assert got.dtypes == want.dtypes and "transform" not in got._jdf.queryExecution().toString()
    a, b = (sorted(map(tuple, x.collect())) for x in (got, want))
    assert a == b and len(a) > 20 and a != sorted(map(tuple, whole.collect()))
