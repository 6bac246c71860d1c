"""Candidates by stretches of k-mers: the rows of the k-mer matrix's product, without the matrix."""

import random
from pathlib import Path

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from stringweave import assembly
from stringweave.operators import meeting, overlap
from stringweave.session import shared_dir
from stringweave.sources import reads as R

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def odd_reads(spark):
    draw = random.Random(5)
    repeat = "ACGTTGCATTGACCAGTACCATG"
    texts = [repeat * 4 + "GGATCCATTAGACCATNNACGTAGACCATTA", "TTGACCAGATTACA" + repeat * 2, "A" * 40, "T" * 30 + "GATTACA", "CATGGTACTGGTCAATGCAACGT" * 3, "NNNN", "AC", repeat * 4, "ACGT" * 20, "ACGTACGTA" * 9, "AAAAC" * 15, "GTTTT" * 12]
    g = [(1, "ACGTACCATTGACCAGATTACAGGCATCGAT" * 9, 279), (2, "".join(draw.choice("ACGT") for _ in range(900)), 900)]
    r = spark.createDataFrame([(i, s, len(s)) for i, s in enumerate(texts)], "read_id long, seq string, len int")
    return r.unionByName(R.shotgun(spark.createDataFrame(g, "chrom long, seq string, len int"), 60, 7, error=0.02).select("read_id", "seq", "len")).localCheckpoint()


@pytest.mark.parametrize("k, by_diagonal", [(17, True), (31, True), (31, False)])
def test_meeting_gives_the_product_of_the_matrix(odd_reads, k, by_diagonal):
    km = overlap.kmers(odd_reads, k)
    want = overlap.candidates(overlap.build_a(km, overlap.reliable(overlap.count_kmers(km), 2, None)), odd_reads, k, by_diagonal=by_diagonal)
    want = want if by_diagonal else want.groupBy("u", "v").agg(F.sum("n_shared").alias("n_shared"))
    got = meeting.pairs(odd_reads, k, by_diagonal)
    assert got.columns == want.columns and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and want.count() > 600


def test_small_steps_and_blocks_change_nothing(monkeypatch, odd_reads):
    import pyarrow as pa
    import numpy as np

    rows = odd_reads.where("length(seq) >= 17").collect()
    batch = pa.RecordBatch.from_arrays([pa.array([r.read_id for r in rows]), pa.array([r.seq for r in rows])], names=["read_id", "seq"])

    def found():
        blobs = [row for part in [meeting._packed(list(meeting._chunks(batch, 17)), 1)] for row in zip(*(part.column(i).to_pylist() for i in (1, 2, 3)))]
        return [x.tolist() for x in meeting._joined([tuple(r) for r in meeting._products(*meeting._unpacked(blobs), 17, True)])]

    want = found()
    for name, value in (("STEP", 50), ("MOST", 7)):
        monkeypatch.setattr(meeting, name, value)
    assert found() == want and len(want[0]) > 1000
    assert meeting._same(np.array([5, 7], np.uint64), np.array([5, 3], np.uint64)).tolist() == [32, 1]


def test_candidates_write_no_matrix(spark):
    def kept():
        return sum(p.stat().st_size for p in Path(shared_dir(spark).removeprefix("file://")).rglob("*.parquet"))

    before = kept()
    assert entry.queries()["candidates_w01"](spark, SMALL).count() == 436_125
    assert kept() - before < 1_000_000


def test_the_string_graph_needs_no_matrix(odd_reads):
    took: dict = {}
    aln, _ = assembly.string_graph(odd_reads.where("length(seq) >= 31"), assembly.Profile.low_error(reduce=False), took)
    assert aln.count() > 0 and "DetectOverlap" in took and "CreateSpMat" not in took
