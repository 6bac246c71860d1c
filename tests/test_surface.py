"""Joins, components, stores, functions and measures that surround the assembly, against plain Python."""

import random

from pyspark.sql import functions as F

from stringweave import assembly, baselines, measures
from stringweave.functions import dna, surface
from stringweave.operators import contigs, joins
from stringweave.session import Scratch
from stringweave.sources import reads as R
from stringweave.sources import stores


def test_as_of_takes_the_last_row_not_after(spark):
    left = spark.createDataFrame([(1, 5, 10), (2, 5, 3), (3, None, 9), (4, 6, None), (5, 5, 7), (5, 5, 7)], "i long, k long, t long")
    right = spark.createDataFrame([(5, 4, 100), (5, 7, 101), (5, 7, 102), (5, 11, 103), (6, 1, 104), (None, 1, 105)], "k long, t long, id long")
    got = sorted(((r.i, r.hit) for r in joins.as_of(left, right, "k", "t", "id", "hit").collect()), key=str)
    assert got == [(1, 102), (2, None), (3, None), (4, None), (5, 102), (5, 102)]
    assert joins.as_of(left, right.limit(0), "k", "t", "id", "hit").where("hit is null").count() == 6


def test_ranges_meet_once(spark):
    rng = random.Random(1)
    rows = [(i, rng.randrange(2), s := rng.randrange(200), s + rng.randrange(60)) for i in range(120)]
    df = spark.createDataFrame(rows, "id long, chrom long, start long, end long")
    for size in (7, 50, 1000):
        got = sorted(tuple(r) for r in joins.ranges_meet(df, df, "chrom", size, 5).where("u < v").collect())
        want = sorted((a[0], b[0], n) for a in rows for b in rows if a[0] < b[0] and a[1] == b[1] and (n := min(a[3], b[3]) - max(a[2], b[2])) >= 5)
        assert got == want


def test_components_by_every_method(spark):
    rng = random.Random(2)
    for n, m in ((30, 20), (60, 90), (2, 1)):
        edges = [(rng.randrange(n), rng.randrange(n)) for _ in range(m)] + [(i, i + 1) for i in range(100, 112)]
        l = contigs.both_ways(spark.createDataFrame([e for e in edges if e[0] != e[1]], "u long, v long"))
        want = baselines.union_find([e for e in edges if e[0] != e[1]])
        for method in ("contract", "hook", "label", "star"):
            assert {r.v: r.contig_id for r in contigs.components(l, method).collect()} == want, method


def test_correction_repairs_errors_and_leaves_clean_reads(spark):
    rng = random.Random(3)
    whole = "".join(rng.choice("ACGT") for _ in range(400))
    clean = [(i, whole[s : s + 100]) for i, s in enumerate(range(0, 301, 10))]
    assert baselines.single_node(clean, 31, corrected=True) == baselines.single_node(clean, 31) == [whole]
    bad = [(i, s if i != 12 else s[:50] + {"A": "C"}.get(s[50], "A") + s[51:]) for i, s in clean]
    assert baselines.single_node(bad, 31, corrected=True) == [whole]


def test_functions_for_sql_users(spark):
    surface.register(spark)
    assert spark.sql("select kmer_pack('ACGTT', 3), kmer_pack('AC', 3), kmer_pack(cast(null as string), 3)").first()[:] == ([6, 27, 47], [], None)
    assert [tuple(r) for r in spark.sql("select * from kmers_of('ACGTT', 3)").collect()] == [(0, "ACG", False), (1, "ACG", True), (2, "AAC", True)]
    assert spark.sql("select xdrop_extend('ACGTACGT', 'ACGTTCGT', 3) as e").first().e.score == 6
    assert spark.sql("select consensus(b, 1) from values ('C'), ('A'), ('C'), ('A') as t(b)").first()[0] == "A"


def test_second_round_joins_contigs(spark):
    rng = random.Random(4)
    whole = "".join(rng.choice("ACGT") for _ in range(600))
    g = spark.createDataFrame([(1, whole, 600)], "chrom long, seq string, len int")
    r = Scratch(spark, "test").keep(R.shotgun(g, 100, 25))
    halves = [assembly.assemble(x).contigs for x in (r.where("end <= 400"), r.where("start >= 200"))]
    out = assembly.second_round(halves).contigs.collect()
    assert len(out) == 1 and out[0].seq in (whole, baselines.revcomp(whole))


def test_stores_round_trip(spark, tmp_path):
    g = spark.createDataFrame([(1, "ACGT"), (2, "TTTT")], "chrom long, seq string")
    for kind in stores.FORMATS:
        back = stores.load(spark, stores.save(g, f"{tmp_path}/{kind}", kind), kind)
        assert sorted(map(tuple, back.collect())) == [(1, "ACGT"), (2, "TTTT")]
    (tmp_path / "x.fq").write_text("@r1\nACGT\n+\nIIII\n@r2\nTT\n+\nII\n")
    assert sorted(map(tuple, stores.read_fastq(spark, f"{tmp_path}/x.fq").collect())) == [("r1", "ACGT", "IIII"), ("r2", "TT", "II")]
    stores.write_graph(spark.createDataFrame([(1, 1, 2, 0, 3), (2, 0, 1, 1, 3)], "u long, u_end int, v long, v_end int, score int"), g.withColumnRenamed("chrom", "read_id"), f"{tmp_path}/graph")
    assert sorted(r.value for r in spark.read.text(f"{tmp_path}/graph").collect()) == ["L\t1\t1\t2\t0\t3", "S\t1\t4", "S\t2\t4"]


def test_polish_and_places(spark):
    g = spark.createDataFrame([(1, "ACGTACCTGA" * 5 + "GGATTCCA", 58)], "chrom long, seq string, len int")
    piled = surface.pile(R.shotgun(g, 30, 7))
    assert "".join(r.base for r in surface.polish(piled).orderBy("at").collect()) == "ACGTACCTGA" * 5 + "GGATTCCA"
    c = spark.createDataFrame([(7, "CTGA" + "GGATTCCA"), (8, "TGGAATCCTCAG"), (9, "AAAAAAAAAAAA")], "contig_id long, seq string")
    assert sorted(tuple(r) for r in measures.placed(c, g, 9).collect()) == [(7, 1, 46, 58, False), (8, 1, 46, 58, True)]
    assert spark.range(1).select(measures.identity(F.lit("ACGT"), F.lit("AGGT")), dna.revcomp(F.lit("AC"))).first()[:] == (0.75, "GT")
