"""The whole dynamic programme, unknown bases, masks, look-ups, spelling by ranks and noisy layout on small cases."""

from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from stringweave import baselines, measures
from stringweave.operators import contigs, overlap


def plain_overlap(a, b):
    """Best score of an overlap alignment, cell by cell."""
    n, m = len(a), len(b)
    h = [[0] * (m + 1) for _ in range(n + 1)]
    for i, j in product(range(1, n + 1), range(1, m + 1)):
        h[i][j] = max(h[i - 1][j - 1] + (1 if a[i - 1] == b[j - 1] else -1), h[i - 1][j] - 1, h[i][j - 1] - 1)
    return max(max(h[n]), max(r[m] for r in h))


def test_full_overlap_against_plain_cells():
    rng = np.random.default_rng(0)
    for _ in range(60):
        a, b = ("".join(rng.choice(list("ACGT"), rng.integers(0, 25))) for _ in range(2))
        score, ba, ea, bb, eb = overlap.full_overlap(a.encode(), b.encode())
        assert score == plain_overlap(a, b)
        assert (ba == 0 or bb == 0) and (ea == len(a) or eb == len(b) or not score)
    assert overlap.full_overlap(b"TTACGTACGT", b"ACGTACGTGG") == (8, 2, 10, 0, 8)
    assert overlap.full_overlap(b"", b"A") == (0, 0, 0, 0, 0)


def test_windows_over_other_letters_are_no_kmers(spark):
    r = spark.createDataFrame([(1, "ACGTNACGA"), (2, "NNNN"), (3, "ac"), (4, "AC")], "read_id long, seq string")
    got = overlap.kmers(r, 3, both_strands=False)
    assert sorted((x.read_id, x.pos) for x in got.collect()) == [(1, 0), (1, 1), (1, 5), (1, 6)]
    counts = {x.kmer: x.n for x in overlap.count_codes(r, 3, both_strands=False).collect()}
    assert counts == {x.kmer: x.n for x in overlap.count_kmers(got).collect()} and sum(counts.values()) == 4


def test_reduction_runs_to_the_end_or_raises(spark):
    fore = [(i, j, 1, 0, j - i) for i in range(8) for j in range(i + 1, 8)]
    e = spark.createDataFrame(fore + [(v, u, 0, 1, s) for u, v, _, _, s in fore], "u long, v long, u_end int, v_end int, suffix int")
    assert sorted((r.u, r.v) for r in overlap.transitive_reduction(e).where("u < v").collect()) == [(i, i + 1) for i in range(7)]
    with pytest.raises(RuntimeError):
        overlap.transitive_reduction(e, max_rounds=1)


def test_masks_agree_and_degree_counts(spark):
    s = contigs.both_ways(spark.createDataFrame([(1, 2), (2, 3), (3, 4), (3, 5), (5, 6), (6, 7)], "u long, v long"))
    deg = contigs.degrees(s)
    pairs = lambda df: sorted((r.u, r.v) for r in df.collect())
    assert pairs(contigs.mask_flags(s, deg)) == pairs(contigs.mask(s, contigs.branching(deg))) == [(1, 2), (2, 1), (5, 6), (6, 5), (6, 7), (7, 6)]
    assert pairs(contigs.mask(s, contigs.branching(deg, 3))) == pairs(s)


def test_assignment_beyond_the_driver(spark, monkeypatch):
    items = spark.range(500).select(F.col("id").alias("contig_id"), F.lit(2).cast("long").alias("n")).unionByName(spark.range(500, 520).select(F.col("id").alias("contig_id"), (F.col("id") % 50 + 3).alias("n")))
    want = sorted(r.load for r in contigs.load_report(items, contigs.assign(items, 7), 7).collect())
    monkeypatch.setattr(contigs, "DRIVER_LPT", 10)
    monkeypatch.setattr(contigs, "RANK_ROWS", 40)
    made = contigs.assign(items, 7)
    assert made.count() == 520 and sorted(r.load for r in contigs.load_report(items, made, 7).collect()) == want
    loose = contigs.assign(items, 7, ordered=False)
    assert loose.count() == 520 and {r.owner for r in loose.collect()} <= set(range(7))


def test_owners_follow_the_bases(spark, monkeypatch):
    reads = spark.createDataFrame([(i, "ACGT" * 25) for i in range(40)], "read_id long, seq string")
    assert contigs.owners_for(reads) == contigs.LEAST_OWNERS
    monkeypatch.setattr(contigs, "OWNER_BASES", 100)
    assert contigs.owners_for(reads) == 40


def test_look_ups_move_what_the_formula_says(spark):
    place = spark.range(16).select(F.col("id").alias("v"), F.lit(0).alias("owner"))
    edge = spark.createDataFrame([(0, 11)], "u long, v long")
    moved = [f(edge, place, 16, 4)[1].agg(F.sum("received")).first()[0] for f in (contigs.induced_by_grid, contigs.induced_by_all_gather)]
    assert moved == [measures.comm_model(16, 16)["grid"], measures.comm_model(16, 16)["all_gather"]]
    assert contigs.induced_by_all_gather(edge, place, 16, 4)[0].count() == 1


def test_shares_of_the_contig_stage():
    got = measures.contig_shares({"ExtractContig": 10.0, "contig:components": 4.0, "contig:induced subgraph": 2.0, "Alignment": 5.0})
    assert got == {"components": 0.4, "induced subgraph": 0.2, "local assembly": pytest.approx(0.4)}
    assert set(measures.stage_shares({"ExtractContig": 10.0, "contig:components": 4.0})) == {"ExtractContig"}


def test_length_statistics_in_two_levels(spark):
    rng = np.random.default_rng(1)
    lens = [int(x) for x in rng.integers(1, 2000, 300)]
    df = spark.createDataFrame([(i, n) for i, n in enumerate(lens)], "contig_id long, len long")
    for share in (0.1, 0.5, 0.9):
        total, upto = sum(lens), 0
        for n in sorted(lens, reverse=True):
            upto += n
            if upto >= share * total:
                break
        assert measures.nx(df, share).first().nx == n


def test_noisy_layout_of_clean_reads():
    rng = np.random.default_rng(2)
    genome = "".join(rng.choice(list("ACGT"), 900))
    reads = [(i, genome[a : a + 300]) for i, a in enumerate(range(0, 601, 100))]
    reads = [(i, s if i % 2 else baselines.revcomp(s)) for i, s in reads]
    assert baselines.minimizer_layout(reads) in ([genome], [baselines.revcomp(genome)])
    assert baselines.within_budget(reads, 31, 60.0)[1] and not baselines.within_budget(reads, 31, 0.0)[1]
