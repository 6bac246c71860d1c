"""Options of the contig stage away from their defaults, and the small exact baselines."""

from stringweave import baselines, measures
from stringweave.operators import contigs
from stringweave.plans import ablations


def _made(spark, **options):
    out = contigs.generate_contigs(ablations._lit_graph(spark), ablations._lit_reads(spark), 4, **options)
    return sorted((r.contig_id, r.n_reads, r.cyclic) for r in out.select("contig_id", "n_reads", "cyclic").collect())


def test_rings_and_lone_reads_by_option(spark):
    assert _made(spark) == [(1, 3, False)]
    assert _made(spark, cycle="cut", singletons="keep") == [(1, 3, False), (4, 3, True), *[(i, 1, False) for i in (7, 8, 9, 10)]]


def test_lone_reads_keep_their_bases(spark):
    out = contigs.generate_contigs(ablations._lit_graph(spark), ablations._lit_reads(spark), 4, singletons="keep").where("n_reads = 1").collect()
    assert {(r.seq, r.len, tuple(r.reads)) for r in out} == {("ACGTACGT", 8, (i,)) for i in (7, 8, 9, 10)}


def test_no_graph_gives_no_contig(spark):
    empty = ablations._lit_graph(spark).limit(0)
    for single in ("drop", "keep"):
        assert contigs.generate_contigs(empty, ablations._lit_reads(spark), 4, singletons=single).count() == 0


def test_largest_first_keeps_its_guarantee_against_the_optimum():
    for sizes in ([7, 5, 4, 4, 3], [9, 9, 1, 1, 1, 1], [3, 3, 2, 2, 2], [5]):
        for owners in (1, 2, 3):
            loads = [0] * owners
            for i, o in contigs.lpt(list(enumerate(sizes)), owners):
                loads[o] += sizes[i]
            best = baselines.optimal_makespan(sizes, owners)
            assert best <= max(loads) <= measures.lpt_bound(owners) * best + 1e-9
