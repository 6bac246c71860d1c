"""Worked examples, exact baselines and measures of the assembly methods."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from stringweave import assembly, baselines, graphs, measures
from stringweave.functions import dna
from stringweave.operators import contigs, overlap
from stringweave.plans import registry
from stringweave.sources import reads as R


def one(spark, *cols):
    return spark.range(1).select(*cols).first()


def test_reverse_complement_and_slices(spark):
    s = F.lit("ATTCG")
    assert one(spark, dna.revcomp(s), dna.revcomp(dna.revcomp(s))) == ("CGAAT", "ATTCG")
    cut = lambda lo, hi, rev: one(spark, dna.oslice(s, F.lit(lo), F.lit(hi), F.lit(rev)))[0]
    assert [cut(1, 3, False), cut(1, 3, True), cut(2, 2, True), cut(3, 1, False)] == ["TTC", "GAA", "A", ""]
    assert one(spark, dna.unpack(dna.pack(F.lit("ACGTTGCA")), 8), dna.hamming(F.lit("ACGT"), F.lit("AGGA"))) == ("ACGTTGCA", 2)


def test_concatenation_with_the_middle_read_stored_reversed():
    steps = [("AGAACT", False, 0, 1), ("CTTCAGTT", True, 7, 3), ("TGAAGAA", False, 2, 6)]
    assert contigs.spell(steps) == ("AGAACTGAAGAA", False)
    assert contigs.spell([("AGAACT", False, 0, 1), ("AACTGAAG", False, 0, 4), ("TGAAGAA", False, 2, 6)]) == ("AGAACTGAAGAA", False)
    assert contigs.spell([("ACGT", False, 3, 1)]) == ("", True)


def edge(u, v, a=1, b=0):
    return [{"u": u, "v": v, "u_end": a, "v_end": b, "pre": 1, "post": 0}, {"u": v, "v": u, "u_end": b, "v_end": a, "pre": 0, "post": 1}]


def test_cycles_and_folds():
    ring, seqs = edge(1, 2) + edge(2, 3) + edge(3, 1), {i: "AC" for i in (1, 2, 3)}
    assert contigs.walk_owner(ring, seqs) == []
    cut = contigs.walk_owner(ring, seqs, cycle="cut")
    assert [c["reads"] for c in cut] == [[1, 2, 3]] and cut[0]["cyclic"]
    fold = edge(1, 2, 1, 0) + edge(3, 2, 1, 0)
    assert [c["invalid_walk"] for c in contigs.walk_owner(fold, seqs)] == [True]
    assert contigs.walk_owner(fold, seqs, strict=True) == []


def test_lpt_bounds_forms_and_optimum():
    rng = random.Random(0)
    for _ in range(60):
        p, sizes = rng.randrange(2, 4), [rng.randrange(1, 12) for _ in range(rng.randrange(1, 8))]
        for ordered in (True, False):
            load = [0] * p
            for i, o in contigs.lpt(enumerate(sizes), p, ordered):
                load[o] += sizes[i]
            assert max(load) <= measures.lpt_bound(p, ordered) * baselines.optimal_makespan(sizes, p) + 1e-9
    for _ in range(60):
        p, runs = rng.randrange(1, 9), [(s, rng.randrange(1, 30)) for s in rng.sample(range(0, 40), 6)]
        items = [(i, s) for i, s in enumerate(s for s, c in sorted(runs, reverse=True) for _ in range(c))]
        by_heap, by_runs = [0] * p, [0] * p
        for i, o in contigs.lpt(items, p):
            by_heap[o] += items[i][1]
        for s, got in contigs.lpt_runs(runs, p):
            assert sum(got) == dict(runs)[s]
            by_runs = [a + s * g for a, g in zip(by_runs, got)]
        assert sorted(by_heap) == sorted(by_runs)


def test_xdrop_extension_against_full_dynamic_programme():
    rng = random.Random(1)

    def full(a, b):
        best, row = 0, [-j for j in range(len(b) + 1)]
        for i, x in enumerate(a, 1):
            new = [-i]
            for j, y in enumerate(b, 1):
                new.append(max(row[j - 1] + (1 if x == y else -1), row[j] - 1, new[-1] - 1))
            row = new
            best = max(best, *row)
        return best

    for _ in range(80):
        a = "".join(rng.choice("ACGT") for _ in range(rng.randrange(0, 40)))
        b = "".join(c if rng.random() > 0.1 else rng.choice("ACGT") for c in a if rng.random() > 0.05)
        score, i, j = overlap.xdrop_one_side(a.encode(), b.encode(), 1000)
        assert score == full(a, b)
        assert overlap.xdrop_one_side(a.encode(), b.encode(), 7)[0] <= score
    assert overlap.xdrop_one_side(b"ACGTAAAA", b"ACGTCCCC", 2) == (4, 4, 4)


def _pruned_score(a, b, x):
    """x-drop cell by cell."""
    live, best = {(0, 0): 0}, 0
    for d in range(1, len(a) + len(b) + 1):
        found = {}
        for i in range(max(0, d - len(b)), min(d, len(a)) + 1):
            j = d - i
            ways = [live[p] - 1 for p in ((i - 1, j), (i, j - 1)) if p in live]
            if (i - 1, j - 1) in live:
                ways.append(live[i - 1, j - 1] + (1 if a[i - 1] == b[j - 1] else -1))
            if ways and max(ways) >= best - x:
                found[i, j] = max(ways)
        best = max([best, *found.values()])
        live.update(found)
    return best


def test_pairs_extended_in_step_equal_cell_by_cell():
    rnd, a, b = random.Random(5), [], []
    for n in (0, 1, 3, 20, 60, 90, 120) * 6:
        s = "".join(rnd.choices("ACGT", k=n))
        t = "".join(c if rnd.random() > 0.15 else rnd.choice(["", "A", c + "G"]) for c in s) if rnd.random() < 0.8 else "".join(rnd.choices("ACGT", k=40))
        a.append(s.encode()), b.append(t.encode())
    for x in (4, 15):
        many = overlap.xdrop_many(a, b, x)
        assert [int(r[0]) for r in many] == [_pruned_score(s, t, x) for s, t in zip(a, b)]
        assert [tuple(r) for r in many.tolist()] == [overlap.xdrop_one_side(s, t, x) for s, t in zip(a, b)]
    s = "".join(rnd.choices("ACGT", k=9000)).encode()
    assert overlap.xdrop_one_side(s, s[:2000] + s[2400:], 600) == (8200, 9000, 8600)  # wider than the table at first
    assert overlap.xdrop_one_side(b"C" + s, s[:2500], 5) == (2499, 2501, 2500)


def test_packed_words_of_both_strands():
    s = "".join(random.Random(2).choice("ACGT") for _ in range(200))
    for k in (1, 7, 31):
        f, b = overlap.packed(s.encode(), k)
        val = lambda w: int(w.translate(str.maketrans("ACGT", "0123")), 4)
        assert f.tolist() == [val(s[i : i + k]) for i in range(201 - k)]
        assert b.tolist() == [val(baselines.revcomp(s[i : i + k])) for i in range(201 - k)]


def test_flagship_measures(spark, data):
    r = registry.bench_reads(spark, data)
    out = assembly.assemble(r)
    assert out.contigs.count() == 40 and not out.contigs.where("overrun or invalid_walk").count()
    iv = measures.contig_intervals(out.contigs, r)
    assert measures.completeness(iv, registry.bench_genome(spark, data)).first()[0] == pytest.approx(100)
    assert measures.misassembled(iv).count() == 0
    acc = measures.overlap_accuracy(out.alignments, r, 31).first()
    assert acc.common_pairs == acc.true_pairs
    assert sum(measures.stage_shares(out.seconds).values()) == pytest.approx(1)
    greedy = baselines.single_node([(x.read_id, x.seq) for x in r.collect()], 31)
    assert len(greedy) == 40


def test_noisy_reads_by_gapped_alignment(spark, data):
    g = registry.bench_genome(spark, data).where("len >= 400").limit(4)
    r = R.shotgun(g, 200, 40, error=0.01)
    p = assembly.Profile(k=17, x=15, method="xdrop", fuzz=10, min_score=60)
    aln, s = assembly.string_graph(r, p)
    acc = measures.overlap_accuracy(aln, r, 100).first()
    assert acc.common_pairs >= 0.95 * acc.true_pairs
    assert s.count() > 0


def test_traces_and_local_plan(spark, data):
    l = registry._ord_l(spark, data)
    trace = []
    got = contigs.components(l, "hook", trace=trace)
    want = baselines.union_find((r.u, r.v) for r in l.collect())
    assert {r.v: r.contig_id for r in got.collect()} == want and trace[-1] == 0
    e = contigs.to_owner(l.select(F.pmod("u", F.lit(4)).cast("int").alias("owner"), "u", "v"), 4)
    plan = contigs.reindex(e)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") >= 1


def test_fasta_round_trip(spark, tmp_path, data):
    g = registry.bench_genome(spark, data)
    R.write_fasta(g, str(tmp_path / "f"), "chrom", "seq")
    back = R.read_fasta(spark, str(tmp_path / "f"))
    assert {(r.name, r.seq) for r in back.collect()} == {(str(r.chrom), r.seq) for r in g.collect()}


def test_measures_formulas():
    assert measures.comm_model(16, 16) == {"all_gather": 256, "grid": 112}
    assert measures.efficiency(100, 18, 20, 128) == pytest.approx(100 * 18 / (20 * 128))
    assert measures.lpt_bound(3) == pytest.approx(11 / 9) and measures.lpt_bound(4, False) == 1.75
    assert np.isclose(measures.speedup(10, 2), 5)


def test_neighbour_graph_is_mutual(spark, data):
    n = graphs.neighbours(spark.read.parquet(f"{data}/embeddings.parquet"))
    assert n.where("u >= v").count() == 0 and n.count() > 200


def test_no_bound_on_copies_of_a_kmer(spark, monkeypatch):
    monkeypatch.setattr(overlap, "PIECE_ROWS", 16)
    rng = random.Random(5)
    whole = "".join(rng.choice("ACGT") for _ in range(160))
    cut = [whole[s : s + 100] for s in (0, 20, 40, 60)]
    rows = [(i, cut[i % 4] if i % 8 < 4 else baselines.revcomp(cut[i % 4])) for i in range(400)]
    r = spark.createDataFrame(rows, "read_id long, seq string").withColumn("len", F.length("seq"))
    out = assembly.assemble(r)
    assert [c.seq in (whole, baselines.revcomp(whole)) for c in out.contigs.collect()] == [True]
    full = out.alignments.select("u", "v").collect()
    assert len(full) == len(set(full)) == 400 * 399 // 2 and all(x.u < x.v for x in full)
    same = assembly.string_graph(r.where("read_id < 40"), assembly.Profile.low_error(drop_contained=False))[0]
    grouped = assembly.string_graph(r.where("read_id < 40"), assembly.Profile.low_error())[0]
    assert sorted(map(tuple, same.collect())) == sorted(map(tuple, grouped.select(*same.columns).collect()))


def test_overlap_beside_a_repeat_before_it(spark):
    rng = random.Random(6)
    made = lambda n: "".join(rng.choice("ACGT") for _ in range(n))
    word, shared = made(31), made(90)
    r = spark.createDataFrame([(1, word + made(60) + shared), (2, shared + made(60) + word)], "read_id long, seq string").withColumn("len", F.length("seq"))
    for method in ("exact", "ungapped", "xdrop"):
        aln = assembly.string_graph(r, assembly.Profile.low_error(method=method, min_score=60))[0].collect()
        assert [(a.bu, a.eu, a.bv, a.ev) for a in aln] == [(91, 181, 0, 90)], method


def test_reads_closer_than_the_fuzz_are_not_contained(spark):
    """Overhangs (left, right) of u and v: only a read that reaches beyond the other on no side goes."""
    cases = {(5, 0, 0, 5): "fore", (0, 5, 5, 0): "back", (7, 2, 2, 9): "fore", (3, 0, 3, 8): 1, (0, 0, 0, 0): 2, (4, 6, 1, 2): 2, (30, 0, 25, 5): "none", (0, 30, 4, 30): "none", (0, 15, 4, 15): 1}
    rows = [(1, 2, False, 50 + a + b, 50 + c + d, 40, a, 50 + a, c, 50 + c) for a, b, c, d in cases]
    for row, want in zip(rows, cases.values()):
        aln = spark.createDataFrame([row], overlap._ALIGNMENT)
        gone, edges = [r.read_id for r in overlap.contained(aln, 20).collect()], overlap.classify(aln, 20).where("u = 1").collect()
        assert gone == ([want] if isinstance(want, int) else []), row
        assert [(e.u_end, e.v_end) for e in edges] == {"fore": [(1, 0)], "back": [(0, 1)]}.get(want, []), row
        assert all(e.suffix == abs((row[4] - row[9]) - (row[3] - row[7]) if want == "fore" else row[8] - row[6]) for e in edges)


def test_noisy_reads_denser_than_the_fuzz_are_joined(spark):
    g = R.genome(spark.createDataFrame([(1, "".join(random.Random(3).choices("abcdefghijklmnopqrstuvwxyz ", k=700)))], "id long, text string"), "id", "text")
    r = R.shotgun(g, 200, 10, error=0.005)
    got = assembly.assemble(r, assembly.Profile.low_error(method="xdrop", fuzz=20, min_score=60)).contigs.collect()
    assert len(got) == 1 and abs(got[0].len - 1400) <= 40
