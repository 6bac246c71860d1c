"""Queries over whole tables and whole texts, against SQL without the cuts of the registered one."""

import random

import duckdb

import __spark_entry__ as entry
from stringweave import baselines
from stringweave.plans import registry

SMALL = "/root/testdata/sf0.001"


def _both(spark, name, sql, data=SMALL):
    con = duckdb.connect()
    con.execute(f"create view benchmark as select * from '{data}/benchmark.parquet'")
    cur = con.execute(sql)
    cols = [c[0] for c in cur.description]
    return sorted(tuple(r[c] for c in cols) for r in entry.queries()[name](spark, data).collect()), sorted(cur.fetchall())


def test_consensus_over_the_whole_pile(spark):
    got, want = _both(spark, "udaf_consensus", f"with {registry._G} select chrom, p - 1 as at, substr(seq, p, 1) as base from (select chrom, seq, unnest(range(1, len + 1)) as p from g)")
    assert got == want


def _second_round(seq):
    """The second round of one passage by strings: reads of either part chained, then both chains joined."""
    last = max(0, len(seq) - 100)
    spans = [(s, min(len(seq), s + 100)) for s in sorted({*range(0, last + 1, 25), last})]
    chains = []
    for part in ([x for x in spans if x[1] <= len(seq) * 0.65], [x for x in spans if x[0] >= len(seq) * 0.35]):
        if len(part) < 2:
            return None
        chains.append(seq[part[0][0] : part[-1][1]])
    a, b = chains
    for n in range(min(len(a), len(b)), 30, -1):
        if a.endswith(b[:n]):
            made = a + b[n:]
            return min(made, baselines.revcomp(made))
    return None


def test_second_round_of_short_passages(spark, tmp_path):
    rng = random.Random(8)
    texts = ["".join(chr(rng.randrange(33, 127)) for _ in range(n)) for n in (40, 80, 95, 98, 100, 105, 110, 120, 130, 150, 199, 230)]
    spark.createDataFrame(list(enumerate(texts, 1)), "item_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/benchmark.parquet")
    seqs = [x.encode().hex().upper().translate(str.maketrans("0123456789ABCDEF", "ACGT" * 4)) for x in texts]
    want = sorted(w for w in map(_second_round, seqs) if w)
    assert 0 < len(want) < len(seqs) and any(len(w) < 400 for w in want)
    assert sorted(r.seq for r in entry.queries()["second_round"](spark, str(tmp_path)).select("seq").collect()) == want


def test_edits_and_palindromes_of_whole_texts(spark):
    rc = registry._RC.format("seq")
    for name, sql in (
        ("fn_string_edits", f"with {registry._G} select a.chrom, levenshtein(a.seq, b.seq)::int as edits from g a join g b on b.chrom = a.chrom + 1"),
        ("fn_string_dna", f"with {registry._G} select chrom, {rc} as rc, levenshtein(seq, {rc})::int as edits, seq = {rc} as palindrome from g"),
    ):
        got, want = _both(spark, name, sql)
        assert got == want and got, name
