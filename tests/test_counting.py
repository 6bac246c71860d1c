"""Counts by minimizers against plain counts."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from stringweave.functions import dna
from stringweave.operators import counting, overlap
from stringweave.plans import registry, workloads  # noqa: F401  the workloads register kmer_count_documents_k31


@pytest.mark.parametrize("k, both, flush", [(22, True, 1 << 19), (25, False, 300), (31, True, 300), (31, False, 1 << 19)])
def test_counts_by_minimizers_are_plain_counts(spark, monkeypatch, k, both, flush):
    monkeypatch.setattr(counting, "FLUSH", flush)
    monkeypatch.setattr(counting, "STEP", 700)
    monkeypatch.setattr(counting, "HELD", 900)
    rng = np.random.default_rng(7)
    seqs = ["".join(rng.choice(list("ACGT"), n)) for n in (5, k - 1, k, k + 1, 900, 4000)] + ["A" * 500, "ACGT" * 90, "ACGTN" * 30 + "A" * 40 + "T" * 40, ""]
    turn = lambda s: s[::-1].translate(str.maketrans("ACGT", "TGCA"))
    seqs += [turn(seqs[5]), seqs[4], seqs[4] + "N" + seqs[4]]
    want = Counter(min(w, turn(w)) if both else w for s in seqs for w in (s[i : i + k] for i in range(len(s) - k + 1)) if set(w) <= set("ACGT"))
    df = spark.createDataFrame([(s,) for s in seqs], "seq string").repartition(3)
    assert {r.kmer: r.n for r in counting.words(df, k, both).collect()} == want
    assert counting.words(df, k, both).count() == len(want)
    got = counting.histogram(df, k, both).groupBy("n").agg(F.sum("kmers").alias("kmers")).collect()
    assert {r.n: r.kmers for r in got} == Counter(want.values())


def test_texts_give_the_bases_of_hex2(spark):
    texts = spark.createDataFrame([("Straße ≠ street, again and again and again",), ("short",), ("again and again and again",)], "text string")
    seqs = texts.select(dna.hex2("text").alias("seq"))
    a, b = (sorted(map(tuple, x.collect())) for x in (counting.words(texts, 31, hex2=True), counting.words(seqs, 31)))
    assert a == b and len(a) > 20


def test_documents_are_counted_with_less_shuffle_than_a_row_a_kmer(spark, data):
    plan = registry.QUERIES["kmer_count_documents_k31"](spark, data)._jdf.queryExecution().toString()
    assert "stretches" in plan and "sum(n" not in plan
    texts = spark.read.parquet(f"{data}/documents.parquet").where("length(text) > 0")
    held = registry.QUERIES["kmer_histogram_k31"](spark, data).agg(F.sum(F.col("n") * F.col("kmers"))).first()[0]
    assert held == texts.select(F.sum(F.greatest(F.lit(0), 2 * F.octet_length("text") - 30))).first()[0]
    assert overlap.count_codes(texts.select(dna.hex2("text").alias("seq")), 31).count() == registry.QUERIES["kmer_histogram_k31"](spark, data).agg(F.sum("kmers")).first()[0]
