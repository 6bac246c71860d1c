"""Quality, load and cost measures."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def contig_intervals(contigs: DataFrame, truth: DataFrame) -> DataFrame:
    """Truth of the reads of every contig, in walking order."""
    at = contigs.select("contig_id", F.posexplode("reads").alias("pos", "read_id"))
    return at.join(truth.select("read_id", "chrom", "start", "end", "rev"), "read_id")


def covered(intervals: DataFrame) -> DataFrame:
    """``(chrom, covered)``: bases under the union of intervals, by a running maximum of their ends."""
    w = Window.partitionBy("chrom").orderBy("start", "end").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.coalesce(F.max("end").over(w), F.lit(0))
    return intervals.withColumn("fresh", F.greatest(F.lit(0), F.col("end") - F.greatest("start", seen))).groupBy("chrom").agg(F.sum("fresh").alias("covered"))


def completeness(intervals: DataFrame, genomes: DataFrame) -> DataFrame:
    """Share of the reference under at least one contig, in per cent."""
    c = genomes.join(covered(intervals), "chrom", "left")
    return c.agg((100.0 * F.sum(F.coalesce("covered", F.lit(0))) / F.sum("len")).alias("completeness"))


def misassembled(intervals: DataFrame, gap: int = 0) -> DataFrame:
    """Contigs that join reads of different chromosomes, or of places more than ``gap`` apart."""
    w = Window.partitionBy("contig_id").orderBy("pos")
    p = lambda c: F.lag(c).over(w)
    far = (F.greatest("start", p("start")) - F.least("end", p("end"))) > gap
    bad = (p("chrom").isNotNull() & (p("chrom") != F.col("chrom"))) | far
    return intervals.withColumn("bad", F.coalesce(bad, F.lit(False))).groupBy("contig_id").agg(F.bool_or("bad").alias("bad")).where("bad").select("contig_id")


def placed(contigs: DataFrame, genomes: DataFrame, k: int = 31) -> DataFrame:
    """Where contigs lie in a reference, without truth: ``(contig_id, chrom, start, end, rev)``.

    The first k-mer of either strand brings a contig to its places, the whole string decides.  Contigs
    that lie nowhere whole have no row; those of below k bases are left out.
    """
    from stringweave.functions.dna import pack, revcomp
    from stringweave.operators.overlap import kmers

    c = contigs.where(F.length("seq") >= k).select("contig_id", "seq")
    c = c.select("contig_id", F.lit(False).alias("rev"), "seq").unionByName(c.select("contig_id", F.lit(True).alias("rev"), revcomp("seq").alias("seq")))
    c = c.withColumn("kmer", pack(F.substring("seq", 1, k)))
    at = kmers(genomes.select(F.col("chrom").alias("read_id"), "seq"), k, both_strands=False).select(F.col("read_id").alias("chrom"), F.col("pos").alias("start"), "kmer")
    hit = c.join(at, "kmer").drop("kmer").join(genomes.select("chrom", F.col("seq").alias("ref")), "chrom")
    same = F.substring(F.col("ref"), F.col("start") + 1, F.length("seq")) == F.col("seq")
    return hit.where(same).select("contig_id", "chrom", "start", (F.col("start") + F.length("seq")).alias("end"), "rev")


def identity(a, b):
    """Share of equal bases by edit distance, over the longer of two sequences; null where both are empty."""
    return F.try_divide(F.lit(1.0) * (F.greatest(F.length(a), F.length(b)) - F.levenshtein(a, b)), F.greatest(F.length(a), F.length(b)))


def reference_quality(contigs: DataFrame, genomes: DataFrame) -> DataFrame:
    """Completeness, longest contig, contigs and misassembled contigs of error-free contigs, by their strings alone."""
    p = placed(contigs, genomes)
    lost = contigs.join(p.select("contig_id").distinct(), "contig_id", "left_anti").agg(F.count("*").alias("misassembled"))
    main = contigs.agg(F.max(F.length("seq")).cast("long").alias("longest"), F.count("*").alias("contigs"))
    return completeness(p, genomes).join(main, F.lit(True)).join(lost, F.lit(True))


def coverage_profile(intervals: DataFrame, bin_size: int) -> DataFrame:
    """Reads that touch each bin of each chromosome; the coefficient of variation tells uniformity."""
    bins = F.sequence(F.expr(f"start div {bin_size}"), F.expr(f"(end - 1) div {bin_size}"))
    return intervals.select("chrom", F.explode(bins).alias("bin")).groupBy("chrom", "bin").agg(F.count("*").alias("depth"))


def nx(contigs: DataFrame, share: float = 0.5, total: int | None = None) -> DataFrame:
    """N50 and kin: the length at which the longest contigs hold ``share`` of the bases (or of ``total``)."""
    # contigs of one length are one row, and lengths meet in two levels, so no task orders all contigs
    per = contigs.groupBy("len").agg(F.sum("len").alias("bases")).withColumn("group", F.floor(F.log2(F.greatest("len", F.lit(1)))).cast("int"))
    longer = lambda by, at: Window.partitionBy(*by).orderBy(F.desc(at)).rowsBetween(Window.unboundedPreceding, -1)
    groups = per.groupBy("group").agg(F.sum("bases").alias("held"))  # 64 rows at most
    groups = groups.select("group", F.coalesce(F.sum("held").over(longer([F.lit(1)], "group")), F.lit(0)).alias("before"), F.sum("held").over(Window.partitionBy(F.lit(1))).alias("all"))
    upto = F.col("before") + F.coalesce(F.sum("bases").over(longer(["group"], "len")), F.lit(0)) + F.col("bases")
    s = per.join(groups, "group").select("len", upto.alias("upto"), (F.col("all") if total is None else F.lit(total)).alias("all"))
    return s.where(F.col("upto") >= share * F.col("all")).agg(F.max("len").alias("nx"))


def lpt_bound(owners: int, ordered: bool = True) -> float:
    """Largest load over the best possible, as guaranteed."""
    return (4 * owners - 1) / (3 * owners) if ordered else 2 - 1 / owners


def load_summary(report: DataFrame) -> DataFrame:
    """Makespan, mean, imbalance and idle owners of a load report."""
    return report.agg(F.max("load").alias("makespan"), F.avg("load").alias("mean"), (F.max("load") / F.avg("load")).alias("imbalance"), F.sum((F.col("load") == 0).cast("long")).alias("idle"))


def comm_model(n: int, owners: int) -> dict:
    """Owner entries received in all: full all-gather against rows plus transpose partner."""
    root = math.isqrt(owners)
    return {"all_gather": n * owners, "grid": 2 * n * root - n}


def speedup(base_s: float, s: float) -> float:
    return base_s / s


def efficiency(base_s: float, base_p: int, s: float, p: int) -> float:
    """Parallel efficiency against a base of ``base_p`` workers."""
    return base_s * base_p / (s * p)


def stage_shares(seconds: dict) -> dict:
    """Share of every stage; the steps inside the contig stage are no stages."""
    stages = {k: v for k, v in seconds.items() if ":" not in k}
    total = sum(stages.values()) or 1.0
    return {k: v / total for k, v in stages.items()}


def contig_shares(seconds: dict) -> dict:
    """Share of every step inside the contig stage; walking and spelling is what the others leave."""
    steps = {k.partition(":")[2]: v for k, v in seconds.items() if k.startswith("contig:")}
    total = seconds.get("ExtractContig", 0) or 1.0
    return {k: v / total for k, v in steps.items()} | {"local assembly": 1 - sum(steps.values()) / total}


def coverage_variation(profile: DataFrame) -> DataFrame:
    """``(chrom, bins, mean, cv)``: the coefficient of variation of the depth over a chromosome's bins."""
    g = profile.groupBy("chrom").agg(F.count("*").alias("bins"), F.avg("depth").alias("mean"), F.stddev_pop("depth").alias("sd"))
    return g.select("chrom", "bins", "mean", F.try_divide("sd", "mean").alias("cv"))


def overlap_accuracy(aln: DataFrame, truth: DataFrame, at_least: int) -> DataFrame:
    """True, found and common pairs: pairs of reads whose truth overlaps by ``at_least`` bases.

    The range join meets in bins of the shortest read's length, so it stays an equi-join.
    """
    t = truth.select("read_id", "chrom", "start", "end")
    size = max(1, t.agg(F.min(F.col("end") - F.col("start"))).first()[0] or 1)
    bins = t.withColumn("bin", F.explode(F.sequence(F.expr(f"start div {size}"), F.expr(f"(end - 1) div {size}"))))
    a, b = bins.toDF("u", "chrom", "us", "ue", "bin"), bins.toDF("v", "chrom", "vs", "ve", "bin")
    real = a.join(b, ["chrom", "bin"]).where("u < v").where(F.least("ue", "ve") - F.greatest("us", "vs") >= at_least).select("u", "v").distinct()
    j = real.withColumn("t", F.lit(1)).join(aln.select("u", "v").distinct().withColumn("f", F.lit(1)), ["u", "v"], "full")
    return j.agg(F.count("t").alias("true_pairs"), F.count("f").alias("found_pairs"), F.count(F.col("t") + F.col("f")).alias("common_pairs"))
