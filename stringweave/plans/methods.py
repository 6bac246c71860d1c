"""Queries for methods and measures away from the straight path: planted cases, look-ups, semirings, full alignment, noisy baselines."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from stringweave import assembly, baselines, graphs, measures
from stringweave.operators import contigs, matrix, overlap
from stringweave.plans.ablations import _EDGES
from stringweave.plans.registry import (
    _G, _LA, _ORD, _OWN, _SHOT, _TRUE_PAIRS, SQL, _aligned, _bench_graph, _la, _ord, _owned, _RC, bench_genome, bench_reads, query, t,
)
from stringweave.session import Scratch
from stringweave.sources import reads as R

# ---- SQL for queries of the registry, from strings alone ----

SQL["overlap_kinds"] = f"with {_EDGES} select u_end, v_end, count(*)::bigint as n, sum(suffix)::bigint as suffix from e group by 1, 2"
SQL["best_overlap_graph"] = f"with {_EDGES} select u, u_end, v from e qualify row_number() over (partition by u, u_end order by n desc, v) = 1"

# ---- reads and alignments ----


@query(f"""with {_SHOT}, odd as (
  select read_id, case when chrom % 5 = 0 then seq || 'N' when chrom % 5 = 1 then lower(seq) when chrom % 5 = 2 then substr(seq, 1, 20) else seq end as seq from reads)
select read_id, upper(seq) as seq from odd where regexp_matches(upper(seq), '^[ACGT]*$') and length(seq) >= 31""")
def clean_reads(spark, d):
    """Reads with other letters and short ones go, lower case is raised."""
    c, r = F.col("chrom") % 5, bench_reads(spark, d)
    odd = r.withColumn("seq", F.when(c == 0, F.concat("seq", F.lit("N"))).when(c == 1, F.lower("seq")).when(c == 2, F.substring("seq", 1, 20)).otherwise(F.col("seq")))
    return R.clean(odd, 31).select("read_id", "seq")


@query(f"""with {_SHOT}, x as (select read_id, seq[1:50] || 'N' || seq[52:] as seq from reads where length(seq) >= 52),
w as (select substr(seq, p, 17) as w from (select seq, unnest(range(1, length(seq) - 15)) as p from x))
select least(w, {_RC.format('w')}) as kmer, count(*)::bigint as n from w where not contains(w, 'N') group by 1""")
def kmer_count_unknown_bases(spark, d):
    """k-mers of reads with an unknown base in the middle: windows over it are none."""
    from stringweave.functions import dna

    r = bench_reads(spark, d).where(F.length("seq") >= 52)
    r = r.withColumn("seq", F.concat(F.substring("seq", 1, 50), F.lit("N"), F.expr("substring(seq, 52)")))
    return overlap.count_codes(r, 17).select(dna.unpack("kmer", 17).alias("kmer"), "n")


@query(_TRUE_PAIRS.replace("select least(u, v) as u, greatest(u, v) as v, max(n)::int as score", "select least(u, v) as u, greatest(u, v) as v, true as as_good"))
def overlap_full(spark, d):
    """True overlaps by the whole dynamic programme: whether it scores each at least as high as the exact overlap's bases."""
    full, exact = _aligned(spark, d, "full"), _aligned(spark, d, "exact")
    x = exact.select("u", "v", F.col("score").alias("bases")).join(full.select("u", "v", "score"), ["u", "v"], "left")
    return x.select("u", "v", F.coalesce(F.col("score") >= F.col("bases"), F.lit(False)).alias("as_good"))


def planted(spark, d):
    """The reads of the passages and, from every second one, the middle 60 bases as a read of its own."""
    r = bench_reads(spark, d).select("read_id", "seq", "len")
    inner = r.where((F.col("len") == 100) & (F.col("read_id") % 2 == 0)).select((F.col("read_id") + 500_000_000).alias("read_id"), F.substring("seq", 21, 60).alias("seq"))
    return Scratch(spark, "planted").keep(r.unionByName(inner.withColumn("len", F.length("seq"))))


_PLANTED = f"""{_SHOT}, every as (select read_id, seq from reads union all select read_id + 500000000, substr(seq, 21, 60) from reads where length(seq) = 100 and read_id % 2 = 0)"""


@query(f"""with {_PLANTED}, w as (select read_id, unnest([seq, {_RC.format('seq')}]) as s from every)
select distinct x.read_id from every x join w y on x.read_id <> y.read_id and contains(y.s, x.seq) and (length(x.seq) < length(y.s) or y.read_id < x.read_id)""")
def contained_planted(spark, d):
    """Reads that lie whole in another one, planted among reads of which none does."""
    return overlap.contained(assembly.string_graph(planted(spark, d), assembly.Profile.low_error())[0])


@query(f"with {_G} select least(seq, {_RC.format('seq')}) as seq, len::bigint as len from g")
def assemble_planted(spark, d):
    """Contained reads change no contig: the passages come back."""
    from stringweave.functions import dna

    return assembly.assemble(planted(spark, d)).contigs.select(dna.canonical("seq").alias("seq"), "len")


# ---- measures on cases whose answer is not the best ----


def _chains(spark, d):
    """Every passage's reads in order as a contig; each third passage runs on into the next one's first read."""
    r = bench_reads(spark, d)
    own = r.groupBy("chrom").agg(F.transform(F.array_sort(F.collect_list(F.struct("start", "read_id"))), lambda x: x["read_id"]).alias("reads"))
    nxt = own.select((F.col("chrom") - 1).alias("chrom"), F.slice("reads", 1, 1).alias("more")).where("chrom % 3 = 0")
    return own.join(nxt, "chrom", "left").select(F.col("chrom").alias("contig_id"), F.concat("reads", F.coalesce("more", F.array().cast("array<long>"))).alias("reads"))


@query(f"with {_G} select chrom as contig_id from g where chrom % 3 = 0 and chrom + 1 in (select chrom from g)")
def misassembled_planted(spark, d):
    """Chimeric contigs, planted, are those that the measure finds."""
    return measures.misassembled(measures.contig_intervals(_chains(spark, d), bench_reads(spark, d)))


@query(f"with {_G} select round(100.0 * sum(case when chrom % 2 = 0 then len else 0 end) / sum(len), 6)::double as completeness from g")
def completeness_of_half(spark, d):
    """Completeness where only every second passage has a contig."""
    at = measures.contig_intervals(_chains(spark, d).where("contig_id % 2 = 0"), bench_reads(spark, d)).where("chrom % 2 = 0")
    return measures.completeness(at, bench_genome(spark, d)).select(F.round(F.col("completeness").cast("double"), 6).alias("completeness"))


@query(f"""with {_SHOT}, p as (select chrom, b, count(*) as depth from (select chrom, unnest(range(s // 50, (e - 1) // 50 + 1)) as b from reads) group by 1, 2)
select chrom, count(*)::bigint as bins, round(avg(depth), 6) as mean, round(stddev_pop(depth) / avg(depth), 6) as cv from p group by chrom""")
def coverage_variation(spark, d):
    """How uniformly the reads cover each passage."""
    v = measures.coverage_variation(measures.coverage_profile(bench_reads(spark, d), 50))
    return v.select("chrom", "bins", F.round("mean", 6).alias("mean"), F.round("cv", 6).alias("cv"))


@query()
def contig_stage_seconds(spark, d):
    """Shares of the steps inside the contig stage."""
    a = assembly.assemble(bench_reads(spark, d))
    return spark.createDataFrame([(k, float(v)) for k, v in measures.contig_shares(a.seconds).items()], "step string, share double")


# ---- contig stage ----


@query(f"with {_ORD} select u, v from l")
def branch_mask_flags(spark, d):
    """The mask by degrees on every edge, without a list of branching vertices."""
    s = _ord(spark, d)
    return contigs.mask_flags(s, contigs.degrees(s))


@query(f"with {_ORD}, b3 as (select v from deg where deg > 3) select u, v from e where u not in (select v from b3) and v not in (select v from b3)")
def branch_mask_degree_three(spark, d):
    """A vertex may have three edges before it counts as branching."""
    s = _ord(spark, d)
    return contigs.mask(s, contigs.branching(contigs.degrees(s), 3))


def _gathered(spark, d):
    l, p = _owned(spark, d)
    n = t(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1
    return contigs.induced_by_all_gather(l, p, n, 4)


@query(f"with {_OWN} select a.owner, l.u, l.v from l join p a on a.v = l.u")
def induced_all_gather(spark, d):
    """The induced subgraph where every process has gathered the whole vertex map."""
    return _gathered(spark, d)[0]


@query(f"with {_OWN}, k as (select unnest(range(16)) as k), n as (select count(*)::bigint as n from p) select (k // 4)::bigint as bi, (k % 4)::bigint as bj, n as received from k, n")
def all_gather_cost(spark, d):
    """Owners that every process receives then."""
    return _gathered(spark, d)[1]


@query(f"""with {_OWN}, n as (select max(o_orderkey) + 1 as n from orders), h as (select v // ceil(n / 4)::bigint as b, count(*)::bigint as held from p, n group by 1),
c as (select (x.held + case when x.b = y.b then 0 else y.held end)::bigint as received from h x, h y)
select sum(received)::bigint as grid, (16 * (select count(*) from p))::bigint as all_gather, sum(received) < 16 * (select count(*) from p) as grid_wins from c""")
def look_up_costs(spark, d):
    """Entries that both look-ups move in all: the grid's against the gather of all by all."""
    l, p = _owned(spark, d)
    n = t(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1
    grid, every = (f(l, p, n, 4)[1].agg(F.sum("received").alias(name)) for f, name in ((contigs.induced_by_grid, "grid"), (contigs.induced_by_all_gather, "all_gather")))
    return grid.join(every, F.lit(True)).select("grid", "all_gather", (F.col("grid") < F.col("all_gather")).alias("grid_wins"))


@query("select conv_id * 1000000000 as contig_id, count(*)::bigint as n_reads, length(string_agg(text, '' order by turn))::bigint as len, string_agg(text, '' order by turn) as seq from conversations group by conv_id having count(*) > 1")
def spell_relational(spark, d):
    """Chains of turns spelled by ranks and an ordered concatenation, without owners."""
    c = t(spark, d, "conversations")
    rows = c.select((F.col("conv_id") * graphs.TURNS + F.col("turn")).alias("read_id"), F.col("text").alias("seq"))
    return contigs.spell_relational(graphs.conversations(c), rows)


@query(f"""with {_G}, strand as (select least(seq, {_RC.format('seq')}) as seq, len::bigint as len from g) select md5(seq) as digest, len from strand""")
def spell_relational_reads(spark, d):
    """The passages spelled by ranks from reads on both strands."""
    from stringweave.functions import dna

    s = Scratch(spark, "relational").keep(_bench_graph(spark, d))
    l = contigs.mask(s, contigs.branching(contigs.degrees(s)))
    return contigs.spell_relational(l, bench_reads(spark, d)).select(F.md5(dna.canonical("seq").cast("binary")).alias("digest"), "len")


@query(f"""with {_LA}, c as (select col, list(row order by row) as rows from la group by col), k as (select unnest(range(10))::bigint as col),
f as (select col, coalesce(rows, []) as rows from k left join c using (col)), u as (select col, rows, sum(len(rows)) over (order by col)::bigint as upto from f)
select array_to_string(list_prepend(0::bigint, list(upto order by col)), ',') as jc, md5(array_to_string(flatten(list(rows order by col)), ',')) as ir from u""")
def dcsc_to_csc(spark, d):
    """Doubly compressed columns with an empty one to plain compressed columns."""
    a = _la(spark, d).select(F.col("row").alias("u"), F.col("col").alias("v"))
    return contigs.decompressed(contigs.dcsc(a), 10).select(F.array_join("jc", ",").alias("jc"), F.md5(F.array_join("ir", ",").cast("binary")).alias("ir"))


# ---- matrix algebra ----


@query(f"with {_LA} select a.row, b.row as col, max(a.val * b.val)::bigint as val from la a join la b on a.col = b.col where a.row < b.row group by 1, 2")
def spgemm_max_times(spark, d):
    a = _la(spark, d)
    return matrix.spgemm(a, matrix.transpose(a), matrix.MAX_TIMES, upper=True)


@query(f"with {_LA} select a.row, b.row as col, bool_or(a.val > 3 and b.val > 3) as val from la a join la b on a.col = b.col where a.row < b.row group by 1, 2")
def spgemm_or_and(spark, d):
    a = matrix.apply(_la(spark, d), lambda v: v > 3)
    return matrix.spgemm(a, matrix.transpose(a), matrix.OR_AND, upper=True)


@query(f"with {_LA} select a.row, b.row as col, count(*)::bigint as val from la a join la b on a.col = b.col where a.row < b.row group by 1, 2")
def spgemm_count(spark, d):
    a = _la(spark, d)
    return matrix.spgemm(a, matrix.transpose(a), matrix.COUNT, upper=True)


@query(f"with {_LA} select a.row, a.col, (a.val * b.val)::bigint as val from la a join (select col as row, row as col, val from la) b on a.row = b.row and a.col = b.col")
def matrix_emul(spark, d):
    a = _la(spark, d)
    return matrix.emul(a, matrix.transpose(a))


@query(f"with {_LA} select row, col, val from la a where not exists (select 1 from la b where b.col = a.row and b.row = a.col)")
def matrix_ediff(spark, d):
    a = _la(spark, d)
    return matrix.ediff(a, matrix.transpose(a))


@query(f"with {_LA} select row, col, val from la where row in (select s_suppkey from supplier where s_nationkey < 9) and col in (select s_suppkey from supplier where s_suppkey % 2 = 1)")
def matrix_extract(spark, d):
    s = t(spark, d, "supplier")
    return matrix.extract(_la(spark, d), s.where("s_nationkey < 9").select(F.col("s_suppkey").alias("i")), s.where("s_suppkey % 2 = 1").select(F.col("s_suppkey").alias("i")))


@query(f"with {_LA} select row, col, val * 10 + 1 as val from la where row > col and val % 7 <> 0")
def matrix_apply_select_prune(spark, d):
    kept = matrix.select(matrix.prune(_la(spark, d), lambda v: v % 7 == 0), lambda r, c, v: r > c)
    return matrix.apply(kept, lambda v: v * 10 + 1)


# ---- noisy data in one process ----


@query()
def noisy_single_node(spark, d):
    """Noisy reads in one process: overlaps by minimizers, and the corrected assembler under a budget of seconds."""
    reads = R.shotgun(bench_genome(spark, d), 400, 40, error=0.15)
    rows = [(r.read_id, r.seq) for r in reads.select("read_id", "seq").collect()]
    out = []
    for name, run in (("minimizers", lambda: (baselines.minimizer_layout(rows), True)), ("corrected", lambda: baselines.within_budget(rows, 31, 20.0))):
        began = time.time()
        made, ended = run()
        out.append((name, time.time() - began, ended, len(made), max(map(len, made), default=0)))
    return spark.createDataFrame(out, "method string, seconds double, ended boolean, contigs int, longest int")
