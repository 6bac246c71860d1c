"""Queries for ablations, options away from their defaults, noisy reads and small exact baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from stringweave import assembly, baselines, graphs, measures
from stringweave.functions import dna
from stringweave.operators import contigs, overlap
from stringweave.plans.registry import _CUST, _ENC, _G, _RC, _SHOT, _bench_graph, _cust, bench_genome, bench_reads, query, t
from stringweave.session import Scratch
from stringweave.sources import reads as R

# ---- edges before reduction, from strings alone ----

#: Dovetails of reads that no other read contains: the longest one of each pair, in both directions.
_EDGES = f"""{_SHOT},
w as (select read_id, d, case when d then seq else {_RC.format('seq')} end as s from reads, (select unnest([true, false]) as d)),
inner_reads as (select distinct x.read_id from reads x join w y on x.read_id <> y.read_id and contains(y.s, x.seq) and (length(x.seq) < length(y.s) or y.read_id < x.read_id)),
o as (select * from w where read_id not in (select read_id from inner_reads)),
ends as (select read_id, d, s, unnest(range(31, length(s))) as n from o),
hit as (select x.read_id as u, y.read_id as v, x.d as ud, y.d as vd, x.n, length(y.s) - x.n as suffix
  from ends x join ends y on x.n = y.n and right(x.s, x.n) = left(y.s, y.n) and x.read_id <> y.read_id),
e as (select u, v, ud::int as u_end, (not vd)::int as v_end, n, suffix from hit qualify n = max(n) over (partition by least(u, v), greatest(u, v)))"""


@query(f"with {_EDGES} select u, v, u_end, v_end, suffix::bigint as suffix from e")
def overlap_suffix(spark, d):
    """Edges before reduction with the bases that each adds."""
    return _bench_graph(spark, d, False).select("u", "v", F.col("u_end").cast("int").alias("u_end"), F.col("v_end").cast("int").alias("v_end"), F.col("suffix").cast("long").alias("suffix"))


@query(f"with {_EDGES} select u, u_end, v, score, (row_number() over (partition by u order by u_end))::int as lid from (select u, u_end, v, n::int as score from e qualify row_number() over (partition by u, u_end order by n desc, v) = 1)")
def win_best_overlap(spark, d):
    """The longest overlap of each read end, and a number for every kept end of a read."""
    from pyspark.sql import Window

    best = overlap.best_overlap_graph(_bench_graph(spark, d, False))
    lid = F.row_number().over(Window.partitionBy("u").orderBy("u_end"))
    return best.select("u", F.col("u_end").cast("int").alias("u_end"), "v", F.col("score").cast("int").alias("score"), lid.alias("lid"))


_FORWARD = f"with {_SHOT} select substr(seq, p, 17) as kmer, count(*)::bigint as n from (select seq, unnest(range(1, length(seq) - 15)) as p from reads where length(seq) >= 17) group by 1"


@query(_FORWARD)
def kmer_count_forward(spark, d):
    """Counts of k-mers as they stand, strands apart."""
    c = overlap.count_kmers(overlap.kmers(bench_reads(spark, d), 17, both_strands=False))
    return c.select(dna.unpack("kmer", 17).alias("kmer"), "n")


@query("select true as subset, true as same_for_one")
def kmer_sample_pairs(spark, d):
    """Pairs from a fourth of the k-mers are among those of all; a share of one leaves all."""
    r = Scratch(spark, "sample").keep(bench_reads(spark, d))
    km = Scratch(spark, "sample").keep(overlap.kmers(r, 31))

    def pairs(k):
        a = overlap.build_a(k, overlap.reliable(overlap.count_kmers(k), 2, None))
        return overlap.candidates(a, r, 31).select("u", "v").distinct()

    every, some, one = pairs(km), pairs(overlap.minimizers(km, 4)), pairs(overlap.minimizers(km, 1))
    lost = some.exceptAll(every).agg((F.count("*") == 0).alias("subset"))
    return lost.join(one.exceptAll(every).unionByName(every.exceptAll(one)).agg((F.count("*") == 0).alias("same_for_one")), F.lit(True))


@query(f"""with g as (select lang, {_ENC.format('text')} as s from documents where length(text) > 1)
select lang, kmer, count(*)::bigint as n from (select lang, substr(s, p, 4) as kmer from (select lang, s, unnest(range(1, length(s) - 2)) as p from g)) group by lang, kmer""")
def lang_kmer_profile(spark, d):
    """Words of four bases by language; a look-ahead reads each text once, where substrings would count from its start."""
    docs = t(spark, d, "documents").where(F.length("text") > 1).select("doc_id", "lang", dna.hex2("text").alias("s"))
    words = docs.select("lang", F.explode(F.regexp_extract_all("s", F.lit("(?=([ACGT]{4}))"), 1)).alias("kmer"))
    return words.groupBy("lang", "kmer").agg(F.count("*").alias("n"))


# ---- options of the contig stage ----


def _lit_reads(spark):
    """Ten reads: a chain of three, a ring of three, and a hub whose three leaves the mask sets free."""
    return spark.createDataFrame([(i, "ACGT" * 2) for i in range(1, 11)], "read_id long, seq string").withColumn("len", F.length("seq"))


def _lit_graph(spark):
    pairs = [(1, 2), (2, 3), (4, 5), (5, 6), (4, 6), (7, 8), (7, 9), (7, 10)]
    both = [(u, v, 1, 0, 3, 0) for u, v in pairs] + [(v, u, 0, 1, 4, 7) for u, v in pairs]
    return spark.createDataFrame(both, "u long, v long, u_end int, v_end int, pre int, post int")


def _options(name, rows, doc, **options):
    def run(spark, d):
        out = contigs.generate_contigs(_lit_graph(spark), _lit_reads(spark), 4, **options)
        return out.select("contig_id", "n_reads", "cyclic")

    run.__name__, run.__doc__ = name, doc
    values = ", ".join(f"({c}::bigint, {n}::bigint, {str(y).lower()})" for c, n, y in rows)
    query(f"select * from (values {values}) as x(contig_id, n_reads, cyclic)")(run)


_options("contigs_cycles_dropped", [(1, 3, False)], "A ring has no root and gives no contig.")
_options("contigs_cycles_cut", [(1, 3, False), (4, 3, True)], "A ring is cut before its smallest read.", cycle="cut")
_options("contigs_singletons_kept", [(1, 3, False), (7, 1, False), (8, 1, False), (9, 1, False), (10, 1, False)], "Reads that the mask left alone stay as contigs.", singletons="keep")
_options("contigs_by_hook", [(1, 3, False)], "Components by hook and shortcut.", method="hook")
_options("contigs_by_bases", [(1, 3, False)], "Owners weighed by bases.", weight="bases")


@query()
def unreduced_ablation(spark, d):
    """Edges, contigs and the longest with and without reduction and the pruning of contained reads.

    Without reduction nearly every read has more than two edges, so the mask leaves few chains.
    """
    reads, out = Scratch(spark, "unreduced").keep(bench_reads(spark, d)), []
    for reduce in (True, False):
        for pruned in (True, False):
            a = assembly.assemble(reads, assembly.Profile.low_error(reduce=reduce, drop_contained=pruned))
            edges = a.graph.count()
            n, longest = a.contigs.agg(F.count("*"), F.max("len")).first()
            out.append((reduce, pruned, edges, n, longest))
    return spark.createDataFrame(out, "reduced boolean, contained_dropped boolean, edges long, contigs long, longest long")


@query()
def assemble_high_error(spark, d):
    """The noisy setting end to end: completeness by the truth of the reads, contigs, the longest, misassembled ones."""
    g = bench_genome(spark, d)
    reads = Scratch(spark, "noisy").keep(R.shotgun(g, 400, 40, error=0.15))
    c = assembly.assemble(reads, assembly.Profile.high_error()).contigs
    at = Scratch(spark, "noisy").keep(measures.contig_intervals(c, reads))
    main = c.agg(F.count("*").alias("contigs"), F.max("len").alias("longest"))
    bad = measures.misassembled(at, gap=400).agg(F.count("*").alias("misassembled"))
    return measures.completeness(at, g).join(main, F.lit(True)).join(bad, F.lit(True))


@query("""with recursive e as (select vec_id, label, list_transform(embedding, lambda x: x::double) as v from embeddings),
s as (select a.vec_id as u, b.vec_id as v, list_cosine_similarity(a.v, b.v) as sim from e a join e b on a.label = b.label and a.vec_id <> b.vec_id),
k as (select u, v from s qualify row_number() over (partition by u order by sim desc, v) <= 2),
p as (select a.u, a.v from k a join k b on a.u = b.v and a.v = b.u),
r(v, c) as (select distinct u, u from p union select p.v, r.c from r join p on p.u = r.v)
select v, min(c) as contig_id from r group by v""")
def knn_chain(spark, d):
    """Chains and rings of vectors that are mutually among each other's two nearest."""
    pairs = Scratch(spark, "knn").keep(graphs.neighbours(t(spark, d, "embeddings")).select("u", "v"))
    return contigs.components(contigs.both_ways(pairs))


# ---- loads ----


@query(f"with s as ({_CUST}), o as (select n, (row_number() over (order by id) - 1) % 18 as owner from s) select owner::int as owner, sum(n)::bigint as load from o group by owner")
def round_robin_baseline(spark, d):
    s = _cust(spark, d)
    return contigs.load_report(s, baselines.round_robin(s, 18), 18).select("owner", "load")


_SEGMENT = "select row_number() over (order by c_mktsegment) - 1 as i, count(*)::bigint as n from customer group by c_mktsegment"


@query(f"""with s as ({_SEGMENT}), f as (select unnest(range(32)) as f),
l as (select f, greatest(sum(case when (f >> i) & 1 = 1 then n else 0 end), sum(case when (f >> i) & 1 = 0 then n else 0 end)) as m from f, s group by f)
select min(m)::bigint as optimum, true as within_bound from l""")
def optimal_partition(spark, d):
    """The best split of the five market segments over two owners, and whether largest-first keeps its guarantee."""
    s = t(spark, d, "customer").groupBy("c_mktsegment").agg(F.count("*").alias("n")).orderBy("c_mktsegment")
    sizes = [r.n for r in s.collect()]  # one row per market segment, five by the schema
    best = baselines.optimal_makespan(sizes, 2)
    loads = [0, 0]
    for i, owner in contigs.lpt(list(enumerate(sizes)), 2):
        loads[owner] += sizes[i]
    return spark.createDataFrame([(best, max(loads) <= measures.lpt_bound(2) * best + 1e-9)], "optimum long, within_bound boolean")


@query("select n::bigint as contigs, p::int as owners, true as within from (select unnest([4287, 6411]) as n), (select unnest([18, 50, 128]) as p)")
def lpt_published_counts(spark, d):
    """Largest-first over as many contigs as the published runs had: within the guarantee of the lower bound."""
    out = []
    for n in (4287, 6411):
        items = [(i, 2 + (i * 7919) % 97) for i in range(n)]
        total = sum(s for _, s in items)
        for p in (18, 50, 128):
            loads = [0] * p
            for i, owner in contigs.lpt(items, p):
                loads[owner] += items[i][1]
            out.append((n, p, max(loads) <= measures.lpt_bound(p) * max(98, -(-total // p))))
    return spark.createDataFrame(out, "contigs long, owners int, within boolean")


# ---- surface ----


@query(f"with {_G} select chrom, length(seq) - length(replace(seq, 'A', '')) as \"A\", length(seq) - length(replace(seq, 'C', '')) as \"C\", length(seq) - length(replace(seq, 'G', '')) as \"G\", length(seq) - length(replace(seq, 'T', '')) as \"T\" from g")
def agg_pivot_bases(spark, d):
    """Bases of every chromosome as columns, by a pivot of known values."""
    b = bench_genome(spark, d).select("chrom", F.explode(F.split("seq", "")).alias("base"))
    p = b.groupBy("chrom").pivot("base", list("ACGT")).agg(F.count(F.lit(1)))
    return p.select("chrom", *[F.coalesce(c, F.lit(0)).alias(c) for c in "ACGT"])


@query(f"with {_G} select chrom, {_RC.format('seq')} as rc, levenshtein(seq, {_RC.format('seq')})::int as edits, seq = {_RC.format('seq')} as palindrome from g")
def fn_string_dna(spark, d):
    """Passages against their own other strand."""
    s = F.col("seq")
    return bench_genome(spark, d).select("chrom", dna.revcomp(s).alias("rc"), F.levenshtein(s, dna.revcomp(s)).alias("edits"), (s == dna.revcomp(s)).alias("palindrome"))
