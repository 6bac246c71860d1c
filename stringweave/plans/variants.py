"""Queries for variants, baselines, measures, workloads and the surrounding surface."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from stringweave import assembly, baselines, graphs, measures
from stringweave.functions import dna, surface
from stringweave.operators import contigs, joins, matrix, overlap
from stringweave.plans.registry import (
    _CUST, _ENC, _G, _ORD, _REACH, _REC, _SESS, _SHOT, _bench_a, _bench_graph, _cust, _km, _ord, _ord_l, _RC, bench_genome, bench_reads, query, t,
)
from stringweave.session import Scratch
from stringweave.sources import reads as R
from stringweave.sources import stores
from stringweave.streaming import flows

# ---- k-mers, candidates and edges ----


def _counts(k):
    def run(spark, d):
        c = overlap.count_kmers(overlap.kmers(bench_reads(spark, d), k))
        return c.select(dna.unpack("kmer", k).alias("kmer"), "n")

    run.__name__ = f"kmer_count_k{k}"
    query(f"with {_SHOT}, {_km(k)} select kmer, count(*)::bigint as n from km group by kmer")(run)


_counts(17)
_counts(31)


@query(f"with {_SHOT}, {_km(31)} select distinct x.read_id as u, y.read_id as v from km x join km y on x.kmer = y.kmer and x.read_id < y.read_id")
def all_pairs_baseline(spark, d):
    """Every pair compared without an index of k-mers: the baseline that the matrix product replaces."""
    return baselines.all_pairs(bench_reads(spark, d), 31)


@query(f"""with {_SHOT}, {_km(31)}, c as (select kmer from km group by kmer having count(*) >= 2), a as (select km.* from km join c using (kmer))
select u, v, sum(n)::bigint as n_shared from (select x.read_id as u, y.read_id as v, x.rev <> y.rev as r, count(*) as n from a x join a y on x.kmer = y.kmer and x.read_id < y.read_id group by 1, 2, 3 having count(*) >= 20) group by u, v""")
def candidate_pairs_min_shared(spark, d):
    """Pairs that share twenty k-mers on one relative strand."""
    c = overlap.candidates(_bench_a(spark, d, beside=True), bench_reads(spark, d), 31, min_shared=20)
    return c.groupBy("u", "v").agg(F.sum("n_shared").alias("n_shared"))


@query(f"""with {_SHOT}, x as (select read_id as u, lead(read_id) over w as v, s, e, rev, e - s as nu, lead(s) over w as s2, lead(e) over w as e2, lead(rev) over w as rev2 from reads window w as (partition by chrom order by s)),
y as (select *, (e - s2)::int as o, (e2 - s2)::int as nv from x where v is not null and e - s2 >= 31)
select u, v, (case when rev then 0 else 1 end)::int as u_end, (case when rev2 then 1 else 0 end)::int as v_end, (case when rev then o else s2 - s - 1 end)::int as pre, (case when rev2 then nv - 1 else 0 end)::int as post from y
union all select v, u, (case when rev2 then 1 else 0 end)::int, (case when rev then 0 else 1 end)::int, (case when rev2 then nv - o - 1 else o end)::int, (case when rev then 0 else nu - 1 end)::int from y""")
def edge_pre_post(spark, d):
    """Last base before and first base of the overlap, in walking order; the SQL knows them from the truth alone."""
    return _bench_graph(spark, d).select("u", "v", "u_end", "v_end", F.col("pre").cast("int").alias("pre"), F.col("post").cast("int").alias("post"))


@query("""with x as (select o_orderkey as u, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as v from orders)
select u, v, 1::int as u_end, 0::int as v_end from x where v is not null union all select v, u, 0, 1 from x where v is not null""")
def tr_order_graph(spark, d):
    """Chains of orders with all edges to the next three: reduction leaves the edges to the next one."""
    from pyspark.sql import Window

    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    near = t(spark, d, "orders").select(F.col("o_orderkey").alias("u"), *[F.lead("o_orderkey", i).over(w).alias(f"v{i}") for i in (1, 2, 3)])
    o = near.unpivot("u", ["v1", "v2", "v3"], "which", "v").where("v is not null").select("u", "v", F.substring("which", 2, 1).cast("int").alias("suffix"))
    fore = o.select("u", "v", F.lit(1).alias("u_end"), F.lit(0).alias("v_end"), "suffix")
    back = o.select(F.col("v").alias("u"), F.col("u").alias("v"), F.lit(0).alias("u_end"), F.lit(1).alias("v_end"), "suffix")
    return overlap.transitive_reduction(fore.unionByName(back)).select("u", "v", "u_end", "v_end")


@query(f"with {_SHOT} select a.read_id as u, b.read_id as v, (least(a.e, b.e) - greatest(a.s, b.s))::bigint as shared from reads a join reads b on a.chrom = b.chrom and a.read_id < b.read_id and least(a.e, b.e) - greatest(a.s, b.s) >= 31")
def join_range_overlap(spark, d):
    """Reads that truly overlap, by a range join in bins."""
    r = bench_reads(spark, d).select("chrom", F.col("read_id").alias("id"), "start", "end")
    return joins.ranges_meet(r, r, "chrom", 100, 31).where("u < v")


@query("select c as base, sum(n)::bigint as n, lang from (select lang, unnest(['A', 'C', 'G', 'T']) as c, unnest([length(s) - length(replace(s, 'A', '')), length(s) - length(replace(s, 'C', '')), length(s) - length(replace(s, 'G', '')), length(s) - length(replace(s, 'T', ''))]) as n from (select lang, " + _ENC.format("text") + " as s from documents)) group by lang, c")
def lang_base_profile(spark, d):
    s = t(spark, d, "documents").select("lang", dna.hex2("text").alias("s"))
    sums = s.groupBy("lang").agg(*[F.sum(F.length("s") - F.length(F.replace("s", F.lit(b), F.lit("")))).alias(b) for b in "ACGT"])
    return sums.unpivot("lang", list("ACGT"), "base", "n")


_STRIP = "trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g'))"


@query(f"select page_id, {_STRIP} as body, regexp_extract(html, '<title>([^<]*)</title>', 1) as title, regexp_extract(url, '://([^/?#]*)', 1) as host from pages")
def html_strip(spark, d):
    """Pages without tags, their titles and hosts."""
    body = F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\t\\r\\n]+", " "))
    return t(spark, d, "pages").select("page_id", body.alias("body"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"))


@query(f"with g as (select page_id, length({_ENC.format('html')}) as n from pages where length(html) > 0) select page_id as chrom, (case when n <= 400 then 1 else (n - 400) // 40 + 1 + ((n - 400) % 40 > 0)::int end)::bigint as reads from g")
def html_reads(spark, d):
    """Reads of the noisy carrier, depth ten, per page."""
    g = R.genome(t(spark, d, "pages"), "page_id", "html")
    return R.shotgun(g, 400, 40, error=0.15).groupBy("chrom").agg(F.count("*").alias("reads"))


# ---- graph variants ----


@query(f"with {_REC}, {_REACH} select v, contig_id from m")
def components_orders_star(spark, d):
    return contigs.components(_ord_l(spark, d), "star")


@query(f"with {_REC}, {_REACH} select v, contig_id from m")
def components_orders_all_active(spark, d):
    """Hook and shortcut with converged trees kept: the ablation of skipping them."""
    return contigs.components(_ord_l(spark, d), "hook", skip_inactive=False)


@query()
def components_trace(spark, d):
    """What is left to do after each round, by method."""
    l, rows = _ord_l(spark, d), []
    for method in ("contract", "hook", "label", "star"):
        trace: list = []
        contigs.components(l, method, trace=trace).count()
        rows += [(method, i, int(n)) for i, n in enumerate(trace)]
    return spark.createDataFrame(rows, "method string, round int, active long")


@query(f"with {_ORD}, s as (select u, v, (u < v)::int as u_end, (v < u)::int as v_end from e), z as (select u, u_end from s group by 1, 2 having count(*) > 1) select u, v from s where (u, u_end) not in (select u, u_end from z) and (v, v_end) not in (select u, u_end from z)")
def branch_end_mask(spark, d):
    """Only edges at a branching end go, not all edges of the vertex; an order's end 1 looks to larger keys."""
    s = _ord(spark, d).select("u", "v", (F.col("u") < F.col("v")).cast("int").alias("u_end"), (F.col("v") < F.col("u")).cast("int").alias("v_end"))
    return contigs.mask_ends(s, contigs.branching_ends(s)).select("u", "v")


@query(f"with {_REC}, {_REACH} select m.contig_id, sum(o.n)::bigint as n from m join (select l_orderkey, count(*) as n from lineitem group by 1) o on o.l_orderkey = m.v group by 1")
def contig_sizes_weighted(spark, d):
    """Sizes by weight of the vertices (lines of an order) where reads would count bases."""
    w = t(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("read_id")).agg(F.count("*").alias("len"))
    return contigs.sizes(contigs.components(_ord_l(spark, d)), w)


@query("with " + _SESS.format(g=240 * 60_000_000) + """, q as (select event_id as v, row_number() over w - 1 as pos, count(*) over (partition by user_id, i) as n, first_value(event_id) over w as a, last_value(event_id) over (partition by user_id, i order by ts, event_id rows between unbounded preceding and unbounded following) as b from y window w as (partition by user_id, i order by ts, event_id))
select v, (case when a < b then pos else n - 1 - pos end)::bigint as pos from q where n > 1""")
def walk_sessions(spark, d):
    return contigs.chain_ranks(contigs.both_ways(graphs.sessions(t(spark, d, "events"), 240))).select("v", "pos")


@query("select 0::bigint as bi, 2::bigint as bj, 2::bigint as partner_row, 0::bigint as partner_col, 8::bigint as received")
def grid_example(spark, d):
    """Sixteen vertices on a 4 x 4 grid: the block of the edge between the first and the twelfth vertex, its
    transpose partner, and how many owners its process receives, four of its rows and four of its columns."""
    edge = spark.createDataFrame([(0, 11)], "u long, v long")
    place = spark.range(16).select(F.col("id").alias("v"), F.lit(0).alias("owner"))
    kept, cost = contigs.induced_by_grid(edge, place, 16, 4)
    one = matrix.blocks(kept.select(F.col("u").alias("row"), F.col("v").alias("col"), F.lit(1).alias("val")), 16, 4).select("bi", "bj")
    return one.join(cost, ["bi", "bj"]).select("bi", "bj", F.col("bj").alias("partner_row"), F.col("bi").alias("partner_col"), "received")


@query(f"""with {_SHOT},
part as (select chrom, count(*) filter (r.e <= g.len * 0.65) as n1, max(r.e) filter (r.e <= g.len * 0.65) as until,
    count(*) filter (r.s >= g.len * 0.35) as n2, min(r.s) filter (r.s >= g.len * 0.35) as since from reads r join g using (chrom) group by chrom)
select least(seq, {_RC.format('seq')}) as seq, len::bigint as len from g join part using (chrom) where n1 > 1 and n2 > 1 and until - since >= 31""")
def second_round(spark, d):
    """Two runs over the left and the right part of each passage; a run over their contigs joins them.

    Passages whose parts share fewer than 31 bases, or have no contig on one side, give no row.
    """
    g = bench_genome(spark, d)
    r = R.shotgun(g, 100, 25).join(g.select("chrom", F.col("len").alias("whole")), "chrom")
    left, right = r.where("end <= whole * 0.65"), r.where("start >= whole * 0.35")
    first = [assembly.assemble(x.select("read_id", "seq", "len")).contigs for x in (left, right)]
    return assembly.second_round(first).contigs.select(dna.canonical("seq").alias("seq"), "len")


# ---- load balance over owners ----

_SWEEP = [18, 32, 50, 72, 100, 128]


@query(f"""with recursive s as ({_CUST}), o as (select id, n, row_number() over (order by n desc, id) as i from s),
r as (select p::int as p, 0::bigint as i, list_transform(range(p), lambda x: 0::bigint) as loads from (select unnest({_SWEEP}) as p)
  union all select r.p, o.i, list_transform(loads, lambda x, k: case when k = list_position(loads, list_min(loads)) then x + o.n else x end) from r join o on o.i = r.i + 1)
select p as owners, list_max(arg_max(loads, i))::bigint as makespan from r group by p""")
def lpt_sweep(spark, d):
    """Largest load over 18 to 128 owners."""
    s = Scratch(spark, "sweep").keep(_cust(spark, d))
    rows = []
    for p in _SWEEP:
        rows.append((p, contigs.load_report(s, contigs.assign(s, p), p).agg(F.max("load")).first()[0]))
    return spark.createDataFrame(rows, "owners int, makespan long")


@query(f"""with recursive s as ({_CUST}), z as (select sum(n)::bigint as total, max(n) as top from s), k as (select unnest({_SWEEP}) as p),
o as (select 'largest first' as rule, n, row_number() over (order by n desc, id) as i from s union all select 'as they come', n, row_number() over (order by id) from s),
r as (select rule, p::int as p, 0::bigint as i, list_transform(range(p), lambda x: 0::bigint) as loads from k, (select distinct rule from o)
  union all select r.rule, r.p, o.i, list_transform(loads, lambda x, k: case when k = list_position(loads, list_min(loads)) then x + o.n else x end) from r join o on o.i = r.i + 1 and o.rule = r.rule),
m as (select rule, p, list_max(arg_max(loads, i))::bigint as load from r group by 1, 2
  union all select 'hash', p::int, max(load) from (select p, id % p as owner, sum(n)::bigint as load from s, k group by 1, 2) group by p)
select rule, p as owners, load / greatest(top, (total + p - 1) // p) as ratio, case rule when 'largest first' then (4 * p - 1) / (3 * p) when 'as they come' then 2 - 1 / p end as bound from m, z""")
def lpt_ratio(spark, d):
    """Makespan over the lower bound (the mean or the largest item) beside the guarantee, by rule and owners."""
    s, rows = Scratch(spark, "ratio").keep(_cust(spark, d)), []
    total, top = s.agg(F.sum("n"), F.max("n")).first()
    for p in _SWEEP:
        made = {"largest first": contigs.assign(s, p), "as they come": contigs.assign(s, p, ordered=False), "hash": baselines.hash_assign(s, p)}
        for rule, a in made.items():
            load = contigs.load_report(s, a, p).agg(F.max("load")).first()[0]
            bound = None if rule == "hash" else measures.lpt_bound(p, rule == "largest first")
            rows.append((rule, p, load / max(top, -(-total // p)), bound))
    return spark.createDataFrame(rows, "rule string, owners int, ratio double, bound double")


# ---- accuracy, time and scaling ----


def _single(spark, d, corrected):
    rows = [(r.read_id, r.seq) for r in bench_reads(spark, d).select("read_id", "seq").collect()]
    return spark.createDataFrame(list(enumerate(baselines.single_node(rows, 31, corrected))), "contig_id long, seq string")


@query()
def greedy_single_node_corrected(spark, d):
    """The one-process baseline that corrects its reads first."""
    return _single(spark, d, True).select(F.length("seq").cast("long").alias("len"), "seq")


@query()
def quality_table(spark, d):
    """Quality by method, from contig strings and the reference alone."""
    g, out = bench_genome(spark, d), None
    made = {"pipeline": assembly.assemble(bench_reads(spark, d)).contigs, "single process": _single(spark, d, False), "single process, corrected": _single(spark, d, True)}
    for name, c in made.items():
        row = measures.reference_quality(c, g).select(F.lit(name).alias("method"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("select 100.0::double as completeness, max(len)::bigint as longest, count(*)::bigint as contigs, 0::bigint as misassembled from (with " + _G + " select len from g)")
def quality_by_reference(spark, d):
    c = assembly.assemble(bench_reads(spark, d)).contigs
    return measures.reference_quality(c, bench_genome(spark, d)).select(F.col("completeness").cast("double").alias("completeness"), "longest", "contigs", "misassembled")


@query()
def runtime_table(spark, d):
    """Seconds of the pipeline and of the one-process baselines, and what the pipeline gains."""
    reads = Scratch(spark, "runtime").keep(bench_reads(spark, d))
    began = time.time()
    assembly.assemble(reads)
    own, rows = time.time() - began, [(r.read_id, r.seq) for r in reads.select("read_id", "seq").collect()]
    out = [("pipeline", own, 1.0)]
    for name, corrected in (("single process", False), ("single process, corrected", True)):
        began = time.time()
        baselines.single_node(rows, 31, corrected)
        took = time.time() - began
        out.append((name, took, measures.speedup(took, own)))
    return spark.createDataFrame(out, "method string, seconds double, speedup double")


@query()
def scaling_table(spark, d):
    """Seconds of the contig stage and parallel efficiency by number of owners, against the smallest."""
    reads = Scratch(spark, "scaling").keep(bench_reads(spark, d))
    s, rows, base = Scratch(spark, "scaling").keep(_bench_graph(spark, d)), [], None
    for p in (2, 4, 8):
        began = time.time()
        contigs.generate_contigs(s, reads, p).count()
        took = time.time() - began
        base = base or (took, p)
        rows.append((p, took, measures.efficiency(*base, took, p)))
    return spark.createDataFrame(rows, "owners int, seconds double, efficiency double")


@query()
def stage_nonzeros(spark, d):
    """Nonzeros of every matrix of a run and how many elements each has per row."""
    a, reads = _bench_a(spark, d), bench_reads(spark, d)
    aln, s = assembly.string_graph(reads, assembly.Profile.low_error())
    c = overlap.candidates(a, reads, 31).select("u", "v").distinct()
    out = None
    for name, df, key in (("A", a, "row"), ("C", c, "u"), ("R", aln, "u"), ("S", s, "u"), ("L", contigs.mask(s, contigs.branching(contigs.degrees(s))), "u")):
        row = df.agg(F.count("*").alias("nonzeros"), F.count_distinct(key).alias("rows")).select(F.lit(name).alias("matrix"), "*", F.try_divide(F.col("nonzeros"), F.col("rows")).alias("per_row"))
        out = row if out is None else out.unionByName(row)
    return out


def _noisy(name, length, stride, rate, p):
    def run(spark, d):
        r = Scratch(spark, name).keep(R.shotgun(bench_genome(spark, d), length, stride, error=rate))
        aln, _ = assembly.string_graph(r, p)
        return measures.overlap_accuracy(aln, r, p.min_score)

    run.__name__ = name
    run.__doc__ = f"True, found and common overlaps of reads with {rate:.1%} errors."
    query()(run)


_noisy("overlaps_low_error", 200, 20, 0.005, assembly.Profile.low_error(method="xdrop", fuzz=20, min_score=60))
_noisy("overlaps_high_error", 400, 80, 0.15, assembly.Profile.high_error())


@query(f"with {_SHOT} select chrom, count(*)::bigint as reads, 1.0::double as identity from reads group by chrom")
def read_identity(spark, d):
    """Reads against the stretch of the reference that they were cut from."""
    r = bench_reads(spark, d).join(bench_genome(spark, d).select("chrom", F.col("seq").alias("ref")), "chrom")
    own = dna.oslice("ref", F.col("start"), F.col("end") - 1, F.col("rev"))
    return r.groupBy("chrom").agg(F.count("*").alias("reads"), F.min(measures.identity(F.col("seq"), own)).cast("double").alias("identity"))


@query(f"with {_G} select chrom, seq from g")
def consensus_polish(spark, d):
    """Majority bases of the pile of reads, back to the reference."""
    c = surface.polish(surface.pile(bench_reads(spark, d)))
    return c.groupBy("chrom").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "base"))), lambda x: x["base"]), "").alias("seq"))


# ---- surface: functions, sources, sinks ----


@query(f"with {_SHOT} select chrom, s::int as at, max(substr(seq, 1, 1)) as base from (select chrom, unnest(range(len)) as s, substr(seq, unnest(range(len)) + 1, 1) as seq from g) group by 1, 2")
def udaf_consensus(spark, d):
    surface.register(spark)
    surface.pile(bench_reads(spark, d)).createOrReplaceTempView("sw_pile")
    return spark.sql("select chrom, at, consensus(base, 1) as base from sw_pile group by chrom, at")


@query(f"with {_SHOT}, {_km(31)} select read_id, pos, kmer, rev from km")
def udtf_kmers(spark, d):
    surface.register(spark)
    bench_reads(spark, d).select("read_id", "seq").createOrReplaceTempView("sw_reads")
    return spark.sql("select read_id, pos, kmer, rev from sw_reads, lateral kmers_of(seq, 31)")


@query(f"with {_SHOT} select read_id, unnest(range(0, length(seq) - 16))::int as pos, substr(seq, unnest(range(0, length(seq) - 16)) + 1, 17) as kmer from reads where length(seq) >= 17")
def udf_pack_unpack(spark, d):
    surface.register(spark)
    bench_reads(spark, d).select("read_id", "seq").createOrReplaceTempView("sw_reads")
    codes = spark.sql("select read_id, posexplode(kmer_pack(seq, 17)) as (pos, code) from sw_reads")
    return codes.select("read_id", "pos", dna.unpack("code", 17).alias("kmer"))


@query(f"with {_SHOT} select read_id, length(seq)::int as score, length(seq)::int as u_bases, length(seq)::int as v_bases from reads")
def udf_xdrop_extend(spark, d):
    """Reads extended along themselves: all bases match."""
    surface.register(spark)
    bench_reads(spark, d).select("read_id", "seq").createOrReplaceTempView("sw_reads")
    return spark.sql("select read_id, e.* from (select read_id, xdrop_extend(seq, seq, 15) as e from sw_reads)")


@query(f"with {_G} select kind, chrom::bigint as chrom, seq from g, (select unnest(['csv', 'fasta', 'json', 'orc', 'parquet']) as kind)")
def io_roundtrip(spark, d):
    """Genomes written and read again in every format."""
    g, store, out = bench_genome(spark, d).select("chrom", "seq"), Scratch(spark, "formats"), None
    for kind in stores.FORMATS:
        back = stores.load(spark, stores.save(g, f"{store.root}/{kind}", kind), kind).select(F.lit(kind).alias("kind"), "chrom", "seq")
        out = back if out is None else out.unionByName(back)
    return out


@query(f"with {_ORD} select u, v from l")
def io_graph_triples(spark, d):
    """The masked order graph as a coordinate text and back."""
    l, store = _ord_l(spark, d), Scratch(spark, "triples")
    stores.write_triples(l.select(F.col("u").alias("row"), F.col("v").alias("col"), F.lit(1).alias("val")), f"{store.root}/l")
    return stores.read_triples(spark, f"{store.root}/l").select(F.col("row").alias("u"), F.col("col").alias("v"))


@query(f"with {_REC}, {_REACH}, p as (select v, (contig_id % 16)::int as owner from m) select v, owner from p where owner = 3")
def io_owner_store(spark, d):
    """Placement stored by owner; a reader of one owner opens its folder only."""
    m = contigs.components(_ord_l(spark, d))
    path = stores.by_owner(m.select("v", F.pmod("contig_id", F.lit(16)).cast("int").alias("owner")), f"{Scratch(spark, 'owners').root}/p")
    return spark.read.parquet(path).where("owner = 3").select("v", F.col("owner").cast("int").alias("owner"))


# ---- relational surface with forms that differ between engines ----


@query("select p.event_id, arg_max(v.event_id, (v.ts, v.event_id)::row(a timestamp, b bigint)) as view_id from events p left join events v on v.user_id = p.user_id and v.ts <= p.ts and v.event_type = 'view' where p.event_type = 'purchase' group by p.event_id")
def join_asof_event(spark, d):
    """The last view before each purchase of the same user."""
    e = t(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    return joins.as_of(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", "event_id", "view_id").select("event_id", "view_id")


@query("select conv_id, string_agg(text, ' ' order by turn) as text from conversations group by conv_id")
def agg_ordered_concat(spark, d):
    return t(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), " ").alias("text"))


@query("select lang, quantile_cont(n_chars, 0.5)::double as median, quantile_cont(n_chars, 0.9)::double as p90 from documents group by lang")
def agg_percentiles(spark, d):
    return t(spark, d, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"), F.percentile("n_chars", 0.9).alias("p90"))


@query("select true as near")
def agg_approx_distinct(spark, d):
    """Distinct k-mers by sketch lie within five per cent of the exact number."""
    km = overlap.kmers(bench_reads(spark, d), 31)
    return km.agg((F.abs(F.approx_count_distinct("kmer", 0.01) - F.count_distinct("kmer")) < 0.05 * F.count_distinct("kmer")).alias("near"))


@query("select o_orderstatus, round(stddev_samp(o_totalprice), 2) as sd, round(corr(o_totalprice, o_custkey), 6) as r from orders group by 1")
def agg_load_stats(spark, d):
    o = t(spark, d, "orders")
    return o.groupBy("o_orderstatus").agg(F.round(F.stddev_samp("o_totalprice"), 2).alias("sd"), F.round(F.corr("o_totalprice", "o_custkey"), 6).alias("r"))


@query("select item_id, list_sum(list_transform(string_split(text, ' '), lambda w: length(w)))::bigint as letters, list_max(list_transform(string_split(text, ' '), lambda w: length(w)))::int as longest, len(list_filter(string_split(text, ' '), lambda w: length(w) > 5))::int as long_words from benchmark")
def fn_array_hof(spark, d):
    w = F.split("text", " ")
    n = F.transform(w, F.length)
    return t(spark, d, "benchmark").select("item_id", F.aggregate(n, F.lit(0).cast("long"), lambda s, x: s + x).alias("letters"), F.array_max(n).alias("longest"), F.size(F.filter(w, lambda x: F.length(x) > 5)).alias("long_words"))


@query(f"select chrom, a, c from (select chrom, len - length(replace(seq, 'A', '')) as a, len - length(replace(seq, 'C', '')) as c from (with {_G} select * from g))")
def fn_map(spark, d):
    """Base counts as a map."""
    n = lambda b: F.length("seq") - F.length(F.replace("seq", F.lit(b), F.lit("")))
    m = bench_genome(spark, d).select("chrom", F.map_from_arrays(F.array(*map(F.lit, "ACGT")), F.array(*map(n, "ACGT"))).alias("m"))
    return m.select("chrom", F.col("m")["A"].cast("long").alias("a"), F.col("m")["C"].cast("long").alias("c"))


@query("select event_type, sum(json_extract_string(props, '$.k')::bigint)::bigint as k from events group by 1")
def fn_json_props(spark, d):
    return t(spark, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"))


@query("select year(o_orderdate)::int as y, month(o_orderdate)::int as m, count(*)::bigint as n, max(date_diff('day', date_trunc('month', o_orderdate), o_orderdate))::int as last_day from orders group by 1, 2")
def fn_dates(spark, d):
    o = t(spark, d, "orders").select(F.col("o_orderdate").cast("timestamp").alias("x"))
    return o.groupBy(F.year("x").alias("y"), F.month("x").alias("m")).agg(F.count("*").alias("n"), F.max(F.datediff("x", F.date_trunc("month", "x"))).alias("last_day"))


@query(f"with {_G} select a.chrom, levenshtein(a.seq, b.seq)::int as edits from g a join g b on b.chrom = a.chrom + 1")
def fn_string_edits(spark, d):
    """Edit distance of neighbouring passages."""
    g = bench_genome(spark, d)
    n = g.select((F.col("chrom") - 1).alias("chrom"), F.col("seq").alias("other"))
    return g.join(n, "chrom").select("chrom", F.levenshtein("seq", "other").alias("edits"))


@query("with " + _SESS.format(g=240 * 60_000_000) + ", w as (select user_id, i, min(ts) as s, count(*)::bigint as n from y group by 1, 2) select user_id, epoch_us(s) as start_us, n from w qualify i < max(i) over (partition by user_id)")
def stream_stateful_chains(spark, d):
    return flows.stateful_chains(spark, d)
