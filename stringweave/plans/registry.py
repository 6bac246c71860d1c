"""Queries over the given tables, with the SQL that an independent engine runs beside them."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from stringweave import assembly, baselines, graphs, measures
from stringweave.functions import dna
from stringweave.operators import contigs, counting, matrix, overlap
from stringweave.plans.coverage import COVERAGE, SPARK
from stringweave.session import Scratch
from stringweave.sources import reads as R
from stringweave.streaming import flows

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def t(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


# ---- DNA functions and reads ----

_ENC = "translate(hex(encode({})), '0123456789ABCDEF', 'ACGTACGTACGTACGT')"
_RC = "reverse(translate({}, 'ACGT', 'TGCA'))"
_G = f"g as (select item_id as chrom, {_ENC.format('text')} as seq, length({_ENC.format('text')}) as len from benchmark where length(text) > 0)"
_SHOT = f"""{_G},
st as (select chrom, len, seq, unnest(list_distinct(list_append(range(0, greatest(0, len - 100) + 1, 25), greatest(0, len - 100)))) as s from g),
rd as (
  select chrom * 1000000000 + s as read_id, chrom, s, least(len, s + 100) as e, substr(seq, s + 1, least(len, s + 100) - s) as fwd,
    instr('13579bdf', substr(md5(chrom::varchar || ':' || s::varchar), 1, 1)) > 0 as rev from st),
reads as (select read_id, chrom, s, e, rev, case when rev then {_RC.format('fwd')} else fwd end as seq from rd)"""


def bench_genome(spark, d):
    return R.genome(t(spark, d, "benchmark"), "item_id", "text")


def bench_reads(spark, d):
    return R.shotgun(bench_genome(spark, d), 100, 25)


@query(f"select doc_id, md5({_ENC.format('text')}) as digest, length({_ENC.format('text')})::bigint as len from documents")
def dna_encode(spark, d):
    s = dna.hex2("text")
    return t(spark, d, "documents").select("doc_id", F.md5(s.cast("binary")).alias("digest"), F.length(s).cast("long").alias("len"))


@query(f"""select item_id, array_to_string(list_transform(string_split(text, ' '), lambda w: translate(upper(substr(md5(w), 1, 16)), '0123456789ABCDEF', 'ACGTACGTACGTACGT')), '') as seq from benchmark""")
def dna_encode_words(spark, d):
    return t(spark, d, "benchmark").select("item_id", dna.word16("text").alias("seq"))


@query(f"select chrom, {_RC.format('seq')} as rc from (with {_G} select * from g)")
def dna_revcomp(spark, d):
    return bench_genome(spark, d).select("chrom", dna.revcomp("seq").alias("rc"))


@query(f"with {_G} select chrom, substr(seq, 6, 20) as fore, {_RC.format('substr(seq, 6, 20)')} as back, round(length(regexp_replace(seq, '[^GC]', '', 'g')) / len, 6) as gc from g")
def dna_slice(spark, d):
    g = bench_genome(spark, d)
    cut = lambda rev: dna.oslice("seq", F.lit(5), F.lit(24), F.lit(rev))
    return g.select("chrom", cut(False).alias("fore"), cut(True).alias("back"), F.round(dna.gc_content("seq"), 6).alias("gc"))


@query(f"with {_SHOT} select read_id, chrom, s::int as start, e::int as \"end\", rev, seq from reads")
def reads_shotgun(spark, d):
    return bench_reads(spark, d).select("read_id", "chrom", "start", "end", "rev", "seq")


@query(f"""with {_SHOT},
sizes as (select sum(len)::bigint as genome_bases from g),
seen as (select s, e, max(e) over (partition by chrom order by s, e rows between unbounded preceding and 1 preceding) as upto from reads),
under as (select sum(greatest(0, e - greatest(s, coalesce(upto, 0))))::bigint as touched from seen),
off as (select sum(hamming(case when rev then {_RC.format('reads.seq')} else reads.seq end, substr(g.seq, s + 1, e - s)))::bigint as wrong from reads join g using (chrom)),
told as (select count(*)::bigint as n_reads, avg(length(seq)) as mean_len, sum(length(seq))::bigint as bases, count(distinct chrom)::bigint as chroms, min(length(seq))::int as min_len, max(length(seq))::int as max_len from reads)
select n_reads, mean_len, bases, chroms, min_len, max_len, genome_bases, touched, bases / genome_bases as depth, wrong / bases as error from told, sizes, under, off""")
def dataset_profile(spark, d):
    return R.profile(bench_reads(spark, d), bench_genome(spark, d))


# ---- k-mers and matrices ----

_KM = "km as (select read_id, p::int as pos, least(w, {rc}) as kmer, least(w, {rc}) <> w as rev from (select read_id, p - 1 as p, substr(seq, p, {k}) as w from (select read_id, seq, unnest(range(1, length(seq) - {k2})) as p from reads where length(seq) >= {k})))"


def _km(k):
    return _KM.format(rc=_RC.format("w"), k=k, k2=k - 2)


def _doc_hist(k):
    return f"""
with g as (select {_ENC.format('text')} as seq from documents where length(text) > 0),
w as (select substr(seq, p, {k}) as w from (select seq, unnest(range(1, length(seq) - {k - 2})) as p from g where length(seq) >= {k})),
c as (select least(w, {_RC.format('w')}) as kmer, count(*)::bigint as n from w group by 1)
select n, count(*)::bigint as kmers from c group by n"""


def _histogram(spark, d, k):
    if counting.fits(k):
        return counting.histogram(t(spark, d, "documents").where("length(text) > 0").select("text"), k, hex2=True).groupBy("n").agg(F.sum("kmers").alias("kmers"))
    return overlap.count_codes(R.genome(t(spark, d, "documents"), "doc_id", "text"), k).groupBy("n").agg(F.count("*").alias("kmers"))


@query(_doc_hist(17))
def kmer_histogram_k17(spark, d):
    return _histogram(spark, d, 17)


@query(_doc_hist(31))
def kmer_histogram_k31(spark, d):
    return _histogram(spark, d, 31)


@query(f"with {_SHOT}, {_km(31)} select kmer, count(*)::bigint as n from km group by kmer having count(*) between 2 and 8")
def kmer_reliable(spark, d):
    c = overlap.reliable(overlap.count_kmers(overlap.kmers(bench_reads(spark, d), 31)))
    return c.select(dna.unpack("kmer", 31).alias("kmer"), "n")


_A = f"{_SHOT}, {_km(31)}, ok as (select kmer from km group by kmer having count(*) >= 2), a as (select km.* from km join ok using (kmer))"


def _bench_a(spark, d, beside=False):
    km = overlap.kmers(bench_reads(spark, d), 31, beside=beside)
    return overlap.build_a(km, overlap.reliable(overlap.count_kmers(km), 2, None))


@query(f"with {_A} select read_id as row, kmer as col, pos, rev from a")
def kmer_matrix_A(spark, d):
    return _bench_a(spark, d).select("row", dna.unpack("col", 31).alias("col"), "val.pos", "val.rev")


@query(f"with {_A} select kmer as row, read_id as col, pos from a")
def kmer_matrix_T(spark, d):
    return matrix.transpose(_bench_a(spark, d)).select(dna.unpack("row", 31).alias("row"), "col", "val.pos")


_PAIR = f"""{_A},
pr as (
  select x.read_id as u, y.read_id as v, x.rev <> y.rev as rev, x.pos as pu, case when x.rev <> y.rev then length(r.seq) - 31 - y.pos else y.pos end as pv
  from a x join a y on x.kmer = y.kmer and x.read_id < y.read_id join reads r on r.read_id = y.read_id)"""


@query(f"with {_PAIR} select u, v, count(*)::bigint as n_shared from pr group by u, v")
def candidate_pairs(spark, d):
    c = overlap.candidates(_bench_a(spark, d, beside=True), bench_reads(spark, d), 31)
    return c.groupBy("u", "v").agg(F.sum("n_shared").alias("n_shared"))


@query(f"with {_PAIR} select u, v, rev, min((pu, pv)::row(a int, b int)).a as pu1, min((pu, pv)::row(a int, b int)).b::int as pv1, max((pu, pv)::row(a int, b int)).a as pu2 from pr group by u, v, rev")
def candidate_seeds(spark, d):
    c = overlap.candidates(_bench_a(spark, d, beside=True), bench_reads(spark, d), 31)
    return c.select("u", "v", "rev", F.col("seed1.pu").alias("pu1"), F.col("seed1.pv").alias("pv1"), F.col("seed2.pu").alias("pu2"))


def _aligned(spark, d, method):
    return assembly.string_graph(bench_reads(spark, d), assembly.Profile.low_error(method=method))[0]


#: Pairs of reads whose strings overlap at an end, found by comparing prefixes and suffixes.
_TRUE_PAIRS = f"""with {_SHOT},
w as (select read_id, d, case when d then {_RC.format('seq')} else seq end as s from reads, (select unnest([true, false]) as d)),
suf as (select read_id, d, unnest(range(31, length(s) + 1)) as n, s from w),
hit as (select x.read_id as u, y.read_id as v, x.n from suf x join suf y on x.n = y.n and right(x.s, x.n) = left(y.s, y.n) and x.read_id <> y.read_id)
select least(u, v) as u, greatest(u, v) as v, max(n)::int as score from hit group by 1, 2"""


@query(_TRUE_PAIRS)
def overlap_exact(spark, d):
    return _aligned(spark, d, "exact").select("u", "v", "score")


@query(_TRUE_PAIRS)
def overlap_xdrop_ungapped(spark, d):
    a = _aligned(spark, d, "ungapped")
    whole = F.col("score") == F.col("eu") - F.col("bu")
    return overlap.classify(a.where(whole)).where("u < v").join(a.select("u", "v"), ["u", "v"], "left_semi").select("u", "v", "score").distinct()


@query()
def overlap_xdrop(spark, d):
    return measures.overlap_accuracy(_aligned(spark, d, "xdrop"), bench_reads(spark, d), 31)


@query("select doc_id, item_id from documents, benchmark where contains(documents.text, benchmark.text)")
def contained_passages(spark, d):
    """Passages inside documents: shared 31-mers of the encoded texts bring pairs together, the text decides."""
    docs, items = t(spark, d, "documents").select("doc_id", "text"), t(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"))
    g = lambda df, key: R.genome(df, key, "text").withColumnRenamed("chrom", "read_id")
    first = items.select("item_id", dna.hex2("passage").alias("s")).select("item_id", dna.pack(F.substring("s", 1, 31)).alias("kmer"))
    km = overlap.kmers(g(docs, "doc_id"), 31, both_strands=False).select(F.col("read_id").alias("doc_id"), "kmer")
    pairs = km.join(first, "kmer").select("doc_id", "item_id").distinct()
    return pairs.join(docs, "doc_id").join(items, "item_id").where(F.col("text").contains(F.col("passage"))).select("doc_id", "item_id")


@query(f"""with {_SHOT}, w as (select read_id, s as strand from (select read_id, unnest([seq, {_RC.format('seq')}]) as s from reads))
select distinct x.read_id from reads x join w y on x.read_id <> y.read_id and (contains(y.strand, x.seq)) and (length(x.seq) < length(y.strand) or y.read_id < x.read_id)""")
def contained_reads(spark, d):
    return overlap.contained(_aligned(spark, d, "exact"))


def _bench_graph(spark, d, reduce=True):
    return assembly.string_graph(bench_reads(spark, d), assembly.Profile.low_error(reduce=reduce))[1]


@query()
def overlap_kinds(spark, d):
    e = _bench_graph(spark, d, False)
    return e.groupBy("u_end", "v_end").agg(F.count("*").alias("n"), F.sum("suffix").cast("long").alias("suffix"))


@query(f"""with {_SHOT}, nxt as (select read_id as u, lead(read_id) over w as v, chrom, s, e, rev, lead(s) over w as s2, lead(e) over w as e2, lead(rev) over w as rev2 from reads window w as (partition by chrom order by s)),
f as (select u, v, case when rev then 0 else 1 end as u_end, case when rev2 then 1 else 0 end as v_end, (e2 - e)::int as suffix from nxt where v is not null and e - s2 >= 31)
select u, v, u_end::int as u_end, v_end::int as v_end, suffix from f
union all select v, u, v_end::int, u_end::int, (s2 - s)::int as suffix from nxt join f using (u, v)""")
def transitive_reduction(spark, d):
    return _bench_graph(spark, d).select("u", "v", "u_end", "v_end", F.col("suffix").cast("int").alias("suffix"))


# ---- contig generation on ready-made graphs ----

_ORD = """a as (select distinct l_orderkey as o, l_partkey as p, l_suppkey as s from lineitem),
pairs as (select x.o as u, y.o as v, count(*)::bigint as n_shared from a x join a y on x.p = y.p and x.s = y.s and x.o < y.o group by 1, 2),
e as (select u, v from pairs union select v, u from pairs),
deg as (select u as v, count(*)::bigint as deg from e group by 1),
b as (select v from deg where deg > 2),
l as (select u, v from e where u not in (select v from b) and v not in (select v from b))"""
_REACH = "r(v, c) as (select distinct u, u from l union select l.v, r.c from r join l on l.u = r.v), m as (select v, min(c) as contig_id from r group by v)"
_REC = _ORD.replace("a as", "recursive a as", 1)


def _ord(spark, d):
    store = Scratch(spark, "orders-graph")
    return store.keep(contigs.both_ways(graphs.orders(t(spark, d, "lineitem"))))


def _ord_l(spark, d):
    s = _ord(spark, d)
    return Scratch(spark, "masked").keep(contigs.mask(s, contigs.branching(contigs.degrees(s))))


def _ord_member(spark, d, method="contract", **more):
    return contigs.components(_ord_l(spark, d), method, **more)


@query(f"with {_ORD} select * from pairs")
def order_graph(spark, d):
    return graphs.orders(t(spark, d, "lineitem"))


@query(f"with {_ORD} select * from deg")
def degree_vector(spark, d):
    return contigs.degrees(_ord(spark, d))


@query(f"with {_ORD} select deg, count(*)::bigint as n from deg group by deg")
def degree_histogram(spark, d):
    return contigs.degrees(_ord(spark, d)).groupBy("deg").agg(F.count("*").alias("n"))


@query(f"with {_ORD} select v from b")
def branch_vertices(spark, d):
    return contigs.branching(contigs.degrees(_ord(spark, d)))


@query(f"with {_ORD} select u, v from l")
def branch_mask(spark, d):
    return _ord_l(spark, d)


@query(f"with {_ORD} select u as v from l group by u having count(*) = 1")
def root_vertices(spark, d):
    return contigs.roots(_ord_l(spark, d))


for _m in ("contract", "hook", "label"):

    def _components(spark, d, _m=_m):
        return _ord_member(spark, d, _m)

    _components.__name__ = f"components_orders_{_m}"
    query(f"with {_REC}, {_REACH} select v, contig_id from m")(_components)


@query(f"""with {_REC}, {_REACH}, sz as (select contig_id, count(*) as n, (select count(*) from l join m x on x.v = l.u where x.contig_id = m.contig_id) / 2 as k from m group by contig_id),
ch as (select m.v, m.contig_id from m join sz using (contig_id) where n <> k),
ends as (select min(x.v) as lo, x.contig_id from ch x where (select count(*) from l where l.u = x.v) = 1 group by x.contig_id),
wk(v, contig_id, pos, bef) as (select lo, contig_id, 0::bigint, -1::bigint from ends union all select l.v, wk.contig_id, wk.pos + 1, wk.v from wk join l on l.u = wk.v and l.v <> wk.bef)
select wk.v, ends.lo as contig_id, pos, count(*) over (partition by wk.contig_id) as q from wk join ends using (contig_id)""")
def chain_ranking(spark, d):
    return contigs.chain_ranks(_ord_l(spark, d))


_SESS = "x as (select event_id, user_id, ts, event_id as k, lag(ts) over (partition by user_id order by ts, event_id) as p from events), y as (select *, sum(case when p is null or date_diff('microsecond', p, ts) > {g} then 1 else 0 end) over (partition by user_id order by ts, event_id) as i from x), z as (select event_id as v, min(event_id) over (partition by user_id, i) as contig_id, count(*) over (partition by user_id, i) as n from y)"


@query("with " + _SESS.format(g=240 * 60_000_000) + " select v, contig_id from z where n > 1")
def components_sessions(spark, d):
    return contigs.components(contigs.both_ways(graphs.sessions(t(spark, d, "events"), 240)))


@query("select o_orderkey as v, min(o_orderkey) over (partition by o_custkey) as contig_id from orders qualify count(*) over (partition by o_custkey) > 1")
def components_customers(spark, d):
    return contigs.components(contigs.both_ways(graphs.customers(t(spark, d, "orders"))))


@query("select conv_id * 1000000000 + turn as v, conv_id * 1000000000 as contig_id from conversations qualify count(*) over (partition by conv_id) > 1")
def components_conversations(spark, d):
    return contigs.components(graphs.conversations(t(spark, d, "conversations")))


@query(f"with {_REC}, {_REACH}, n as (select contig_id, count(*)::bigint as n from m group by 1), k as (select contig_id, count(*) // 2 as k from l join m on m.v = l.u group by 1) select contig_id, n from n join k using (contig_id) where n = k")
def chain_vs_cycle(spark, d):
    l = _ord_l(spark, d)
    return contigs.cycles(l, contigs.components(l))


@query(f"with {_REC}, {_REACH} select contig_id, count(*)::bigint as n from m group by 1")
def contig_sizes(spark, d):
    return contigs.sizes(_ord_member(spark, d))


@query(f"with {_REC}, {_REACH} select n, count(*)::bigint as contigs from (select contig_id, count(*)::bigint as n from m group by 1) group by n")
def contig_size_histogram(spark, d):
    return contigs.sizes(_ord_member(spark, d)).groupBy("n").agg(F.count("*").alias("contigs"))


def _lpt_sql(source, owners, order, tail="select id as contig_id, owner from r where i > 0"):
    return f"""with recursive s as ({source}), o as (select id, n, row_number() over (order by {order}) as i from s),
r as (select 0::bigint as i, null::bigint as id, null::int as owner, list_transform(range({owners}), lambda x: 0::bigint) as loads
  union all select o.i, o.id, (list_position(loads, list_min(loads)) - 1)::int,
    list_transform(loads, lambda x, k: case when k = list_position(loads, list_min(loads)) then x + o.n else x end)
  from r join o on o.i = r.i + 1)
{tail}"""


_SUPP = "select l_suppkey as id, count(*)::bigint as n from lineitem group by 1"
_CUST = "select o_custkey as id, count(*)::bigint as n from orders group by 1"


def _supp(spark, d):
    return t(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("contig_id")).agg(F.count("*").alias("n"))


def _cust(spark, d):
    return t(spark, d, "orders").groupBy(F.col("o_custkey").alias("contig_id")).agg(F.count("*").alias("n"))


@query(_lpt_sql(_SUPP, 18, "n desc, id"))
def lpt_sorted_p18(spark, d):
    return contigs.assign(_supp(spark, d), 18)


@query(_lpt_sql(_CUST, 128, "n desc, id"))
def lpt_sorted_p128(spark, d):
    return contigs.assign(_cust(spark, d), 128)


@query(_lpt_sql(_SUPP, 18, "id"))
def lpt_unsorted_p18(spark, d):
    return contigs.assign(_supp(spark, d), 18, ordered=False)


_LOADS = "select k::int as owner, loads[k + 1] as load from (select loads from r order by i desc limit 1), (select unnest(range({p})) as k)"


@query(_lpt_sql(_CUST, 128, "n desc, id", _LOADS.format(p=128)))
def lpt_load_histogram(spark, d):
    s = _cust(spark, d)
    return contigs.load_report(s, contigs.assign(s, 128, where="histogram"), 128).select("owner", "load")


@query(_lpt_sql(_SUPP, 18, "n desc, id", f"select max(load)::bigint as makespan, avg(load) as mean, max(load) / avg(load) as imbalance, sum((load = 0)::int)::bigint as idle from ({_LOADS.format(p=18)})"))
def lpt_load_report(spark, d):
    s = _supp(spark, d)
    return measures.load_summary(contigs.load_report(s, contigs.assign(s, 18), 18))


@query(_lpt_sql("select n_regionkey as id, count(*)::bigint as n from nation group by 1", 8, "n desc, id", _LOADS.format(p=8)))
def lpt_idle(spark, d):
    s = t(spark, d, "nation").groupBy(F.col("n_regionkey").cast("long").alias("contig_id")).agg(F.count("*").alias("n"))
    return contigs.load_report(s, contigs.assign(s, 8), 8).select("owner", "load")


@query("with s as (" + _SUPP + ") select k::int as owner, coalesce(sum(n), 0)::bigint as load from (select unnest(range(18)) as k) left join s on id % 18 = k group by k")
def lpt_hash_baseline(spark, d):
    s = _supp(spark, d)
    return contigs.load_report(s, baselines.hash_assign(s, 18), 18).select("owner", "load")


def _owned(spark, d):
    """The order graph's mask with owner = contig modulo 16."""
    l = _ord_l(spark, d)
    m = Scratch(spark, "owned").keep(contigs.components(l))
    return l, m.select("v", F.pmod("contig_id", F.lit(16)).cast("int").alias("owner"))


_OWN = f"{_REC}, {_REACH}, p as (select v, (contig_id % 16)::int as owner from m)"


@query(f"with {_OWN} select * from p")
def placement(spark, d):
    return _owned(spark, d)[1]


@query(f"with {_OWN} select a.owner, l.u, l.v from l join p a on a.v = l.u join p b on b.v = l.v where a.owner = b.owner")
def induced_two_sided(spark, d):
    return contigs.induced(*_owned(spark, d))


@query(f"with {_OWN} select a.owner, l.u, l.v from l join p a on a.v = l.u")
def induced_one_sided(spark, d):
    return contigs.induced(*_owned(spark, d), sides=1)


@query("""with e as (select distinct c_nationkey::bigint as u, s_nationkey::bigint as v from orders join lineitem on o_orderkey = l_orderkey join customer on c_custkey = o_custkey join supplier on s_suppkey = l_suppkey)
select a.n_regionkey as owner, u, v from e join nation a on a.n_nationkey = u join nation b on b.n_nationkey = v where a.n_regionkey = b.n_regionkey""")
def induced_region(spark, d):
    """A general vertex map: edges between nations that trade, kept inside regions."""
    o, l, c, s = (t(spark, d, x) for x in ("orders", "lineitem", "customer", "supplier"))
    j = o.join(l, o.o_orderkey == l.l_orderkey).join(c, c.c_custkey == o.o_custkey).join(s, s.s_suppkey == l.l_suppkey)
    e = j.select(F.col("c_nationkey").cast("long").alias("u"), F.col("s_nationkey").cast("long").alias("v")).distinct()
    return contigs.induced(e, t(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("v"), F.col("n_regionkey").alias("owner")))


@query(f"with {_OWN} select a.owner, l.u, l.v from l join p a on a.v = l.u")
def induced_grid(spark, d):
    l, p = _owned(spark, d)
    n = t(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1
    return contigs.induced_by_grid(l, p, n, 4)[0]


@query(f"""with {_OWN}, n as (select max(o_orderkey) + 1 as n from orders), h as (select v // ceil(n / 4)::bigint as b, count(*)::bigint as held from p, n group by 1)
select x.b as bi, y.b as bj, (x.held + case when x.b = y.b then 0 else y.held end)::bigint as received from h x, h y""")
def grid_comm_model(spark, d):
    l, p = _owned(spark, d)
    n = t(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1
    return contigs.induced_by_grid(l, p, n, 4)[1]


@query(f"with {_REC}, n as (select ceil((max(o_orderkey) + 1) / 4)::bigint as s from orders) select u // s as bi, v // s as bj, count(*)::bigint as nnz from l, n group by 1, 2")
def grid_blocks(spark, d):
    n = t(spark, d, "orders").agg(F.max("o_orderkey")).first()[0] + 1
    return matrix.blocks(_ord_l(spark, d).select(F.col("u").alias("row"), F.col("v").alias("col"), F.lit(1).alias("val")), n, 4)


@query("select (conv_id % 8)::int as owner, conv_id * 1000000000 + turn as read_id, k::int as part, substr(text, k * 50 + 1, 50) as seq from (select *, unnest(range(0, (greatest(length(text), 1) - 1) // 50 + 1)) as k from conversations)")
def read_shipping(spark, d):
    """Turns to owners in pieces of fifty characters."""
    c = t(spark, d, "conversations")
    place = c.select((F.col("conv_id") * graphs.TURNS + F.col("turn")).alias("v"), (F.col("conv_id") % 8).cast("int").alias("owner"))
    rows = c.select((F.col("conv_id") * graphs.TURNS + F.col("turn")).alias("read_id"), F.col("text").alias("seq"))
    return contigs.ship_reads(rows, place, 50).select("owner", "read_id", F.col("part").cast("int").alias("part"), "seq")


_CE = """x as (select o_custkey, o_orderkey as u, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as v from orders),
e as (select (o_custkey % 8)::int as owner, u, v from x where v is not null union all select (o_custkey % 8)::int, v, u from x where v is not null)"""


def _cust_owned(spark, d):
    own = t(spark, d, "orders").select(F.col("o_orderkey").alias("v"), F.pmod("o_custkey", F.lit(8)).cast("int").alias("owner"))
    return contigs.induced(contigs.both_ways(graphs.customers(t(spark, d, "orders"))), own, sides=1)


@query(f"""with {_CE}, i as (select owner, u, row_number() over (partition by owner order by u) - 1 as lid from (select distinct owner, u from e)),
c as (select e.owner, y.lid as c, list(x.lid order by x.lid) as rows from e join i x on x.owner = e.owner and x.u = e.u join i y on y.owner = e.owner and y.u = e.v group by 1, 2),
q as (select owner, c, rows, sum(len(rows)) over (partition by owner order by c) as upto from c)
select owner, md5(array_to_string(list_prepend(0, list(upto::bigint order by c)), ',')) as jc, md5(array_to_string(flatten(list(rows order by c)), ',')) as ir, sum(len(rows))::bigint as nnz from q group by owner""")
def csc_arrays(spark, d):
    c = contigs.csc(_cust_owned(spark, d))
    h = lambda x: F.md5(F.array_join(x, ",").cast("binary"))
    return c.select("owner", h("jc").alias("jc"), h("ir").alias("ir"), F.size("ir").cast("long").alias("nnz"))


@query(f"with {_CE} select v as col, array_to_string(list(u order by u), ',') as rows from e group by v")
def dcsc_columns(spark, d):
    return contigs.dcsc(_cust_owned(spark, d)).select("col", F.array_join("rows", ",").alias("rows"))


def _conversation_contigs(spark, d):
    c = t(spark, d, "conversations")
    rows = c.select((F.col("conv_id") * graphs.TURNS + F.col("turn")).alias("read_id"), F.col("text").alias("seq"), F.length("text").alias("len"))
    return contigs.generate_contigs(graphs.conversations(c), rows, 8)


# ---- measures on the assembly ----

@query(f"with {_G} select least(seq, {_RC.format('seq')}) as seq, len::bigint as len from g")
def assemble_benchmark(spark, d):
    """The flagship: error-free shotgun reads of the passages on random strands, back to the passages."""
    out = assembly.assemble(bench_reads(spark, d)).contigs
    return out.select(dna.canonical("seq").alias("seq"), "len")


def _bench_contigs(spark, d):
    r = bench_reads(spark, d)
    return assembly.assemble(r).contigs, r


@query("select 100.0::double as completeness")
def quality_completeness(spark, d):
    c, r = _bench_contigs(spark, d)
    return measures.completeness(measures.contig_intervals(c, r), bench_genome(spark, d)).select(F.col("completeness").cast("double").alias("completeness"))


@query(f"with {_G} select max(len)::bigint as longest, count(*)::bigint as contigs, sum(len)::bigint as bases from g")
def quality_longest(spark, d):
    c, _ = _bench_contigs(spark, d)
    return c.agg(F.max("len").alias("longest"), F.count("*").alias("contigs"), F.sum("len").alias("bases"))


@query("select 0::bigint as misassembled")
def quality_misassembled(spark, d):
    c, r = _bench_contigs(spark, d)
    return measures.misassembled(measures.contig_intervals(c, r)).agg(F.count("*").alias("misassembled"))


@query(f"with {_SHOT} select chrom, b as bin, count(*)::bigint as depth from (select chrom, unnest(range(s // 50, (e - 1) // 50 + 1)) as b from reads) group by 1, 2")
def coverage_profile(spark, d):
    return measures.coverage_profile(bench_reads(spark, d), 50)


@query("with x as (select len, sum(len) over (order by len desc, item_id) as upto, sum(len) over () as s from (select item_id, 2 * octet_length(encode(text)) as len from benchmark)) select max(len)::bigint as nx from x where upto >= 0.5 * s")
def n50(spark, d):
    return measures.nx(_bench_contigs(spark, d)[0].select("contig_id", "len"))


@query()
def stage_seconds(spark, d):
    a = assembly.assemble(bench_reads(spark, d))
    return spark.createDataFrame([(k, float(v)) for k, v in measures.stage_shares(a.seconds).items()], "stage string, share double")


@query()
def best_overlap_graph(spark, d):
    return overlap.best_overlap_graph(_bench_graph(spark, d, False)).select("u", "u_end", "v")


@query("""with e as (select vec_id, label, list_transform(embedding, lambda x: x::double) as v from embeddings),
s as (select a.vec_id as u, b.vec_id as v, list_cosine_similarity(a.v, b.v) as sim from e a join e b on a.label = b.label and a.vec_id <> b.vec_id),
k as (select u, v, sim from s qualify row_number() over (partition by u order by sim desc, v) <= 2)
select a.u, a.v, round(a.sim, 6) as sim from k a join k b on a.u = b.v and a.v = b.u where a.u < a.v""")
def knn_graph(spark, d):
    return graphs.neighbours(t(spark, d, "embeddings")).select("u", "v", F.round("sim", 6).alias("sim"))


# ---- baselines ----

@query("select o_orderkey as v, pos from (select o_orderkey, row_number() over w - 1 as pos, count(*) over (partition by o_custkey) as n, first_value(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as a, last_value(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and unbounded following) as b from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)) where n > 1 and a < b union all select o_orderkey, n - 1 - pos from (select o_orderkey, row_number() over w - 1 as pos, count(*) over (partition by o_custkey) as n, first_value(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as a, last_value(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and unbounded following) as b from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)) where n > 1 and a > b")
def walk_customers(spark, d):
    """Chains of a customer's orders by list ranking: every order's place from the smaller end."""
    return contigs.chain_ranks(contigs.both_ways(graphs.customers(t(spark, d, "orders")))).select("v", "pos")


@query("select conv_id * 1000000000 + turn as v, conv_id * 1000000000 as root, turn as pos from conversations qualify count(*) over (partition by conv_id) > 1")
def remote_walk_conversations(spark, d):
    return baselines.remote_walk(graphs.conversations(t(spark, d, "conversations")))


@query()
def greedy_single_node(spark, d):
    """One process, no Spark: the longest overlaps first."""
    rows = [(r.read_id, r.seq) for r in bench_reads(spark, d).select("read_id", "seq").collect()]
    out = baselines.single_node(rows, 31)
    return spark.createDataFrame([(len(s), s) for s in out], "len long, seq string")


# ---- matrix algebra ----

_LA = "la as (select l_suppkey as row, l_linenumber::bigint as col, count(*)::bigint as val from lineitem group by 1, 2)"


def _la(spark, d):
    return t(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("row"), F.col("l_linenumber").cast("long").alias("col")).agg(F.count("*").alias("val"))


@query(f"with {_LA} select a.row, b.row as col, sum(a.val * b.val)::bigint as val from la a join la b on a.col = b.col group by 1, 2")
def spgemm_plus_times(spark, d):
    a = _la(spark, d)
    return matrix.spgemm(a, matrix.transpose(a))


@query(f"with {_LA} select a.row, b.row as col, min(a.val + b.val)::bigint as val from la a join la b on a.col = b.col where a.row < b.row group by 1, 2")
def spgemm_min_plus(spark, d):
    a = _la(spark, d)
    return matrix.spgemm(a, matrix.transpose(a), matrix.MIN_PLUS, upper=True)


@query(f"with {_LA} select row as i, sum(val * s_nationkey)::bigint as val from la join supplier on s_suppkey = col group by 1")
def spmv_plus_times(spark, d):
    x = t(spark, d, "supplier").select(F.col("s_suppkey").alias("i"), F.col("s_nationkey").cast("long").alias("val"))
    return matrix.spmv(_la(spark, d), x)


@query(f"with {_LA} select row as i, max(val)::bigint as val from la group by 1")
def matrix_reduce(spark, d):
    return matrix.reduce(_la(spark, d), "row", F.max)


@query(f"with {_LA}, s as (select s_suppkey as i from supplier where s_nationkey < 3) select row, col, val from la where row not in (select i from s) and col not in (select i from s)")
def matrix_mask(spark, d):
    return matrix.mask(_la(spark, d), t(spark, d, "supplier").where("s_nationkey < 3").select(F.col("s_suppkey").alias("i")))


@query(f"with {_LA} select coalesce(a.row, b.row) as row, coalesce(a.col, b.col) as col, (coalesce(a.val, 0) + coalesce(b.val, 0))::bigint as val from la a full join (select col as row, row as col, val from la) b on a.row = b.row and a.col = b.col")
def matrix_eadd(spark, d):
    a = _la(spark, d)
    return matrix.eadd(a, matrix.transpose(a))


@query(f"with {_ORD} select count(*)::bigint as nnz, count(distinct u)::bigint as n_rows, count(distinct v)::bigint as n_cols, max(abs(u - v))::bigint as bandwidth, 0::bigint as lone from e")
def matrix_props(spark, d):
    return matrix.props(_ord(spark, d).select(F.col("u").alias("row"), F.col("v").alias("col"), F.lit(1).alias("val")))


# ---- streaming ----

@query("select epoch_us(date_trunc('day', ts)) as day_us, event_type, count(*)::bigint as n from events group by 1, 2")
def stream_tumbling(spark, d):
    return flows.tumbling(spark, d)


@query("select epoch_us(date_trunc('day', ts) - to_days(k)) as day_us, count(*)::bigint as n from events, (select unnest([0, 1]) as k) group by 1")
def stream_sliding(spark, d):
    return flows.sliding(spark, d)


@query("with " + _SESS.format(g=240 * 60_000_000) + ", w as (select user_id, i, min(ts) as s, count(*)::bigint as n from y group by 1, 2) select user_id, epoch_us(s) as start_us, n from w")
def stream_sessions(spark, d):
    return flows.sessions(spark, d)


@query(f"with {_SHOT}, {_km(17)} select n, count(*)::bigint as kmers from (select kmer, count(*)::bigint as n from km group by 1) group by n")
def stream_kmer_counts(spark, d):
    return flows.kmer_counts(spark, d)


@query("select count(distinct l_orderkey)::bigint as orders from lineitem")
def stream_dedup(spark, d):
    return flows.dedup(spark, d)


@query("select p.event_id, v.event_id as view_id from events p join events v on v.user_id = p.user_id and v.ts <= p.ts and v.ts >= p.ts - interval 24 hours where p.event_type = 'purchase' and v.event_type = 'view'")
def stream_interval_join(spark, d):
    return flows.interval_join(spark, d)


@query(f"""with i as (select item_id, {_ENC.format('text')} as s from benchmark), d as (select {_ENC.format('text')} as s from documents),
ik as (select item_id, substr(s, p, 31) as k from (select item_id, s, unnest(range(1, length(s) - 29)) as p from i where length(s) >= 31)),
dk as (select substr(s, p, 31) as k from (select s, unnest(range(1, length(s) - 29)) as p from d where length(s) >= 31))
select item_id as item, count(*)::bigint as shared from ik join dk using (k) group by 1""")
def stream_static_candidates(spark, d):
    return flows.static_candidates(spark, d)


# ---- conversations spelled from their chains ----

@query("select conv_id * 1000000000 as contig_id, count(*)::bigint as n_reads, string_agg(text, '' order by turn) as seq from conversations group by conv_id having count(*) > 1")
def spell_conversations(spark, d):
    return _conversation_contigs(spark, d).select("contig_id", "n_reads", "seq")


@query("select conv_id * 1000000000 as contig_id, turn as pos, conv_id * 1000000000 + turn as v from conversations qualify count(*) over (partition by conv_id) > 1")
def walk_conversations(spark, d):
    c = _conversation_contigs(spark, d)
    return c.select("contig_id", F.posexplode("reads").alias("pos", "v")).select("contig_id", F.col("pos").cast("long").alias("pos"), "v")


# ---- worked examples ----

@query("""with x as (select o_orderkey as v, o_custkey as c, row_number() over (partition by o_custkey order by o_orderkey) - 1 as r from orders),
y as (select v, c, r // 8 as lot, r % 8 + 1 as pos, count(*) over (partition by c, r // 8) as n from x),
z as (select *, case when n < 7 or pos < 3 then 1 when pos = 3 then null when pos < 7 then 2 else 3 end as part from y)
select v, min(v) over (partition by c, lot, part) as contig_id from z where part is not null qualify count(*) over (partition by c, lot, part) > 1""")
def branch_example(spark, d):
    """Every eight orders of a customer as the tree of the example: a chain of six, and two more behind the third, where it branches."""
    of = Window.partitionBy("c").orderBy("v")
    o = t(spark, d, "orders").select(F.col("o_orderkey").alias("v"), F.col("o_custkey").alias("c"))
    o = o.withColumn("r", F.row_number().over(of) - 1).select("v", "c", F.expr("r div 8").alias("lot"), (F.col("r") % 8 + 1).alias("pos"))
    on = Window.partitionBy("c", "lot").orderBy("pos")
    e = o.select(F.col("v").alias("u"), "pos", F.lead("v").over(on).alias("next"), F.lead("v", 4).over(on).alias("side"))
    e = e.select("u", F.explode(F.array(F.when(F.col("pos") != 6, F.col("next")), F.when(F.col("pos") == 3, F.col("side")))).alias("v")).where("v is not null")
    s = Scratch(spark, "branches").keep(contigs.both_ways(e))
    return contigs.components(contigs.mask(s, contigs.branching(contigs.degrees(s))))


@query("select 'AGAACTGAAGAA' as seq, 3::bigint as n_reads, false as overrun")
def concatenation_example(spark, d):
    rows = spark.createDataFrame([(1, "AGAACT"), (2, "AACTGAAG"), (3, "TGAAGAA")], "read_id long, seq string").withColumn("len", F.length("seq"))
    e = [(1, 2, 1, 0, 1, 0), (2, 1, 0, 1, 4, 5), (2, 3, 1, 0, 4, 2), (3, 2, 0, 1, 5, 7)]
    s = spark.createDataFrame(e, "u long, v long, u_end int, v_end int, pre int, post int")
    return contigs.generate_contigs(s, rows, 2).select("seq", "n_reads", "overrun")


for _name, _text in COVERAGE.items():

    def _run(spark, d, _text=SPARK.get(_name, _text)):
        import re as _re

        text = _text
        for name in set(_re.findall(r"\{(\w+)\}", text)):
            t(spark, d, name).createOrReplaceTempView(f"sw_{name}")
            text = text.replace("{" + name + "}", f"sw_{name}")
        return spark.sql(text)

    _run.__name__ = _name
    query(_text.replace("{", "").replace("}", ""))(_run)
