"""Queries for the three assembly workloads of the survey (W01 to W03), and reads and k-mers of whole documents."""

from __future__ import annotations

from pyspark.sql import functions as F

from stringweave import assembly, measures
from stringweave.functions import dna
from stringweave.operators import counting, meeting, overlap, sharing
from stringweave.plans.registry import _ENC, _RC, _SHOT, query, t
from stringweave.session import Scratch
from stringweave.sources import reads as R

# ---- documents ----

_DOC_SHOT = _SHOT.replace("select item_id as chrom", "select doc_id as chrom").replace("from benchmark", "from documents")


def doc_genome(spark, d):
    return R.genome(t(spark, d, "documents"), "doc_id", "text")


@query(f"with {_DOC_SHOT} select read_id, chrom, s::int as start, e::int as \"end\", rev, seq from reads")
def reads_shotgun_documents(spark, d):
    return R.shotgun(doc_genome(spark, d), 100, 25).select("read_id", "chrom", "start", "end", "rev", "seq")


def _doc_counts(k):
    def run(spark, d):
        if counting.fits(k):
            return counting.words(t(spark, d, "documents").where("length(text) > 0").select("text"), k, hex2=True)
        c = overlap.count_codes(doc_genome(spark, d), k)
        return c.select(dna.unpack("kmer", k).alias("kmer"), "n")

    run.__name__ = f"kmer_count_documents_k{k}"
    query(f"""
with g as (select {_ENC.format('text')} as seq from documents where length(text) > 0),
w as (select substr(seq, p, {k}) as w from (select seq, unnest(range(1, length(seq) - {k - 2})) as p from g where length(seq) >= {k}))
select least(w, {_RC.format('w')}) as kmer, count(*)::bigint as n from w group by 1""")(run)


_doc_counts(17)
_doc_counts(31)

# ---- workloads: genome, read length, stride, errors, profile ----


def _w01(spark, d):
    """Passages, then the turns of conversations; chromosomes are numbered in that order."""
    b = t(spark, d, "benchmark").select(F.lit(0).alias("kind"), F.col("item_id").cast("long").alias("id"), F.lit(0).alias("turn"), "text")
    c = t(spark, d, "conversations").select(F.lit(1).alias("kind"), F.col("conv_id").cast("long").alias("id"), F.col("turn").cast("int").alias("turn"), "text")
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))  # a small table stands in one file, its reads are many
    return R.genome(R.numbered(b.unionByName(c), ["kind", "id", "turn"], "chrom").repartition(tasks, "chrom"), "chrom", "text")


def _w02(spark, d):
    return R.genome(t(spark, d, "documents").where("lang = 'en'"), "doc_id", "text")


def _w03(spark, d):
    return R.genome(t(spark, d, "pages"), "page_id", "html")


_LOW = assembly.Profile.low_error(method="xdrop", fuzz=20, min_score=60)
WORKLOADS = {
    "w01": (_w01, 200, 5, 0.005, _LOW),  # depth 40
    "w02": (_w02, 390, 13, 0.005, _LOW),  # depth 30
    "w03": (_w03, 2000, 200, 0.15, assembly.Profile.high_error()),  # depth 10
}
#: Documents and pages repeat so much that pairs of their reads grow with the square of the input; classes hold the same links.
SHARED = {"w01": meeting.pairs, "w02": sharing.classes, "w03": sharing.classes}


def workload_reads(spark, d, name, spread=False):
    """Reads of a workload; with ``spread`` its texts are dealt to as many tasks as a shuffle has, whatever their files."""
    genome, length, stride, error, _ = WORKLOADS[name]
    g = genome(spark, d)
    if spread:
        g = g.repartition(int(spark.conf.get("spark.sql.shuffle.partitions", "200")), "chrom")
    return R.shotgun(g, length, stride, error=error)


def _workload(name):
    genome, _, _, _, p = WORKLOADS[name]

    def reads(spark, d):
        return workload_reads(spark, d, name).select("read_id", "chrom", "start", "end", "rev", "seq")

    def candidates(spark, d):
        return SHARED[name](workload_reads(spark, d, name, spread=SHARED[name] is sharing.classes), p.k)

    def assemble(spark, d):
        store, g = Scratch(spark, name), genome(spark, d)
        r = store.keep(workload_reads(spark, d, name))
        c = assembly.assemble(r, p).contigs
        at = store.keep(measures.contig_intervals(c, r))
        main = c.agg(F.count("*").alias("contigs"), F.max("len").alias("longest"))
        bad = measures.misassembled(at).agg(F.count("*").alias("misassembled"))
        return measures.completeness(at, g).join(main, F.lit(True)).join(bad, F.lit(True))

    reads.__doc__ = f"Reads of workload {name}."
    candidates.__doc__ = f"Reads of workload {name} that share k-mers: pairs, or classes that expand to all of them."
    assemble.__doc__ = f"Workload {name} from reads to contigs: completeness by truth, contigs, the longest, misassembled ones."
    for stem, f in (("reads", reads), ("candidates", candidates), ("assemble", assemble)):
        f.__name__ = f"{stem}_{name}"
        query()(f)


for _name in WORKLOADS:
    _workload(_name)
