"""Queries for near copies of whole documents, and how they agree with the quality labels."""

from __future__ import annotations

from pyspark.sql import functions as F

from stringweave.operators.near import near_copies
from stringweave.plans.registry import query, t
from stringweave.session import Scratch

_COPIES = r"""recursive cls as (select min(doc_id) as rep, count(*) as held, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as ws, text from documents where regexp_matches(text, '[^\x20\x09-\x0D]') group by text),
sh as (select distinct rep, unnest(case when len(ws) < 5 then [array_to_string(ws, ' ')] else list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) end) as s from cls),
size as (select rep, count(*) as n from sh group by rep),
pair as (select x.rep as a, y.rep as b, count(*) as i from sh x join sh y on x.s = y.s and x.rep < y.rep group by 1, 2),
link as (select a, b from pair join size x on x.rep = a join size y on y.rep = b where 5 * i >= 4 * (x.n + y.n - i)),
ends as (select a, b from link union all select b, a from link),
reach(v, m) as (select rep, rep from cls union select v, ends.b from reach join ends on ends.a = m),
root as (select v, min(m) as class_id from reach group by v),
more as (select a, sum(held)::bigint as more from ends join cls on rep = b group by a),
res as (select d.doc_id, coalesce(r.class_id, d.doc_id) as class_id, coalesce(c.held - 1 + coalesce(m.more, 0), 0)::bigint as n_links
  from documents d left join cls c on c.text = d.text left join root r on r.v = c.rep left join more m on m.a = c.rep)"""


@query(f"with {_COPIES} select doc_id, class_id, n_links from res")
def docs_near_copies(spark, d):
    """Documents that share 0.8 of their five-word shingles or more: class and number of links."""
    return near_copies(t(spark, d, "documents").select("doc_id", "text"))


@query(f"""with {_COPIES} select l.quality, count(*)::bigint as documents, count(*) filter (where n_links > 0)::bigint as linked, count(*) filter (where n_links > 0 and l.quality = m.quality)::bigint as agree
from res left join labels l using (doc_id) left join labels m on m.doc_id = class_id group by 1""")
def near_copies_quality(spark, d):
    """By label of quality: documents, those with a near copy, and those labelled like the first of their class."""
    found, q = Scratch(spark, "copies").keep(docs_near_copies(spark, d)), t(spark, d, "labels")
    own, first = q.select("doc_id", "quality"), q.select(F.col("doc_id").alias("class_id"), F.col("quality").alias("of_first"))
    linked = F.col("n_links") > 0
    x = found.join(own, "doc_id", "left").join(first, "class_id", "left")
    return x.groupBy("quality").agg(F.count("*").alias("documents"), F.count_if(linked).alias("linked"), F.count_if(linked & (F.col("quality") == F.col("of_first"))).alias("agree"))
