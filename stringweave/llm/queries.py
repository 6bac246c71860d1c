"""The corpus operators as queries over the given tables, with SQL where SQL can say the same."""

from __future__ import annotations

from pyspark.sql import functions as F

from stringweave.llm import bpe, chat, embeddings, langid, mixing, pii, quality, simhash, toxicity, urls
from stringweave.llm._common import held_out, table

#: Where the public tokenizer's file is; a parameter of the query.
TOKENIZER = None
#: Text files of canonical URLs to block, one a line; a parameter of the query.  The tables hold no such list.
BLOCK_LIST = None


def tokenizer_path() -> str:
    if TOKENIZER:
        return TOKENIZER
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def op1_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.train(*toxicity.labelled(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic")))
    return toxicity.score(docs.withColumn("held_out", held_out("doc_id")), model).select("doc_id", "held_out", "score", "predicted")


def op2_bpe(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return bpe.encode_corpus(docs, tokenizer_path(), keep=["doc_id"], ids=False)


def op3_tool_calls(spark, sf_dir):
    return chat.format_calls(chat.events_of_turns(table(spark, sf_dir, "conversations")), chat.REPLY)


def op4_simhash(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return simhash.near_duplicates(docs, keep=["doc_id"]).select("doc_id", "fingerprint", "component_id")


def op5_pii(spark, sf_dir):
    return pii.scan(table(spark, sf_dir, "documents").select("doc_id", "text"), keep=["doc_id"])


def op6_host_rules(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return quality.judge(docs, keep=["doc_id"]).drop("soft_failed")


def op7_embeddings(spark, sf_dir):
    return embeddings.near_duplicates(table(spark, sf_dir, "embeddings"))


def listed_urls(pages):
    """The block list of BLOCK_LIST, or a stand-in for one, drawn by digest and blind to the words of a URL.

    The stand-in holds every canonical URL of the table whose md5 begins with 0, so a host has listed and
    unlisted pages, and for each of them one that no page has.
    """
    if BLOCK_LIST:
        return pages.sparkSession.read.text(BLOCK_LIST).select(F.trim("value").alias("url")).where("url <> ''")
    host, path = urls.host_path(F.col("url"))
    known = pages.select(urls.canonical(host, path).alias("url")).where(F.md5(F.col("url").cast("binary")).startswith("0")).distinct()
    return known.select(F.explode(F.array("url", F.concat("url", F.lit("/gone")))).alias("url"))


def op8_url_filter(spark, sf_dir):
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return urls.judge(pages, listed_urls(pages)).select("page_id", "host", "path", "rule", "verdict")


def op9_language(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    rows = docs.select("doc_id", "text").withColumn("held_out", held_out("doc_id"))
    return langid.identify(rows, learn_from=docs).select("doc_id", "held_out", "lang_pred", "score")


def op10_mixing(spark, sf_dir):
    return mixing.mix(table(spark, sf_dir, "documents").select("doc_id", "source", "text")).select("doc_id", "size", "source_size", "target", "taken")


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "op1_toxicity": op1_toxicity, "op2_bpe": op2_bpe, "op3_tool_calls": op3_tool_calls, "op4_simhash": op4_simhash, "op5_pii": op5_pii,
    "op6_host_rules": op6_host_rules, "op7_embeddings": op7_embeddings, "op8_url_filter": op8_url_filter, "op9_language": op9_language,
    "op10_mixing": op10_mixing, "pipeline": pipeline,
}

_WORDS = r"regexp_extract_all(coalesce({}, ''), '[^\x20\x09-\x0D]+')"

SQL = {
    "op3_tool_calls": """
with recursive c as (
  select conv_id::bigint as conv_id, turn::bigint as turn, role, text, substr(md5(conv_id::varchar || ':' || turn::varchar), 1, 1) as g,
    substr(md5(conv_id::varchar || ':' || (turn - 2)::varchar), 1, 1) as g2 from conversations),
ev as (
  select conv_id, turn * 2 + again as pos, turn, role, text, g, case role when 'user' then 'call' when 'assistant' then 'result' else coalesce(role, 'message') end as kind,
    case when role = 'user' then conv_id::varchar || '-' || turn::varchar
      when role = 'assistant' then conv_id::varchar || '-' || (turn - 1)::varchar || case when g = '0' then '-lost' else '' end end as call_id,
    case when role = 'user' then list_sort(list_filter([
      case when g2 not in ('2', '3') then conv_id::varchar || '-' || (turn - 2)::varchar end,
      case when g in ('2', '3', '4') then conv_id::varchar || '-' || (turn + 2)::varchar end], lambda x: x is not null)) else []::varchar[] end as waits
  from c, (select unnest([0, 1])::bigint as again) where again = 0 or (role = 'assistant' and g = '1')),
first as (
  select conv_id, call_id, min(pos) filter (kind = 'call') as call_pos, min(pos) filter (kind = 'result') as result_pos from ev where call_id is not null group by 1, 2),
calls as (select conv_id, call_id, min(pos) as pos, arg_min(waits, pos) as waits from ev where kind = 'call' group by 1, 2),
deps as (
  select a.conv_id, a.call_id, a.pos, b.call_id as dep, b.pos as dep_pos from (select conv_id, call_id, pos, unnest(waits) as dep from calls) a
  join calls b on b.conv_id = a.conv_id and b.call_id = a.dep),
late as (select conv_id, count(*) as m from calls where conv_id in (select conv_id from deps where dep_pos >= pos) group by 1),
walk(conv_id, call_id, here, n, m) as (
  select conv_id, call_id, call_id, 0, m from calls join late using (conv_id)
  union select w.conv_id, w.call_id, d.dep, w.n + 1, w.m from walk w join deps d on d.conv_id = w.conv_id and d.call_id = w.here where w.n < w.m),
deep as (select conv_id, call_id, case when max(n) >= max(m) then -1 else max(n) end as depth from walk group by 1, 2),
j as (
  select ev.*, call_pos, result_pos, coalesce(depth, 0)::int as depth, case when kind <> 'call' then '' when g = '0' then '$.chars: not integer' when g = '1' then '$.prompt: missing' else '' end as errors
  from ev left join first using (conv_id, call_id) left join deep using (conv_id, call_id))
select conv_id, pos, kind, call_id, case kind when 'call' then result_pos when 'result' then call_pos end as partner,
  case when kind not in ('call', 'result') then 'message' when kind = 'call' and pos > call_pos or kind = 'result' and pos > result_pos then 'repeated'
    when kind = 'call' and result_pos is null then 'unanswered' when kind = 'result' and call_pos is null then 'orphan' else 'linked' end as status,
  depth, errors = '' as valid, errors,
  case when kind = 'call' then '{' || case when len(waits) > 0 then '"after":' || to_json(waits)::varchar || ',' else '' end || '"arguments":{"chars":'
      || case when g = '0' then '"' || length(text)::varchar || '"' else length(text)::varchar end || case when g = '1' then '' else ',"prompt":' || to_json(text)::varchar end
      || ',"turn":' || turn::varchar || '},"id":"' || call_id || '","name":"reply","role":"call"}'
    when kind = 'result' then '{"content":' || to_json(text)::varchar || ',"id":"' || call_id || '","name":"reply","role":"result"}'
    else '{"content":' || to_json(text)::varchar || ',"role":"' || kind || '"}' end as json
from j""",
    "op6_host_rules": rf"""
with d as (select doc_id, source, coalesce(text, '') as t, {_WORDS.format("text")} as w from documents),
numbered as (select row_number() over () as k, * from d),
base as (
  select k, doc_id, source, len(w)::bigint as n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g'))::bigint as word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::bigint as n_symbols,
    (len(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))
     - len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))))::bigint as n_dup_lines
  from numbered),
windows as (select k, unnest(range(1, len(w) - 6)) as i, w from numbered where len(w) >= 8),
gram as (select k, i, array_to_string(w[i:i+7], ' ') as g from windows),
twice as (select k, i from (select k, i, count(*) over (partition by k, g) as c from gram) where c > 1),
inside as (select k, count(distinct i + o)::bigint as n from twice, (select unnest(range(0, 8)) as o) group by k),
r as (
  select b.*, coalesce(n, 0)::bigint as n_repeat_words, (n_words < 20 or 100 * coalesce(n, 0) > 30 * n_words) as base_failed,
    (10 * n_symbols > n_words or word_chars < 2 * n_words or word_chars > 12 * n_words) as soft_failed
  from base b left join inside using (k)),
h as (select source, count(*)::double as n, sum((base_failed or soft_failed)::int)::double as f from r group by source),
m as (select sum(f) / sum(n) as m, sum(n) as docs, count(*) as hosts, sum(f * f / n) as sq from h),
v as (select m, sq / docs - m * m - m * (1 - m) * hosts / docs as v from m),
s as (select m, case when v > 0 then greatest(1, least(1e6, m * (1 - m) / v - 1)) else 1e6 end as s from v),
rate as (select source, (f + m * s) / (n + s) as rate from h, s)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  (not base_failed and rate <= 0.5 and not (soft_failed and rate > 0.05)) as kept
from r join rate on rate.source is not distinct from r.source""",
    "op7_embeddings": """
with recursive e as (
  select vec_id, label, list_transform(embedding, lambda x: x::double) as v from embeddings),
l as (
  select a.vec_id as a, b.vec_id as b from e a join e b on a.label = b.label and a.vec_id <> b.vec_id
  where list_cosine_similarity(a.v, b.v) >= 0.98),
r(a, b) as (select a, b from l union select r.a, l.b from r join l on r.b = l.a),
c as (select a, min(b) as b from r group by a),
n as (select a, count(*)::bigint as n from l group by a)
select vec_id, coalesce(n, 0)::bigint as n_links, least(vec_id, coalesce(c.b, vec_id)) as component_id, vec_id <= coalesce(c.b, vec_id) as kept
from e left join c on c.a = vec_id left join n on n.a = vec_id""",
    "op8_url_filter": r"""
with u as (
  select page_id, case when contains(url, '://') then substr(url, position('://' in url) + 3) else '' end as rest from pages),
p as (
  select page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's') as path from u),
rules(h, p, v) as (values ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
fit as (
  select page_id, host, path, (select max_by(h || rules.p, length(h || rules.p)) from rules
    where (host = h or ends_with(host, '.' || h)) and starts_with(p.path, rules.p)) as rule from p),
c as (select page_id, regexp_replace(host, '^(www|m)\.', '') || regexp_replace(path, '(\.html|/)+$', '') as canon from p),
drawn as (select distinct canon from c where md5(canon) like '0%'),
listed as (select canon as url from drawn union select canon || '/gone' from drawn)
select page_id, host, path, rule,
  coalesce((select v from rules where h || rules.p = rule),
    case when regexp_replace(host, '^(www|m)\.', '') || regexp_replace(path, '(\.html|/)+$', '') in (select url from listed) then 'block' else 'allow' end) as verdict
from fit""",
    "op10_mixing": rf"""
with d as (
  select doc_id, source, len({_WORDS.format("text")})::bigint as size,
    ('0x' || substr(md5(coalesce(doc_id::varchar, '') || ':7'), 1, 15))::bigint as h from documents),
s as (select source, sum(size)::bigint as source_size from d group by source),
k as (select *, row_number() over (order by source nulls last)::bigint as rank from s),
w as (select *, ((rank - 1) % 3 + 1)::bigint as weight, 3 * source_size as cap, (sum(source_size) over ())::bigint as budget from k),
f as (
  select *, coalesce(sum(cap) over (order by cap / weight, rank rows between unbounded preceding and 1 preceding), 0)::bigint as cap_before,
    (sum(weight) over () - coalesce(sum(weight) over (order by cap / weight, rank rows between unbounded preceding and 1 preceding), 0))::bigint as weight_left from w),
g as (select *, cap::hugeint * weight_left <= weight::hugeint * (budget - cap_before) as stops from f),
t as (
  select source, source_size, rank, budget, case when stops then cap::double
    else (weight * (budget - coalesce(sum(case when stops then cap end) over (), 0)))::double / (sum(case when not stops then weight end) over ())::double end as target from g),
o as (
  select d.doc_id, d.size, d.h, t.source_size, t.rank, t.target, t.budget, row_number() over () as n,
    (sum(d.size) over (partition by t.rank order by d.h, d.doc_id nulls first))::bigint as upto
  from d join t on d.source is not distinct from t.source),
x as (
  select o.*, (upto + turn * source_size)::double / target as finish from o, (select unnest([0, 1, 2]) as turn) where size > 0 and target > 0),
c as (select n, size, budget, sum(size) over (order by finish, rank, h, doc_id nulls first) as total from x),
y as (select n, sum(size)::bigint as taken from c where total <= budget group by n)
select doc_id, size, source_size, target, coalesce(taken, 0)::bigint as taken from o left join y using (n)""",
}
