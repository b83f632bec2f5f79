"""The registered opN queries: each applies its operator with production parameters to its whole table."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import bpe, common, decontaminate, licenses, simhash, suffix_dedup, token_files, topk, toxicity, url_filter, warc

#: Fixed values of the URL query: rules as (host, path, verdict).
URL_RULES = [
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
]


def op1_url_filter(spark, sf_dir):
    """The rules, above a list of every seventh page's url, as another crawler may have noted it down."""
    pages = common.table(spark, sf_dir, "pages")
    rules = spark.createDataFrame(URL_RULES, "host string, path string, verdict string")
    listed = pages.where(F.col("page_id") % 7 == 0).select(F.concat("url", F.lit("#seen")).alias("url"))
    return url_filter.judge_urls(pages, rules, listed)


def op2_exact_topk(spark, sf_dir):
    vectors = topk.integer_vectors(common.table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return topk.exact_top_k(vectors, vectors.where(F.col("vec_id") % 50 == 0), k=5)


def op3_decontamination(spark, sf_dir):
    return decontaminate.contained_items(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))


def op4_simhash(spark, sf_dir):
    return simhash.near_duplicates(common.table(spark, sf_dir, "documents"), words=3, t=2)


def op5_bpe(spark, sf_dir):
    docs = common.table(spark, sf_dir, "documents")
    return bpe.encode_documents(docs, common.vocabulary("byte_bpe_50k.json"), keep_ids=False)


def op6_licences(spark, sf_dir):
    return licenses.scan_licences(common.table(spark, sf_dir, "documents"))


def op7_warc_revisits(spark, sf_dir):
    return warc.resolve_revisits(warc.crawl_of_pages(common.table(spark, sf_dir, "pages")))


def op8_suffix_dedup(spark, sf_dir):
    return suffix_dedup.remove_repeats(common.table(spark, sf_dir, "documents"), window=100, keep_text=False)


def op9_token_files(spark, sf_dir):
    docs = common.table(spark, sf_dir, "documents")
    manifest, _ = token_files.write_token_files(docs, common.vocabulary("word_bpe_49k.json"))
    return token_files.read_token_files(manifest)


def op10_toxicity(spark, sf_dir):
    docs = common.table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, common.table(spark, sf_dir, "labels"))
    return toxicity.score_documents(docs, model)


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {f.__name__: f for f in (op1_url_filter, op2_exact_topk, op3_decontamination, op4_simhash, op5_bpe, op6_licences, op7_warc_revisits, op8_suffix_dedup, op9_token_files, op10_toxicity, pipeline)}


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" for x in r) + ")" for r in rows)


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("'", "''") + "'"


def _licence_sql() -> str:
    """Rules one after the other, as the operator spends identifiers."""
    rules = [(i + 1, "".join(f"<{x}>" for x in ids), licence) for i, (ids, licence) in enumerate(licenses.RULES)]
    return f"""
with recursive known(sentence, sid) as (values {_values(licenses.SENTENCES)}),
rules(i, run, licence) as (values {", ".join(f"({i}, '{run}', '{licence}')" for i, run, licence in rules)}),
s as (select doc_id, row_number() over () as r, string_split(regexp_replace(regexp_replace(coalesce(text, ''), {_quoted(licenses.DEFINED)}, ' ', 'g'), {_quoted(licenses.ENDS)}, chr(1), 'g'), chr(1)) as parts from documents),
u as (select doc_id, r, unnest(parts) as whole, generate_subscripts(parts, 1) as pos from s),
l as (select doc_id, r, pos, case when contains(whole, chr(10)) then list_concat([whole], string_split(whole, chr(10))) else [whole] end as units from u),
x as (select doc_id, r, pos, unnest(units) as raw, generate_subscripts(units, 1) as line from l),
h as (select x.doc_id, x.r, x.pos, x.line, k.sid from x join known k on trim(regexp_replace(lower(x.raw), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')) = k.sentence qualify x.line = 1 or min(x.line) over (partition by x.r, x.pos) > 1),
g as (select doc_id, r, string_agg(sid, ' ' order by pos, line) as sentences, string_agg('<' || sid || '>', '' order by pos, line) as whole from h group by doc_id, r),
w as (select doc_id, r, sentences, 0 as i, whole as rest, []::varchar[] as found from g
  union all select doc_id, r, sentences, rules.i, replace(rest, run, '|'), case when contains(rest, run) and not list_contains(found, licence) then list_append(found, licence) else found end from w join rules on rules.i = w.i + 1)
select doc_id, sentences, array_to_string(found, ' ') as licences, trim(regexp_replace(replace(rest, '|', ''), '[<>]+', ' ', 'g')) as unmatched from w where i = {len(rules)}"""


def _canonical_sql(url: str) -> str:
    """warc.canonical_url() of a column."""
    rest = f"regexp_extract({url}, '(?s)^[^:/?#]*://([^#]*)', 1)"
    host = f"regexp_replace(translate(regexp_extract({rest}, '(?s)^(?:[^/?@]*@)?([^/?]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), ':(80|443)$', '')"
    path = f"regexp_extract({rest}, '(?s)^[^/?]*([^?]*)', 1)"
    params = f"array_to_string(list_sort(list_filter(string_split(regexp_extract({rest}, '(?s)\\?(.*)$', 1), '&'), lambda x: x <> '' and not starts_with(x, 'utm_'))), '&')"
    return f"case when regexp_matches({url}, '^[^:/?#]*://') then {host} || case when {path} = '' then '/' else {path} end || case when {params} <> '' then '?' || {params} else '' end end"


SQL = {
    "op1_url_filter": f"""
with rules(host, path, verdict) as (values {_values(URL_RULES)}),
listed as (select distinct {_canonical_sql("url")} as key from pages where page_id % 7 = 0 and {_canonical_sql("url")} is not null),
p as (
  select page_id, {_canonical_sql("url")} as key,
    translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') as path
  from pages),
j as (select *, coalesce(key in (select key from listed), false) as listed,
  (select max_by(u.host || u.path, length(u.host || u.path)) from rules u where (p.host = u.host or ends_with(p.host, '.' || u.host)) and starts_with(p.path, u.path)) as rule,
  (select max_by(u.verdict, length(u.host || u.path)) from rules u where (p.host = u.host or ends_with(p.host, '.' || u.host)) and starts_with(p.path, u.path)) as ruled from p)
select page_id, host, path, rule, coalesce(ruled, case when listed then 'block' end, 'allow') as verdict, listed from j""",
    "op3_decontamination": """
with d as (select doc_id, row_number() over () as r, regexp_extract_all(lower(coalesce(text, '')), '[\\p{L}\\p{N}]+') as w from documents where doc_id is not null),
i as (select item_id, row_number() over () as q, regexp_extract_all(lower(coalesce(text, '')), '[\\p{L}\\p{N}]+') as w from benchmark where item_id is not null),
ds as (select distinct doc_id, r, array_to_string(w[k + 1:k + 5], ' ') as s from (select doc_id, r, w, unnest(range(greatest(len(w) - 4, 1))) as k from d where len(w) > 0)),
si as (select distinct item_id, q, array_to_string(w[k + 1:k + 5], ' ') as s from (select item_id, q, w, unnest(range(greatest(len(w) - 4, 1))) as k from i where len(w) > 0)),
n as (select item_id, q, count(*) as n_item from si group by item_id, q),
p as (select doc_id, r, item_id, q, count(*) as n_shared from ds join si using (s) group by all),
b as (select doc_id, item_id, n_shared, n_item, n_shared::double / n_item as containment from p join n using (item_id, q) where n_shared::double / n_item >= 0.8)
select doc_id, item_id, n_shared, n_item, containment from b qualify row_number() over (partition by doc_id, item_id order by containment desc, n_shared desc) = 1""",
    "op6_licences": _licence_sql(),
    "op7_warc_revisits": f"""
with q as (select page_id, '"' || md5(coalesce(html, '')) || '"' as h, {_canonical_sql("url")} as key, page_id % 7 as way from pages),
e as (select page_id, key, h, 1704067200 + page_id as t from q where page_id % 11 <> 3),
r as (select q.page_id, q.key, q.h, q.way, max_by(e.page_id, (e.t, 'response-' || e.page_id)) as prior, max_by(e.h, (e.t, 'response-' || e.page_id)) as prior_h
  from q left join e on q.key = e.key and e.t < 1704067200 + q.page_id + 31536000 group by all),
s as (select *, case when way = 1 then '"other"' when way = 5 then 'W/' || h when way not in (2, 3, 4) then h end as etag, case when way = 3 then (1704067200 + page_id)::varchar when way = 4 then '0' end as modified from r),
o as (select *, case when key is null or page_id is null then 'no_key' when prior is null then 'no_earlier_response' when etag is null and modified is null then 'no_validator'
  when etag is not null and regexp_replace(etag, '^W/', '') = prior_h then 'resolved' when etag is null and modified = (1704067200 + prior)::varchar then 'resolved' else 'validator_mismatch' end as outcome from s)
select 'revisit-' || page_id as record_id, key as canonical, 'response-' || prior as refers_to, outcome,
  case when outcome = 'resolved' then 'cache-control: max-age=60' || chr(10) || 'content-type: text/html' || chr(10) || 'date: ' || (1704067200 + 31536000 + page_id) || chr(10)
    || 'etag: ' || coalesce(etag, prior_h) || chr(10) || 'last-modified: ' || (1704067200 + prior) end as headers
from o""",
    "op2_exact_topk": """
with v as (select distinct vec_id, list_transform(embedding, lambda e: floor(256 * e::double)) as v from embeddings where embedding is not null and not list_has_any(list_transform(embedding, lambda e: e is null or not isfinite(e)), [true])),
s as (select q.vec_id as query_id, c.vec_id, list_dot_product(q.v, c.v)::bigint as score from v q join v c on q.vec_id % 50 = 0 and q.vec_id <> c.vec_id)
select query_id, rank, vec_id, score from (select *, row_number() over (partition by query_id order by score desc, vec_id)::int as rank from s) where rank <= 5""",
}


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
