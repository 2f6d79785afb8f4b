"""Queries on the operators of this folder, over whole tables with production parameters, and their SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.llm import ctw, hilbert, hosts, imatch, language, mixing, neardup, packing, topk, warc
from catalogflow.session import fresh_path, table

MIX = {"src0": 4, "src1": 2}


def op4_language_mixture(spark, sf):
    docs = table(spark, sf, "documents")
    return language.identify(docs, language.fit(docs))


def op5_mix_sources(spark, sf):
    return mixing.mix_levels(table(spark, sf, "documents"), weights=MIX, percents=[10, 30, 100])


def op7_near_duplicates(spark, sf):
    return neardup.near_duplicate_groups(table(spark, sf, "documents"))


def op9_pack_windows(spark, sf):
    return packing.pack(table(spark, sf, "documents"))


#: example.com, .net and .org stand for public suffixes: what is one label below them is registered.
SUFFIXES = ("example.com", "example.net", "example.org")


def op1_warc_files(spark, sf):
    return warc.write_warc(table(spark, sf, "pages"), warc.warc_path(spark))


def op2_context_tree_weighting(spark, sf):
    return ctw.code_lengths(table(spark, sf, "documents"))


def op3_imatch_fingerprints(spark, sf):
    return imatch.fingerprints(table(spark, sf, "documents"))


def op6_host_reputation(spark, sf):
    """A page's outcome is its document's label; the document's number is in the URL."""
    labels = table(spark, sf, "labels").select(F.col("doc_id").alias("page_id"), F.expr("case when quality = 0 or toxic = 1 then 1 else 0 end").alias("bad"))
    number = F.expr("try_cast(regexp_extract(url, '^[a-z]+://[^/]+/[a-z]+/([0-9]+)', 1) as bigint)")
    return hosts.filter_urls(table(spark, sf, "pages"), labels, suffixes=SUFFIXES, key=number)


def op8_exact_top_k(spark, sf):
    """Rows whose id is divisible by 50 are the queries; they are searched for among all rows."""
    return topk.top_k(table(spark, sf, "embeddings"), asked=F.col("vec_id") % 50 == 0)


def op10_hilbert_shards(spark, sf):
    """Whole documents go into sorted files; the rows are read back from these, with the extents of their file."""
    return hilbert.shards(table(spark, sf, "documents"), fresh_path(spark, "hilbert"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_warc_files, op2_context_tree_weighting, op3_imatch_fingerprints, op4_language_mixture, op5_mix_sources,
        op6_host_reputation, op7_near_duplicates, op8_exact_top_k, op9_pack_windows, op10_hilbert_shards,
    )
}

WORDS = r"cast(coalesce(length(regexp_replace(text, '[^ \t\n\r]+', 'x', 'g')) - length(regexp_replace(text, '[^ \t\n\r]+', '', 'g')), 0) as bigint)"

SUFFIX_SQL = "case " + " ".join(f"when host = '{x}' or ends_with(host, '.{x}') then '{x}'" for x in sorted(SUFFIXES, key=len, reverse=True)) + " else regexp_extract(host, '([^.]*)$', 1) end"


def _level(level: str, up: str, m: str, own: str) -> str:
    """CTEs of one level of the hierarchy: nodes with their prior mean, the strength, the posterior mean."""
    return f"""n_{level} as (select {own}, sum(n) n, sum(k) k, any_value(m) m from (select h.*, {m} from hosts h {up}) group by all),
s_{level} as (select greatest(2.0, least(200.0, case when rho > 0 then 1 / rho - 1 else 200.0 end)) s from (select case when coalesce(sum(m * (1 - m) * (n - 1)), 0) > 0 then (sum(n * power(k / n - m, 2)) - sum(m * (1 - m))) / sum(m * (1 - m) * (n - 1)) else 0 end rho from n_{level} where n > 1)),
b_{level} as (select x.*, s, (k + s * m) / (n + s) mean from n_{level} x, s_{level})"""


def _hilbert_sql(bits: int, target: int) -> str:
    digit, follow = hilbert.curve_tables(3)
    top = 1 << bits
    return f"""with recursive src as (select source, ((row_number() over (order by source) - 1) * {top}) // count(*) over () d0 from (select distinct source from documents where source is not null)),
lng as (select lang, ((row_number() over (order by lang) - 1) * {top}) // count(*) over () d1 from (select distinct lang from documents where lang is not null)),
r as (select doc_id, d.source, d.lang, coalesce(n_chars, 0) n_chars, ('0x' || substr(md5(coalesce(cast(doc_id as varchar), 'null')), 1, 15))::bigint h, coalesce(d0, 0) d0, coalesce(d1, 0) d1,
least({top - 1}, floor(log2(1 + greatest(coalesce(n_chars, 0), 0)) * {top / 32}))::bigint d2 from documents d left join src using (source) left join lng using (lang)),
cells as (select d0, d1, d2, sum(n_chars)::bigint size from r group by 1, 2, 3),
walk as (select d0, d1, d2, {bits - 1} b, 0::bigint hx, 0 st from cells union all
select d0, d1, d2, b - 1, hx * 8 + {digit}[o + 1], {follow}[o + 1] from (select *, st * 8 + (d0 >> b) % 2 + 2 * ((d1 >> b) % 2) + 4 * ((d2 >> b) % 2) o from walk where b >= 0)),
placed as (select c.*, hx cell, coalesce(sum(size) over (order by hx rows between unbounded preceding and 1 preceding), 0) before from cells c join (select d0, d1, d2, hx from walk where b = -1) using (d0, d1, d2)),
o as (select doc_id, source, lang, n_chars, cell, ((before + (h::hugeint * size) // {1 << 60}) // {target})::bigint shard from r join placed using (d0, d1, d2)),
e as (select shard, min(source) min_source, max(source) max_source, min(lang) min_lang, max(lang) max_lang, min(n_chars) min_n_chars, max(n_chars) max_n_chars from o group by 1),
x as (select *, not coalesce(min_lang <= 'de' and max_lang >= 'de' and min_n_chars <= 4000 and max_n_chars >= 1000, false) skipped from e)
select o.*, min_source, max_source, min_lang, max_lang, min_n_chars, max_n_chars, skipped, (select round(avg(skipped::int), 6) from x) skipped_share from o join x using (shard)"""


ORACLES = {
    "op5_mix_sources": f"""
with light as (select doc_id, coalesce(source, '') source, {WORDS} tokens, ('0x' || substr(md5(coalesce(cast(doc_id as varchar), 'null')), 1, 15))::bigint h from documents),
have as (select source, sum(tokens)::bigint have, case source when 'src0' then 4 when 'src1' then 2 else 1 end::bigint w from light group by 1),
unit as (select min((have * 1000000) // w) unit from have where have > 0),
limits as (select source, level, ((unit::hugeint * w * p) // 100000000)::bigint budget from have, unit, (values (1, 10), (2, 30), (3, 100)) x(level, p)),
run as (select doc_id, source, tokens, sum(tokens) over (partition by source order by h range between unbounded preceding and current row) upto from light)
select doc_id, source, tokens, min(level)::int as level from run join limits using (source) where upto <= budget group by run.rowid_, doc_id, source, tokens"""
    .replace("select doc_id, source, tokens, sum(tokens) over", "select row_number() over () rowid_, doc_id, source, tokens, sum(tokens) over"),
    "op3_imatch_fingerprints": """
with t as (select doc_id, row_number() over () r, list_filter(list_distinct(string_split_regex(lower(coalesce(text, '')), '[^a-z0-9ß-öø-ÿà]+')), lambda x: x <> '') w from documents),
x as (select r, unnest(w) term from t), lex as (select term from x group by 1 having count(*) >= ceil((select count(*) from documents) * 0.0005::double) and count(*) <= floor((select count(*) from documents) * 0.1::double) and count(*) >= 2),
p as (select r, term from x join lex using (term)), g as (select r, count(*) n, string_agg(term, ' ' order by term) f, {subsets} from p group by 1)
select doc_id, coalesce(n, 0) n_terms, md5(f) full_hash, md5(f0) hash_0, md5(f1) hash_1, md5(f2) hash_2, md5(f3) hash_3 from t left join g using (r)""".replace(
        "{subsets}", ", ".join(f"string_agg(term, ' ' order by term) filter (where substr(md5('{k}:' || term), 1, 1) < 'a') f{k}" for k in range(4))
    ),
    "op6_host_reputation": f"""
with pg as (select page_id, url, regexp_replace(regexp_replace(regexp_replace(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1)), '^.*@', ''), ':[0-9]*$', ''), '[.]$', '') host, try_cast(regexp_extract(url, '^[a-z]+://[^/]+/[a-z]+/([0-9]+)', 1) as bigint) doc from pages),
sf as (select *, {SUFFIX_SQL} suffix from pg), inn as (select *, case when host = suffix then '' else substr(host, 1, length(host) - length(suffix) - 1) end i from sf),
own as (select page_id, url, host, suffix, doc, case when i = '' then host else regexp_extract(i, '([^.]*)$', 1) || '.' || suffix end as domain from inn),
hosts as (select host, domain, suffix, count(bad)::double n, coalesce(sum(bad), 0)::double k from (select own.*, case when l.doc_id is null then null when quality = 0 or toxic = 1 then 1 else 0 end bad from own left join labels l on l.doc_id = own.doc) where host <> '' group by 1, 2, 3),
whole as (select (coalesce(sum(k), 0) + 0.1 * 2.0) / (coalesce(sum(n), 0) + 2.0) m from hosts),
{_level('suffix', ', whole', 'whole.m', 'suffix')}, {_level('domain', 'join b_suffix u on u.suffix = h.suffix', 'u.mean m', 'suffix, domain')}, {_level('host', 'join b_domain u on u.suffix = h.suffix and u.domain = h.domain', 'u.mean m', 'suffix, domain, host')},
rep as (select host, n, mean, mean - 1.645 * sqrt(mean * (1 - mean) / (n + s + 1)) bound from b_host)
select page_id, url, host, domain, coalesce(n, 0)::bigint n, round(mean, 6) mean, round(bound, 6) bound, coalesce(bound <= 0.25, true) kept from own left join rep using (host)""",
    "op8_exact_top_k": """
with s as (select a.vec_id, b.vec_id neighbour_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]), 9) score from embeddings a, embeddings b where a.vec_id % 50 = 0 and a.vec_id <> b.vec_id)
select vec_id, rank, neighbour_id, score from (select *, row_number() over (partition by vec_id order by score desc, neighbour_id)::int rank from s) where rank <= 10""",
    "op10_hilbert_shards": _hilbert_sql(5, 4_000_000),
}
