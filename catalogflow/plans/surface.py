"""Queries: the operators that a user needs around the methods, each over whole tables."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from catalogflow.functions.text import normalize_name, sql_normalize_name, sql_tokens, tokens
from catalogflow.plans.registry import load, query
from catalogflow.session import fresh_path, table
from catalogflow.streaming import traffic as S


def sql_query(name: str, text: str, duck: str | None = None, tables: str = "") -> None:
    """A query that is the same SQL in both engines (but for ``duck``), run through temporary views."""
    def run(spark, sf):
        for t in tables.split():
            table(spark, sf, t).createOrReplaceTempView(f"v_{t}")
        return spark.sql(text.format(**{t: f"v_{t}" for t in tables.split()}))

    run.__name__ = name
    query((duck or text).format(**{t: t for t in tables.split()}), name)(run)


sql_query("op_filter_predicates", "select doc_id, lang, n_chars from {documents} where lang in ('en', 'fr') and n_chars between 500 and 5000 and text like '%the%' and not (lang <=> null)", "select doc_id, lang, n_chars from {documents} where lang in ('en', 'fr') and n_chars between 500 and 5000 and text like '%the%' and lang is distinct from null", "documents")
sql_query("op_project_columns", "select doc_id as item_id, cast(n_chars as double) / 1000 as kilo_chars, case when n_chars > 2000 then 'long' else 'short' end as size_class, upper(lang) as lang_code from {documents}", None, "documents")
sql_query("op_join_inner", "select d.doc_id, lang, quality, toxic from {documents} d join {labels} l on d.doc_id = l.doc_id", None, "documents labels")
sql_query("op_join_left", "select n_name, count(s_suppkey) as suppliers from {nation} left join {supplier} on n_nationkey = s_nationkey group by n_name", None, "nation supplier")
sql_query("op_join_full", "select coalesce(a.k, b.k) as k, a.n as n_a, b.n as n_b from (select p_brand as k, count(*) as n from {part} where p_size < 25 and p_type <> 'LARGE' group by p_brand) a full join (select p_brand as k, count(*) as n from {part} where p_type = 'LARGE' group by p_brand) b on a.k = b.k", None, "part")

_HINTED = "select p_type, count(*) n, round(sum(l_quantity), 2) qty from lineitem join part on l_partkey = p_partkey group by 1"


def _hinted(name: str, hint: str) -> None:
    def run(spark, sf):
        j = load(spark, sf, "lineitem").join(load(spark, sf, "part").hint(hint), F.col("l_partkey") == F.col("p_partkey"))
        return j.groupBy("p_type").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))

    run.__name__ = name
    query(_HINTED, name)(run)


_hinted("op_join_broadcast", "broadcast")
_hinted("op_join_merge", "merge")
_hinted("op_join_shuffle_hash", "shuffle_hash")
sql_query("op_join_semi", "select doc_id, lang from {documents} d where exists (select 1 from {labels} l where l.doc_id = d.doc_id)", None, "documents labels")
sql_query("op_join_anti", "select doc_id, lang from {documents} d where not exists (select 1 from {labels} l where l.doc_id = d.doc_id)", None, "documents labels")
sql_query("op_join_theta", "select a.p_name, a.p_brand, count(*) as pairs from {part} a join {part} b on a.p_name = b.p_name and a.p_brand = b.p_brand and a.p_size < b.p_size group by a.p_name, a.p_brand", None, "part")
_BANDS = "(values (0, 1000, 'a'), (1000, 3000, 'b'), (3000, 10000, 'c'), (10000, 100000000, 'd'))"
sql_query("op_join_range", "select band, count(*) as n, sum(n_chars) as chars from {documents} join " + _BANDS + " as b(lo, hi, band) on n_chars >= lo and n_chars < hi group by band", "select band, count(*) as n, sum(n_chars)::bigint as chars from {documents} join " + _BANDS + " as b(lo, hi, band) on n_chars >= lo and n_chars < hi group by band", "documents")


@query("""with b as (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 6 hours then 0 else 1 end nw from events),
s as (select user_id, sid, min(ts) a, max(ts) z from (select *, sum(nw) over (partition by user_id order by ts, event_id rows unbounded preceding) sid from b) group by 1, 2)
select e.event_type, count(*) n from events e join s on e.user_id = s.user_id and e.ts >= s.a and e.ts <= s.z and e.event_type in ('error', 'purchase') group by 1""")
def op_join_interval(spark, sf):
    """Errors and purchases inside their user's visits: equality on the user, then the interval."""
    from catalogflow.operators.monitor import sessions

    e = load(spark, sf, "events")
    s = sessions(e).withColumnRenamed("user_id", "u")
    hit = e.where("event_type in ('error', 'purchase')").withColumn("t", F.col("ts").cast("timestamp")).join(s, F.col("user_id") == F.col("u")).where("t >= started and t <= ended")
    return hit.groupBy("event_type").agg(F.count("*").alias("n"))


@query("select e.event_id, arg_max(p.event_id, (p.ts, p.event_id)) purchase_id from events e left join events p on p.user_id = e.user_id and p.event_type = 'purchase' and p.ts < e.ts where e.event_type = 'error' group by 1")
def op_join_asof(spark, sf):
    """The last purchase before each error: one window over the user's events in order, no pairs."""
    e = load(spark, sf, "events")
    us = e.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(W.unboundedPreceding, -1)
    last = F.max(F.when(F.col("event_type") == "purchase", F.struct("us", "event_id"))).over(w)
    return us.withColumn("p", last).where("event_type = 'error'").select("event_id", F.col("p.event_id").alias("purchase_id"))


sql_query("op_agg_hash", "select source, count(*) as n, sum(n_chars) as chars, min(n_chars) as least, max(n_chars) as most from {documents} group by source", "select source, count(*) as n, sum(n_chars)::bigint as chars, min(n_chars) as least, max(n_chars) as most from {documents} group by source", "documents")
sql_query("op_agg_distinct", "select event_type, count(distinct user_id) as users, count(distinct cast(ts as date)) as days from {events} group by event_type", None, "events")
sql_query("op_agg_conditional", "select lang, count(*) filter (where quality = 0) as noisy, count(*) filter (where toxic = 1) as toxic from {documents} join {labels} using (doc_id) group by lang", None, "documents labels")
sql_query("op_agg_percentile", "select lang, percentile_cont(0.5) within group (order by n_chars) as median, percentile_cont(0.9) within group (order by n_chars) as p90 from {documents} group by lang", "select lang, quantile_cont(n_chars, 0.5) as median, quantile_cont(n_chars, 0.9) as p90 from {documents} group by lang", "documents")
sql_query("op_agg_mode", "select source, max_by(lang, struct(n, lang)) as lang from (select source, lang, count(*) as n from {documents} group by source, lang) group by source", "select source, arg_max(lang, (n, lang)) as lang from (select source, lang, count(*) as n from {documents} group by source, lang) group by source", "documents")
sql_query("op_agg_max_by", "select source, max_by(doc_id, struct(n_chars, doc_id)) as doc_id from {documents} group by source", "select source, arg_max(doc_id, (n_chars, doc_id)) as doc_id from {documents} group by source", "documents")
sql_query("op_agg_listagg", "select p_brand, listagg(distinct p_type, '|') within group (order by p_type) as types from {part} group by p_brand", "select p_brand, string_agg(distinct p_type, '|' order by p_type) as types from {part} group by p_brand", "part")


@query()
def op_agg_approx_distinct(spark, sf):
    return load(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.01).alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_hll"))


@query()
def op_agg_approx_topk(spark, sf):
    """A top-k report by a bounded sketch: five types of part by lines."""
    load(spark, sf, "lineitem").join(load(spark, sf, "part"), F.col("l_partkey") == F.col("p_partkey")).createOrReplaceTempView("v_typed")
    return spark.sql("select inline(approx_top_k(p_type, 5)) from v_typed")


_CUBED = "select c_mktsegment, o_orderpriority, count(*) as n from {orders} join {customer} on o_custkey = c_custkey group by "
sql_query("op_grouping_sets", _CUBED + "grouping sets ((c_mktsegment, o_orderpriority), (c_mktsegment), ())", None, "orders customer")
sql_query("op_cube_survey", _CUBED + "cube (c_mktsegment, o_orderpriority)", None, "orders customer")
sql_query("op_rollup_limits", "select lang, source, count(*) as n from {documents} group by rollup (lang, source)", None, "documents")


@query("select quality, count(*) filter (where lang = 'en') en, count(*) filter (where lang = 'de') de, count(*) filter (where lang = 'fr') fr, count(*) filter (where lang = 'es') es from documents join labels using (doc_id) group by 1")
def op_pivot_labels(spark, sf):
    j = load(spark, sf, "documents").select("doc_id", "lang").join(load(spark, sf, "labels"), "doc_id")
    return j.groupBy("quality").pivot("lang", ["en", "de", "fr", "es"]).count().fillna(0)


@query("select s_suppkey, 'name' element, s_name as value from supplier union all select s_suppkey, 'nation', s_nationkey::varchar from supplier")
def op_unpivot_elements(spark, sf):
    s = load(spark, sf, "supplier").select("s_suppkey", F.col("s_name").alias("name"), F.col("s_nationkey").cast("string").alias("nation"))
    return s.unpivot("s_suppkey", ["name", "nation"], "element", "value")


sql_query("op_window_rank", "select o_orderkey, rank() over (partition by o_custkey order by o_orderpriority) as r, dense_rank() over (partition by o_custkey order by o_orderpriority) as dr from {orders}", None, "orders")
sql_query("op_window_lag", "select event_id, lag(event_type) over (partition by user_id order by ts, event_id) as before, lead(event_type) over (partition by user_id order by ts, event_id) as after from {events}", None, "events")
sql_query("op_window_running", "select o_orderkey, round(sum(cast(o_totalprice as decimal(18, 2))) over (partition by o_custkey order by o_orderkey), 2) as running from {orders}", None, "orders")
sql_query("op_window_rows_frame", "select event_id, count(*) over (partition by user_id order by ts, event_id rows between 3 preceding and 1 following) as near from {events}", None, "events")
sql_query("op_window_range_frame", "select event_id, count(*) over (partition by user_id order by unix_micros(cast(ts as timestamp)) range between 86400000000 preceding and current row) as day_before from {events}", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as day_before from {events}", "events")
sql_query("op_window_ntile", "select doc_id, ntile(4) over (partition by lang order by n_chars, doc_id) as quarter from {documents}", None, "documents")
sql_query("op_topk_global", "select doc_id, n_chars from {documents} order by n_chars desc, doc_id limit 20", None, "documents")
sql_query("op_topk_per_label", "select doc_id, lang, r from (select doc_id, lang, row_number() over (partition by lang order by n_chars desc, doc_id) as r from {documents}) where r <= 5", None, "documents")
sql_query("op_limit_offset", "select doc_id, n_chars from {documents} order by n_chars desc, doc_id limit 20 offset 20", None, "documents")
for _n, _op in (("union", "union"), ("intersect", "intersect"), ("except", "except"), ("intersect_all", "intersect all"), ("except_all", "except all")):
    sql_query(f"op_set_{_n}", f"select p_brand, p_type, p_size % 10 as size from {{part}} where p_size <= 20 {_op} select p_brand, p_type, p_size % 10 as size from {{part}} where p_size > 20", None, "part")
sql_query("op_distinct", "select distinct lang, source from {documents}", None, "documents")


@query("select user_id, max(event_id) filter (where r = 1) event_id from (select *, row_number() over (partition by user_id order by ts desc, event_id desc) r from events) group by 1")
def op_drop_duplicates(spark, sf):
    """The latest row of each user: a maximum over a struct, so partial results combine before the shuffle."""
    return load(spark, sf, "events").groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


sql_query("op_string_functions", "select doc_id, initcap(lang) as lang, reverse(source) as rev, left(source, 3) as pre, lpad(lang, 4, '_') as pad, levenshtein(lang, 'en') as dist, length(trim(concat(' ', lang, ' '))) as n, repeat(lang, 2) as twice from {documents}", "select doc_id, upper(lang[1]) || lang[2:] as lang, reverse(source) as rev, left(source, 3) as pre, lpad(lang, 4, '_') as pad, levenshtein(lang, 'en')::int as dist, length(trim(concat(' ', lang, ' ')))::int as n, repeat(lang, 2) as twice from {documents}", "documents")


@query(f"select doc_id, regexp_matches(text, '[0-9]') has_digit, length(regexp_replace(text, '[0-9]', '', 'g')) without_digits, regexp_extract(text, '([A-Z][a-z]+)', 1) first_capital, {sql_normalize_name('source')} src from documents")
def op_regex_functions(spark, sf):
    return load(spark, sf, "documents").select("doc_id", F.col("text").rlike("[0-9]").alias("has_digit"), F.length(F.regexp_replace("text", "[0-9]", "")).cast("bigint").alias("without_digits"), F.regexp_extract("text", "([A-Z][a-z]+)", 1).alias("first_capital"), normalize_name("source").alias("src"))


@query("select page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) host, regexp_extract(url, '^([a-z]+):', 1) protocol, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) path, nullif(regexp_extract(url, '[?]([^#]*)', 1), '') query from pages")
def op_url_functions(spark, sf):
    p = lambda part: F.parse_url("url", F.lit(part))
    return load(spark, sf, "pages").select("page_id", p("HOST").alias("host"), p("PROTOCOL").alias("protocol"), p("PATH").alias("path"), p("QUERY").alias("query"))


sql_query("op_date_functions", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, day(last_day(o_orderdate)) as last, datediff(cast('2002-01-01' as date), cast(o_orderdate as date)) as days, cast(cast(date_trunc('month', o_orderdate) as date) as string) as month_start, cast(add_months(o_orderdate, 1) as string) as next_month from {orders}", "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, day(last_day(o_orderdate))::int as last, date_diff('day', o_orderdate::date, date '2002-01-01')::int as days, date_trunc('month', o_orderdate)::date::varchar as month_start, (o_orderdate + interval 1 month)::date::varchar as next_month from {orders}", "orders")
sql_query("op_math_functions", "select l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) as root, floor(l_extendedprice / 1000) as k, abs(l_discount - 0.05) < 0.001 as mid, round(ln(1 + l_quantity), 6) as lg, pmod(l_orderkey, 7) as rest, least(l_quantity, 10.0) as capped, width_bucket(l_quantity, 0, 50, 5) as bucket from {lineitem}", "select l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) as root, floor(l_extendedprice / 1000)::bigint as k, abs(l_discount - 0.05) < 0.001 as mid, round(ln(1 + l_quantity), 6) as lg, l_orderkey % 7 as rest, least(l_quantity, 10.0) as capped, case when l_quantity >= 50 then 6 else 1 + floor(l_quantity / 10)::bigint end as bucket from {lineitem}", "lineitem")
sql_query("op_hash_functions", "select doc_id, md5(text) as m, sha2(text, 256) as s, cast(conv(substring(md5(text), 1, 15), 16, 10) as bigint) as h60 from {documents}", "select doc_id, md5(text) as m, sha256(text) as s, ('0x' || substr(md5(text), 1, 15))::bigint as h60 from {documents}", "documents")


@query("select vec_id, len(embedding)::int n, round(list_max(embedding)::double, 6) most, round(list_min(embedding)::double, 6) least, list_sort(embedding)[1] = list_min(embedding) sorted_ok, len(list_distinct(embedding))::int distincts from embeddings")
def op_array_functions(spark, sf):
    return load(spark, sf, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.array_max("embedding").cast("double"), 6).alias("most"), F.round(F.array_min("embedding").cast("double"), 6).alias("least"), (F.array_sort("embedding")[0] == F.array_min("embedding")).alias("sorted_ok"), F.size(F.array_distinct("embedding")).alias("distincts"))


@query("select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) norm2, len(list_filter(embedding, lambda x: x > 0))::int positive, round(list_dot_product(embedding::double[], list_reverse(embedding)::double[]), 6) mirrored from embeddings")
def op_array_higher_order(spark, sf):
    e = F.transform("embedding", lambda x: x.cast("double"))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    return load(spark, sf, "embeddings").select("vec_id", F.round(total(F.transform(e, lambda x: x * x)), 6).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(total(F.zip_with(e, F.reverse(e), lambda x, y: x * y)), 6).alias("mirrored"))


@query("select source, map_keys(m)[1] first_lang, len(map_keys(m))::int langs, list_sum(map_values(m))::bigint docs from (select source, map_from_entries(list((lang, n) order by lang)) m from (select source, lang, count(*) n from documents group by 1, 2) group by 1)")
def op_map_functions(spark, sf):
    n = load(spark, sf, "documents").groupBy("source", "lang").agg(F.count("*").alias("n"))
    m = n.groupBy("source").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("lang", "n")))).alias("m"))
    return m.select("source", F.map_keys("m")[0].alias("first_lang"), F.size(F.map_keys("m")).alias("langs"), F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("docs"))


@query("select s_suppkey, s_name as name, s_nationkey nation, s_name || '@' || s_nationkey as tag from supplier")
def op_struct_functions(spark, sf):
    s = load(spark, sf, "supplier").select("s_suppkey", F.struct(F.col("s_name").alias("name"), F.col("s_nationkey").alias("nation")).alias("maker"))
    s = s.withColumn("maker", F.col("maker").withField("tag", F.concat_ws("@", "maker.name", F.col("maker.nation").cast("string"))))
    return s.select("s_suppkey", "maker.*")


sql_query("op_json_functions", "select event_id, cast(get_json_object(props, '$.k') as int) as k, json_array_length(concat('[', props, ']')) as n, json_object_keys(props)[0] as first_key from {events}", "select event_id, (props->>'$.k')::int as k, json_array_length('[' || props || ']')::int as n, json_keys(props)[1] as first_key from {events}", "events")
sql_query("op_json_variant", "select event_id, variant_get(try_parse_json(props), '$.k', 'int') as k, try_parse_json(concat('{{', props)) is null as broken_is_null from {events}", "select event_id, (props->>'$.k')::int as k, not json_valid('{{' || props) as broken_is_null from {events}", "events")


@query("select page_id, link from (select page_id, unnest(case when len(l) = 0 then [null] else l end) link from (select page_id, regexp_extract_all(html, 'href=\"(https?:[^\"]*)\"', 1) l from pages))")
def op_explode_outer(spark, sf):
    return load(spark, sf, "pages").select("page_id", F.explode_outer(F.expr("regexp_extract_all(html, 'href=\"(https?:[^\"]*)\"', 1)")).alias("link"))


@query(f"select token, count(*) n, min(pos) first_pos from (select unnest(w) token, unnest(range(0, len(w)))::int pos from (select {sql_tokens()} w from documents)) group by 1")
def op_posexplode(spark, sf):
    return load(spark, sf, "documents").select(F.posexplode(tokens()).alias("pos", "token")).groupBy("token").agg(F.count("*").alias("n"), F.min("pos").alias("first_pos"))


sql_query("op_subquery_scalar", "select doc_id, n_chars from {documents} where n_chars > (select 4 * avg(n_chars) from {documents})", None, "documents")
sql_query("op_subquery_exists", "select c_custkey from {customer} where not exists (select 1 from {orders} where o_custkey = c_custkey and o_totalprice > 250000)", None, "customer orders")
sql_query("op_subquery_correlated", "select doc_id, lang, n_chars from {documents} d where n_chars = (select max(n_chars) from {documents} e where e.lang = d.lang)", None, "documents")
sql_query("op_cte", "with per as (select o_custkey, count(*) as n from {orders} group by o_custkey), hist as (select n, count(*) as customers from per group by n) select n, customers from hist", None, "orders")


@query(f"select p_partkey, {sql_normalize_name('p_name')} as name from part")
def op_udf_arrow(spark, sf):
    from catalogflow.functions.udfs import normalize_udf

    return load(spark, sf, "part").select("p_partkey", normalize_udf("p_name").alias("name"))


@query("""with recursive n as (select doc_id // 100 grp, doc_id ord, n_chars chars, row_number() over (partition by doc_id // 100 order by doc_id) i from documents),
pack as (select grp, ord, i, 1 prompt_no, chars used from n where i = 1 union all select n.grp, n.ord, n.i, case when p.used + n.chars <= 15000 then p.prompt_no else p.prompt_no + 1 end, case when p.used + n.chars <= 15000 then p.used + n.chars else n.chars end from pack p join n on n.grp = p.grp and n.i = p.i + 1)
select grp, ord, prompt_no from pack""")
def op_udf_grouped(spark, sf):
    from catalogflow.functions.udfs import pack_group

    rows = load(spark, sf, "documents").select(F.expr("doc_id div 100").alias("grp"), F.col("doc_id").alias("ord"), F.col("n_chars").alias("chars"))
    return rows.groupBy("grp").applyInPandas(lambda pdf: pack_group(pdf, 15_000), "grp bigint, ord bigint, prompt_no int")


@query("select lang, round(avg(case when g + p = 0 then 1 else 2.0 * (g * p) / (g + p) end), 6) f1 from (select lang, toxic g, (regexp_matches(text, 'idiot|scum|moron|clown'))::int p from documents join labels using (doc_id)) group by 1")
def op_udaf(spark, sf):
    from catalogflow.functions.udfs import mean_f1

    j = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id").select("lang", F.col("toxic").alias("g"), F.col("text").rlike("idiot|scum|moron|clown").cast("int").alias("p"))
    return j.groupBy("lang").agg(mean_f1("g", "p").alias("f1")).withColumn("f1", F.round("f1", 6))


@query("""select page_id, 'title' kind, unnest(regexp_extract_all(html, '<title>([^<]*)</title>', 1)) as value from pages union all select page_id, 'href', unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) from pages""")
def op_udtf(spark, sf):
    from catalogflow.functions.udfs import PageElements

    spark.udtf.register("page_elements_udtf", PageElements)
    load(spark, sf, "pages").createOrReplaceTempView("v_pages")
    return spark.sql("select page_id, e.kind, e.value from v_pages, lateral page_elements_udtf(html) e")


@query("select f, count(*) n, sum(s_suppkey)::bigint keys, round(sum(s_acctbal), 2) balance from supplier, (values ('csv'), ('json'), ('orc'), ('parquet'), ('partitioned')) x(f) group by 1")
def op_source_roundtrip(spark, sf):
    s, out = load(spark, sf, "supplier"), None
    for f in ("csv", "json", "orc", "parquet", "partitioned"):
        path = fresh_path(spark, f"roundtrip-{f}")
        if f == "partitioned":
            s.write.partitionBy("s_nationkey").parquet(path)
            back = spark.read.schema(s.schema).parquet(path)
        else:
            s.write.format(f).save(path)
            back = spark.read.format(f).schema(s.schema).load(path)
        row = back.agg(F.lit(f).alias("f"), F.count("*").alias("n"), F.sum("s_suppkey").alias("keys"), F.round(F.sum("s_acctbal"), 2).alias("balance"))
        out = row if out is None else out.union(row)
    return out


@query("select event_id // 1000 part, op, count(*) n from (select event_id, case when event_id % 3 = 0 then 'update' else 'insert' end op from events) group by 1, 2")
def op_portal_dry_run(spark, sf):
    """Changes go to the portal's sink as a dry run, then are counted."""
    from catalogflow.sources import portal

    portal.register(spark)
    changes = load(spark, sf, "events").select(F.col("event_id").alias("item_id"), F.expr("case when event_id % 3 = 0 then 'update' else 'insert' end").alias("op"), F.sha2("props", 256).alias("digest"), F.col("props").alias("body"))
    changes.write.format("portal").mode("append").option("dry_run", "true").save()
    return changes.groupBy(F.expr("item_id div 1000").alias("part"), "op").agg(F.count("*").alias("n"))


def _micros(df):
    return df.withColumn("started", F.unix_micros("started"))


@query("select epoch_us(time_bucket(interval 6 hours, ts, timestamp '1970-01-01')) started, event_type, count(*) n, round(sum(value), 2) as value from events group by 1, 2")
def op_stream_tumbling(spark, sf):
    return _micros(S.finish(S.tumbling(S.event_stream(spark, sf), "6 hours"), "complete"))


@query("select epoch_us(d) started, event_type, count(*) n, round(sum(value), 2) as value from events, (values (0), (1)) k(k), lateral (select date_trunc('day', ts) - k * interval 1 day d) group by 1, 2")
def op_stream_sliding(spark, sf):
    return _micros(S.finish(S.tumbling(S.event_stream(spark, sf), "2 days", "1 day"), "complete"))


@query("""with b as (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 6 hours then 0 else 1 end nw from events), s as (select *, sum(nw) over (partition by user_id order by ts, event_id rows unbounded preceding) sid from b)
select user_id, epoch_us(min(ts)) started, count(*) n from s group by user_id, sid""")
def op_stream_session(spark, sf):
    return _micros(S.finish(S.session_counts(S.event_stream(spark, sf)), "complete"))


@query("select distinct event_id, user_id from events")
def op_stream_dedup(spark, sf):
    """Events that arrive twice count once; state is dropped as the watermark passes."""
    e = S.event_stream(spark, sf).select("event_id", "user_id", F.explode(F.array("ts", "ts")).alias("ts"))
    return S.finish(e.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


@query("select event_id, c_mktsegment from events join customer on user_id = c_custkey")
def op_stream_join(spark, sf):
    return S.finish(S.event_stream(spark, sf).join(load(spark, sf, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("""with m as (select max(ts) filter (where event_id % 3 = 0) - interval 1 day early, max(ts) - interval 1 day final from events), e as (select date_trunc('day', ts) d, event_id % 3 b from events),
t as (select d, count(*) n from e, m where b < 2 or d + interval 1 day > early group by 1) select epoch_us(d) started, n from t, m where d + interval 1 day <= final""")
def op_stream_late_data(spark, sf):
    """Three batches, by event number: of the third, what the first one's watermark closed in the second is dropped; open windows aren't given."""
    path = fresh_path(spark, "late")
    e = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    for part in range(3):
        e.where(F.col("event_id") % 3 == part).coalesce(1).write.mode("append").parquet(path)
    src = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    w = src.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("started"), "n")
    return _micros(S.finish(w))
