"""Queries: load, monitoring, survey, streams, and the whole process."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_normalize_name
from catalogflow.operators import classify as C
from catalogflow.operators import dedup as D
from catalogflow.operators import extract as X
from catalogflow.operators import load as L
from catalogflow.operators import metadata as MD
from catalogflow.operators import monitor as W
from catalogflow.plans.classify import GOLD, SCORES
from catalogflow.plans.dedup import CASCADE
from catalogflow.plans.extraction import CAT, CONTACTS, NAME, REST
from catalogflow.plans.registry import load, query
from catalogflow.session import fresh_path, staged
from catalogflow.streaming import traffic as S


def _versions(spark, sf):
    """The portal as it is (all parts) and as it shall be: some gone, some dearer, some new."""
    p = load(spark, sf, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_name").alias("name"), F.col("p_type").alias("type"), F.col("p_retailprice").cast("decimal(12,2)").alias("price"))
    new = p.where("item_id % 11 <> 0").withColumn("price", F.expr("cast(case when item_id % 7 = 0 then price + 1 else price end as decimal(12,2))"))
    new = new.union(p.where("item_id % 13 = 0").select(F.expr("item_id + 1000000000"), "name", "type", "price"))
    cols = ["name", "type", "price"]
    return L.payloads(p, cols), L.payloads(new, cols)


_JS = """'{"name":"' || nm || '","type":"' || typ || '","price":' || price || '}'"""
VERSIONS = f"""p as (select p_partkey item_id, p_name nm, p_type typ, p_retailprice::decimal(12, 2) price from part),
v1 as (select item_id, {_JS} body from p), n as (select item_id, nm, typ, (case when item_id % 7 = 0 then price + 1 else price end)::decimal(12, 2) price from p where item_id % 11 <> 0 union all select item_id + 1000000000, nm, typ, price from p where item_id % 13 = 0),
v2 as (select item_id, {_JS} body from n)"""
PLAN = "plan as (select coalesce(a.item_id, b.item_id) item_id, case when b.body is null then 'insert' when a.body is null then 'delete' when a.body = b.body then 'same' else 'update' end op from v2 a full join v1 b on a.item_id = b.item_id)"


@query(f"with {VERSIONS} select item_id, body, sha256(body) digest from v2")
def load_payloads(spark, sf):
    return _versions(spark, sf)[1]


@query(f"with {VERSIONS}, {PLAN} select item_id, op from plan")
def load_plan(spark, sf):
    old, new = _versions(spark, sf)
    return L.plan_sync(new, old)


@query(f"with {VERSIONS}, {PLAN} select item_id, sha256(body) digest from v2")
def load_apply(spark, sf):
    old, new = _versions(spark, sf)
    return L.apply_sync(old, new, L.plan_sync(new, old)).select("item_id", "digest")


@query("""with c as (select p_partkey item_id, p_type coll from part union all select p_partkey, p_brand from part where p_partkey % 17 = 0), e as (select distinct l_partkey + case when l_linenumber = 7 then 1000000 else 0 end item_id from lineitem)
select item_id, 'several collections' problem from c group by 1 having count(distinct coll) > 1 union all select item_id, 'no such item' from e where item_id not in (select p_partkey from part)""")
def membership_violations(spark, sf):
    part = load(spark, sf, "part")
    c = part.select(F.col("p_partkey").alias("item_id"), F.col("p_type").alias("collection")).union(part.where("p_partkey % 17 = 0").select("p_partkey", "p_brand"))
    e = load(spark, sf, "lineitem").select(F.expr("l_partkey + case when l_linenumber = 7 then 1000000 else 0 end").alias("item_id"))
    return L.check_membership(c, e, part.select(F.col("p_partkey").alias("item_id")))


@query(f"with {SCORES} select doc_id, sum(score)::bigint score from picked where label in ('germanic, en', 'noisy') group by 1 having count(distinct label) = 2 order by 2 desc, 1 limit 20")
def faceted_search(spark, sf):
    return L.search(C.select_labels(C.expert_scores(load(spark, sf, "documents"))), ["germanic, en", "noisy"])


@query(f"""with {SCORES}, c as ({CONTACTS}), rg as (select doc_id, min(r_name) region from (select doc_id, cast(substr(value, 5, 3) as int) prefix from c where kind = 'phone') join nation on prefix % 25 = n_nationkey and prefix // 100 not in (5, 6) join region on n_regionkey = r_regionkey group by 1)
select 'label, catalogue, text' facets, doc_id, score from (select p.doc_id, sum(score)::bigint score from picked p join documents d using (doc_id) where label = 'germanic, en' and {CAT} = 2 and contains(lower({NAME} || ' ' || {REST}), 'the') group by 1 order by 2 desc, 1 limit 20)
union all select 'region', doc_id, 0 from (select doc_id from rg where region = 'ASIA' order by 1 limit 20)""")
def faceted_search_wide(spark, sf):
    """By label, catalogue and text; and by region."""
    docs = load(spark, sf, "documents")
    items = X.run_extraction(docs, load(spark, sf, "nation"), load(spark, sf, "region"))
    labels = C.select_labels(C.expert_scores(docs))
    one = L.search_items(items, labels, ["germanic, en"], catalog=2, text="The").select(F.lit("label, catalogue, text").alias("facets"), "doc_id", "score")
    return one.union(L.search_items(items, region="ASIA").select(F.lit("region"), "doc_id", "score"))


_ESC = "replace(replace(replace(replace({}, '&', '&amp;'), '<', '&lt;'), '>', '&gt;'), '\"', '&quot;')"


@query(f"""with i as (select doc_id, {NAME} nm, {REST} ds, {CAT} cat from documents) select doc_id item_id, md5(to_json({{'metadata': list_filter([{{'property': 'description', 'values': [ds]}}, {{'property': 'title', 'values': [nm]}}], lambda x: x['values'][1] <> ''),
'html': '<article><h1>' || {_ESC.format('nm')} || '</h1><p>' || {_ESC.format('ds')} || '</p></article>', 'collection': 'catalogue ' || cat}})::varchar) body from i where nm <> '' or ds <> ''""")
def load_item_payloads(spark, sf):
    """Metadata, layout and collection of text items as the portal gets them."""
    d = X.text_elements(X.with_catalog(load(spark, sf, "documents"))).withColumnRenamed("doc_id", "item_id").where("name <> '' or description <> ''")
    meta = MD.to_metadata(d.select("item_id", "name", "description"), [("title", ["name"]), ("description", ["description"])])
    members = d.select("item_id", F.concat(F.lit("catalogue "), F.col("catalog_id").cast("string")).alias("collection"))
    return L.item_payloads(d, meta, MD.render_html(d), members).select("item_id", F.md5("body").alias("body"))


DAILY = "select ts::date::varchar as day, event_type, count(*) n, count(distinct user_id) users, round(sum(value), 2) as value from events group by 1, 2"


@query(DAILY)
def traffic_daily(spark, sf):
    return W.traffic_by_period(load(spark, sf, "events")).withColumn("day", F.col("day").cast("string"))


@query("select d::date::varchar as day, count(distinct user_id) users, count(*) n from (select unnest(range(0, 7)) k, * from events) e, (select 1) x, lateral (select ts::date - k::int d) group by 1")
def traffic_rolling(spark, sf):
    return W.rolling_users(load(spark, sf, "events")).withColumn("day", F.col("day").cast("string"))


SESSIONS = """b as (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 6 hours then 0 else 1 end nw from events),
s as (select *, sum(nw) over (partition by user_id order by ts, event_id rows unbounded preceding) sid from b), ses as (select user_id, sid, min(ts) started, max(ts) ended, count(*) n from s group by 1, 2)"""


@query(f"with {SESSIONS} select user_id, epoch_us(started) started, epoch_us(ended) ended, n from ses")
def traffic_sessions(spark, sf):
    return W.sessions(load(spark, sf, "events")).select("user_id", F.unix_micros("started").alias("started"), F.unix_micros("ended").alias("ended"), "n")


@query(f"with d as ({DAILY}), m as (select *, avg(n) over w mean, stddev_samp(n) over w sd from d window w as (partition by event_type order by day rows between 7 preceding and 1 preceding)) select day, event_type, n, round(mean, 6) mean, coalesce(abs(n - mean) > 2.0 * sd, false) alert from m")
def traffic_alerts(spark, sf):
    return W.traffic_alerts(W.traffic_by_period(load(spark, sf, "events"))).withColumn("day", F.col("day").cast("string"))


STREAMED = "select epoch_us(date_trunc('day', ts)) started, event_type, count(*) n, round(sum(value), 2) as value from events group by 1, 2"


@query(STREAMED)
def stream_traffic(spark, sf):
    """Complete mode over the stored events: equal to the batch result."""
    return S.finish(S.tumbling(S.event_stream(spark, sf)), "complete").withColumn("started", F.unix_micros("started"))


@query("""with e as (select *, row_number() over (partition by user_id order by ts, event_id) r from events), v as (select user_id, min(r) r from e where event_type = 'view' group by 1),
c as (select user_id, min(e.r) r from e join v using (user_id) where event_type = 'click' and e.r > v.r group by 1), p as (select user_id, min(e.r) r from e join c using (user_id) where event_type = 'purchase' and e.r > c.r group by 1)
select user_id, ((v.r is not null)::int + (c.r is not null)::int + (p.r is not null)::int)::int step from (select distinct user_id from events) left join v using (user_id) left join c using (user_id) left join p using (user_id)""")
def stream_funnel(spark, sf):
    return S.finish(S.funnel(S.event_stream(spark, sf)), "update", ["user_id"])


@query("select event_id item_id, event_type body from (select *, row_number() over (partition by user_id order by ts desc, md5(event_id::varchar) desc) r from events) where r = 1")
def stream_load(spark, sf):
    """The newest event of each user, kept as a state table by batches."""
    src = S.event_stream(spark, sf).select("user_id", F.col("event_id").alias("item_id"), F.col("event_type").alias("body"), F.md5(F.col("event_id").cast("string")).alias("digest"), "ts")
    state = fresh_path(spark, "state")
    L.stream_load(src, state, fresh_path(spark, "state-check"), key="user_id").awaitTermination()
    return L.read_state(spark, state, src.schema).select("item_id", "body")


SURVEY = "sv as (select c_mktsegment profession, cast(substr(o_orderpriority, 1, 1) as int) likelihood, l_returnflag artefact, case when l_linenumber % 6 = 0 then null else ceil(l_quantity / 5)::int end grade from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey)"


def _survey(spark, sf):
    return W.survey_rows(load(spark, sf, "customer"), load(spark, sf, "orders"), load(spark, sf, "lineitem"))


@query(f"with {SURVEY} select artefact, count(*) n, count(grade) answered, round(count(*) filter (where grade >= 7) / count(grade), 6) good_share, round(avg(grade), 6) mean from sv group by 1")
def survey_grades(spark, sf):
    return _survey(spark, sf).groupBy("artefact").agg(F.count("*").alias("n"), F.count("grade").alias("answered"), F.round(F.count_if(F.col("grade") >= 7) / F.count("grade"), 6).alias("good_share"), F.round(F.avg("grade"), 6).alias("mean"))


@query(f"with {SURVEY} select profession, likelihood, count(*) n from sv group by cube (profession, likelihood)")
def survey_likelihood(spark, sf):
    return _survey(spark, sf).cube("profession", "likelihood").agg(F.count("*").alias("n"))


@query(f"with {SURVEY} select profession, artefact, count(grade) answered from sv group by cube (profession, artefact)")
def survey_professions(spark, sf):
    return _survey(spark, sf).cube("profession", "artefact").agg(F.count("grade").alias("answered"))


@query("select p_partkey item_id, p_brand producer, coalesce(r, '') related from part left join (select l_partkey, string_agg(distinct s_name, '|' order by s_name) r from lineitem join supplier on l_suppkey = s_suppkey group by 1) on l_partkey = p_partkey")
def item_enrichment(spark, sf):
    rel = load(spark, sf, "lineitem").join(load(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select(F.col("l_partkey").alias("item_id"), F.col("s_name").alias("related"))
    items = load(spark, sf, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("producer"))
    return L.enrich(items, rel, "item_id").withColumn("related", F.coalesce(F.array_join("related", "|"), F.lit("")))


@query(f"""with {GOLD}, {SCORES}, {CASCADE}, tx as (select doc_id, min(doc_id) over (partition by md5(text)) f, cast(substr(source, 4) as int) % 5 c from documents), sv as (select doc_id from tx where doc_id = f and c < 4)
select 1 as step, 'documents' stage, count(*) n from documents union all select 2, 'tool items', count(*) from tx where c < 4 union all select 3, 'distinct texts', count(*) from sv
union all select 4, 'labels chosen', count(*) from picked join sv using (doc_id) union all select 5, 'structured items', count(*) from items union all select 6, 'structured items left', count(*) from items where id not in (select greatest(a, b) from dups)""")
def pipeline_summary(spark, sf):
    """Counts after every stage: tool items, exact copies gone, labels chosen; structured items before and after the cascade."""
    docs = X.with_catalog(load(spark, sf, "documents"))
    tools = docs.where("kind = 'tool'")
    first = D.exact_duplicates(docs.select("doc_id", "text")).where("doc_id = first_id").select("doc_id")
    left = staged(tools.join(first, "doc_id", "left_semi"), "summary-items")
    picked = C.select_labels(C.expert_scores(left))
    items = D.items_of(load(spark, sf, "part"))
    rest = D.remove_duplicates(items, D.find_duplicates(items, D.associations(spark)))
    out = None
    for i, (name, df) in enumerate((("documents", docs), ("tool items", tools), ("distinct texts", left), ("labels chosen", picked), ("structured items", items), ("structured items left", rest)), 1):
        row = df.agg(F.lit(i).alias("step"), F.lit(name).alias("stage"), F.count("*").alias("n"))
        out = row if out is None else out.union(row)
    return out
