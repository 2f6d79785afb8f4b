"""Queries: variants and ablations beside the main methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_hash60, sql_tokens, tokens
from catalogflow.operators import classify as C
from catalogflow.operators import extract as X
from catalogflow.operators import metrics as M
from catalogflow.operators import probe as P
from catalogflow.plans.classify import GOLD, SCORES, SETS, SHOTS, _base, _docs, _gold, _labelled, _sets, _shots, measured
from catalogflow.plans.extraction import CAT, CONTACTS, NAME, REST
from catalogflow.plans.registry import load, query


@query(f"""with c as ({CONTACTS}), k as (select doc_id, {', '.join(f"array_to_string(list_sort(list(distinct value) filter (kind = '{x}')), '|') {x}" for x in ('email', 'ip', 'phone', 'url'))} from c group by 1),
r as (select doc_id, min(r_name) region from (select doc_id, cast(substr(value, 5, 3) as int) prefix from c where kind = 'phone') join nation on prefix % 25 = n_nationkey and prefix // 100 not in (5, 6) join region on n_regionkey = r_regionkey group by 1)
select d.doc_id, {CAT} catalog_id, case when {CAT} = 4 then 'practice' else 'tool' end kind, {NAME} as name, md5({REST}) description, lang, coalesce(email, '') email, coalesce(ip, '') ip, coalesce(phone, '') phone, coalesce(url, '') url, region
from documents d left join k using (doc_id) left join r using (doc_id)""")
def extraction_items(spark, sf):
    """The whole extraction process over all documents."""
    items = X.run_extraction(_docs(spark, sf), load(spark, sf, "nation"), load(spark, sf, "region"))
    return items.withColumn("description", F.md5("description")).withColumns({k: F.coalesce(F.array_join(k, "|"), F.lit("")) for k in ("email", "ip", "phone", "url")})


@query(f"with {GOLD}, {SHOTS} select count(*) calls, sum(length(prompt))::bigint chars, max(length(prompt)) longest from shots")
def call_budget(spark, sf):
    return M.call_budget(_shots(spark, sf))


@query("select 'added' change, 'condition' domain, 'broken' as label union all select 'removed', 'condition', 'noisy'")
def taxonomy_diff(spark, sf):
    old = spark.createDataFrame([(d, x) for d, ls in C.TX1.items() for x in ls], "domain string, label string")
    new = old.withColumn("label", F.when(F.col("label") == "noisy", "broken").otherwise(F.col("label")))
    return C.taxonomy_diff(old, new)


@query(f"""with {SCORES}, hit as (select doc_id from documents where contains(lower(text), 'idiot')), facet as (select doc_id from picked where label = 'abusive'), truth as (select doc_id from labels where toxic = 1),
f as (select 'text' method, doc_id from hit union all select 'facet', doc_id from facet), j as (select f.* from f join labels using (doc_id))
select method, count(*) found, count(*) filter (where doc_id in (select doc_id from truth)) relevant, round(count(*) filter (where doc_id in (select doc_id from truth)) / count(*), 6) as precision, round(count(*) filter (where doc_id in (select doc_id from truth)) / (select count(*) from truth), 6) recall from j group by 1""")
def search_text_or_facet(spark, sf):
    """Search by a word of the text against search by label, judged by the gold labels."""
    docs, labels = _docs(spark, sf), load(spark, sf, "labels")
    text = docs.where(F.contains(F.lower("text"), F.lit("idiot"))).select(F.lit("text").alias("method"), "doc_id")
    facet = C.select_labels(C.expert_scores(docs)).where("label = 'abusive'").select(F.lit("facet").alias("method"), "doc_id")
    total = labels.agg(F.count(F.expr("case when toxic = 1 then 1 end")).alias("t"))
    g = text.union(facet).join(labels, "doc_id").groupBy("method").agg(F.count("*").alias("found"), F.count(F.expr("case when toxic = 1 then 1 end")).alias("relevant"))
    return g.crossJoin(F.broadcast(total)).select("method", "found", "relevant", F.round(F.col("relevant") / F.col("found"), 6).alias("precision"), F.round(F.col("relevant") / F.col("t"), 6).alias("recall"))


def _learned_sql(share: int) -> str:
    return f"""select {share} train_tenths, count(*) items, round(avg((p.label = g.label)::int), 6) accuracy from (with tok as (select doc_id, unnest(list_distinct({sql_tokens()})) token from documents where doc_id in (select doc_id from labels)),
part as (select doc_id, {sql_hash60("doc_id::varchar")} % 10 part from lab), tr as (select g.doc_id, g.label from gold g join part using (doc_id) where domain = 'conduct' and part < {share}), n as (select label, count(*) n from tr group by 1),
t as (select label, token, count(*) df from tok join tr using (doc_id) group by 1, 2), e as (select token, sum(df) all_df from t group by 1),
o as (select label, token, round(ln((df + 0.5) / (n + 1)) - ln((all_df - df + 0.5) / ((select sum(n) from n) - n + 1)), 6) w from t join e using (token) join n using (label) where df >= 2),
lex as (select * from o qualify row_number() over (partition by label order by w desc, token) <= 20), s as (select doc_id, label, round(sum(w), 6) w from tok join lex using (token) group by 1, 2),
best as (select doc_id, arg_max(label, (w, label)) found from s group by 1), prior as (select arg_max(label, (n, label)) prior from n)
select l.doc_id, coalesce(found, prior) as label from lab l join part using (doc_id) left join best using (doc_id), prior where part >= 7) p join gold g on g.doc_id = p.doc_id and g.domain = 'conduct'"""


@query(f"with {GOLD} " + " union all ".join(f"select * from ({_learned_sql(s)})" for s in (1, 3, 7)))
def learning_curve(spark, sf):
    """Accuracy in the conduct domain of a lexicon learnt on one, three and seven tenths of the labelled items, tested on the last three."""
    gold = _gold(spark, sf).where("domain = 'conduct'")
    docs = _labelled(spark, sf).withColumn("part", P.hash60("cast(doc_id as string)") % 10)
    out = None
    for share in (1, 3, 7):
        train = docs.where(F.col("part") < share)
        own = gold.join(train.select("doc_id"), "doc_id", "left_semi")
        prior = own.groupBy("label").agg(F.count("*").alias("n")).agg(F.max(F.struct("n", "label"))["label"].alias("prior"))
        pred = C.lexicon_labels(docs.where("part >= 7"), C.learn_lexicon(train, own, "conduct"), prior)
        got = pred.join(gold.select("doc_id", F.col("label").alias("g")), "doc_id").agg(F.lit(share).alias("train_tenths"), F.count("*").alias("items"), F.round(F.avg((F.col("label") == F.col("g")).cast("double")), 6).alias("accuracy"))
        out = got if out is None else out.union(got)
    return out


@query(f"""with {SETS}, {SCORES}, w as (select doc_id, list_distinct({sql_tokens()}) w from documents where doc_id in (select doc_id from labels)), lib as (select w.* from w join sa using (doc_id)), rest as (select * from w where doc_id not in (select doc_id from sa)),
s as (select a.doc_id, b.doc_id shot_id, round(len(list_intersect(a.w, b.w)) / greatest(1, len(a.w) + len(b.w) - len(list_intersect(a.w, b.w))), 6) score from rest a, lib b),
rk as (select *, row_number() over (partition by doc_id order by score desc, shot_id) r from s), v as (select k, rk.doc_id, g.domain, g.label, count(*) c, min(r) first from rk, (values (1), (3), (5)) x(k), gold g where r <= k and g.doc_id = rk.shot_id group by 1, 2, 3, 4),
p as (select * from v qualify row_number() over (partition by k, v.doc_id, domain order by c desc, first, label) = 1)
select k shots, p.domain, count(*) items, round(avg((p.label = g.label)::int), 6) f1 from p join gold g on g.doc_id = p.doc_id and g.domain = p.domain group by 1, 2
union all select 0, domain, count(*), round(avg(f1), 6) from (with {measured('picked')} select * from item_m where doc_id not in (select doc_id from sa)) group by 2""")
def shots_sweep(spark, sf):
    """Labels voted by the 1, 3 or 5 nearest shots of set A, beside no shots (the expert's rules), on all other labelled items."""
    from pyspark.sql import Window

    gold = _gold(spark, sf)
    a = _sets(spark, sf).where("dataset = 'A'").select("doc_id")
    docs = _labelled(spark, sf)
    rest = docs.join(a, "doc_id", "left_anti")
    near = C.retrieve_shots(rest, docs.join(a, "doc_id", "left_semi"), 5)
    shots = near.join(gold.withColumnRenamed("doc_id", "shot_id"), "shot_id")
    k = F.explode(F.array(F.lit(1), F.lit(3), F.lit(5))).alias("shots")
    v = shots.select("*", k).where("rank <= shots").groupBy("shots", "doc_id", "domain", "label").agg(F.count("*").alias("c"), F.min("rank").alias("first"))
    w = Window.partitionBy("shots", "doc_id", "domain").orderBy(F.desc("c"), "first", "label")
    p = v.withColumn("r", F.row_number().over(w)).where("r = 1").join(gold.select("doc_id", "domain", F.col("label").alias("g")), ["doc_id", "domain"])
    few = p.groupBy("shots", "domain").agg(F.count("*").alias("items"), F.round(F.avg((F.col("label") == F.col("g")).cast("double")), 6).alias("f1"))
    own = gold.join(a, "doc_id", "left_anti")
    zero = M.item_scores(own, C.select_labels(C.expert_scores(rest)), _base(own), ["doc_id"]).groupBy("domain").agg(F.count("*").alias("items"), F.round(F.avg("f1"), 6).alias("f1"))
    return few.unionByName(zero.withColumn("shots", F.lit(0)))
