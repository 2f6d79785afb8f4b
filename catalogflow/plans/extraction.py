"""Queries: extraction."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_normalize_name
from catalogflow.operators import extract as X
from catalogflow.plans.registry import load, query

CAT = "cast(substr(source, 4) as int) % 5"
FAMILY = "case when catalog_id in (0, 1) then 'S' when catalog_id in (2, 3) then 'A' else 'P' end"
NAME = r"trim(regexp_extract(text, '^([^.\n]*)', 1))"
REST = r"trim(substr(text, length(regexp_extract(text, '^([^.\n]*)', 1)) + 2))"


@query(f"""with d as (select {CAT} catalog_id, lang, source from documents)
select catalog_id, {FAMILY} family, case when catalog_id = 4 then 1 else catalog_id % 2 + 1 end edition, case when catalog_id = 4 then 'practice' else 'tool' end kind,
count(*) items, count(distinct lang) langs, count(distinct source) sources from d group by 1""")
def catalog_registry(spark, sf):
    return X.catalogs(load(spark, sf, "documents"))


@query(f"""with d as (select {CAT} catalog_id, text, {NAME} nm, {REST} ds from documents),
f as (select {FAMILY} family, * from d),
c as (select family, count(*) a, count(*) filter (where nm <> '') n, count(*) filter (where ds <> '') d, count(*) filter (where regexp_matches(text, '{X.PHONE}') or regexp_matches(text, '{X.EMAIL}')) p, count(*) filter (where regexp_matches(text, '{X.LINK}')) u from f group by 1),
m(element, family, mode) as (values {', '.join(f"('{e}', '{f}', '{m}')" for e, *modes in X.ELEMENTS for f, m in zip("SAP", modes) if m)}),
k as (select family, a, unnest(['name', 'description', 'producer_contact', 'producer_url', 'initiative_title', 'initiative_description', 'initiative_url']) element, unnest([n, d, p, u, n, d, u]) filled from c)
select m.family, m.element, mode, filled, a - filled missing from m left join k using (family, element)""")
def element_audit(spark, sf):
    return X.audit_elements(load(spark, sf, "documents"))


@query(f"select doc_id, {CAT} catalog_id, {NAME} as name, length({REST}) description_chars from documents")
def item_fields(spark, sf):
    return X.text_elements(X.with_catalog(load(spark, sf, "documents"))).select("doc_id", "catalog_id", "name", F.length("description").cast("bigint").alias("description_chars"))


UNESCAPE = "replace(replace(replace({}, '&lt;', '<'), '&gt;', '>'), '&amp;', '&')"
BODY = "html"
for _p in ("<script[^>]*>[^<]*</script>", "<style[^>]*>[^<]*</style>", "<!--[^>]*-->", '<div class="ad">[^<]*</div>', "(?s)<nav>.*?</nav>", "(?s)<head>.*?</head>", "<[^>]*>", r"[ \n\t\r]+"):
    BODY = f"regexp_replace({BODY}, '{_p}', ' ', 'g')"
PAGE = f"""select page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) site, {UNESCAPE.format("regexp_extract(html, '<title>([^<]*)</title>', 1)")} title,
{UNESCAPE.format("regexp_extract(html, '<h1>([^<]*)</h1>', 1)")} h1, {UNESCAPE.format(f"trim({BODY})")} body,
(length(html) - length(replace(html, 'href="', ''))) // 6 n_links, (length(html) - length(replace(html, '<p>', ''))) // 3 n_paragraphs from pages"""


@query(f"select * replace (md5(body) as body) from ({PAGE})")
def page_elements(spark, sf):
    return X.extract_page(load(spark, sf, "pages")).withColumn("body", F.md5("body"))


@query("""select page_id, ord - 1 as ord, l[ord] href from (select page_id, l, unnest(range(1, len(l) + 1)) ord from (select page_id, regexp_extract_all(html, 'href="([^"]*)"', 1) l from pages))""")
def page_links(spark, sf):
    return X.page_links(load(spark, sf, "pages")).withColumn("ord", F.col("ord").cast("bigint"))


CONTACTS = " union all ".join(
    f"select doc_id, '{k}' kind, ord - 1 as ord, l[ord] as value from (select doc_id, l, unnest(range(1, len(l) + 1)) ord from (select doc_id, regexp_extract_all(text, '{p}', 0) l from documents))"
    for k, p in (("phone", X.PHONE), ("email", X.EMAIL), ("ip", X.ADDRESS), ("url", X.LINK))
)


@query(CONTACTS)
def contacts(spark, sf):
    return X.extract_contacts(load(spark, sf, "documents"))


@query(f"select kind, count(*) n, count(distinct doc_id) docs from ({CONTACTS}) group by 1")
def contact_counts(spark, sf):
    return X.extract_contacts(load(spark, sf, "documents")).groupBy("kind").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("docs"))


@query(f"""with p as (select doc_id, value, cast(substr(value, 5, 3) as int) prefix from ({CONTACTS}) where kind = 'phone'),
k as (select *, case when prefix // 100 in (5, 6) then null else prefix % 25 end nationkey from p)
select doc_id, value, prefix, n_name nation, r_name region, nationkey * 5 - 60 lat, nationkey * 14 - 180 lon, nationkey is not null resolved
from k left join nation on nationkey = n_nationkey left join region on n_regionkey = r_regionkey""")
def phone_regions(spark, sf):
    return X.locate_by_prefix(X.extract_contacts(load(spark, sf, "documents")), load(spark, sf, "nation"), load(spark, sf, "region"))


@query("select label, 3 * count(*) n from embeddings group by 1")
def icon_augment_count(spark, sf):
    return X.augment(load(spark, sf, "embeddings")).groupBy("label").agg(F.count("*").alias("n"))


VARIANTS = "select vec_id, label, level, list_transform(embedding, lambda x: round(x::double * level) / level) e from embeddings, (values (4), (8), (16)) v(level)"


@query(f"select vec_id, level, round(list_sum(e), 6) total from ({VARIANTS})")
def icon_variants(spark, sf):
    total = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x)
    return X.icon_variants(load(spark, sf, "embeddings")).select("vec_id", "level", F.round(total, 6).alias("total"))


@query(f"""with v as ({VARIANTS}), g as (select vec_id gid, label glabel, embedding::double[] ge from embeddings),
s as (select v.vec_id, level, label, arg_max(gid, (round(list_cosine_similarity(e, ge), 9), -gid)) pred, arg_max(glabel, (round(list_cosine_similarity(e, ge), 9), -gid)) plabel from v, g group by 1, 2, 3)
select level, label, count(*) n, count(*) filter (where pred = vec_id) hits, count(*) filter (where plabel = label) label_hits from s group by 1, 2""")
def icon_classify_seen(spark, sf):
    icons = load(spark, sf, "embeddings")
    got = X.classify_icons(X.icon_variants(icons), icons, ["vec_id", "level", "label"])
    return got.groupBy("level", "label").agg(F.count("*").alias("n"), F.count_if(F.expr("pred_id = vec_id")).alias("hits"), F.count_if(F.expr("pred_label = label")).alias("label_hits"))


@query("""with e as (select label, unnest(range(64)) i, unnest(embedding::double[]) x from embeddings), c as (select label, i, avg(x) x from e group by 1, 2),
g as (select label glabel, list(x order by i) ge from c group by 1),
s as (select vec_id, label, arg_max(glabel, (round(list_cosine_similarity(embedding::double[], ge), 9), -glabel)) p from embeddings, g group by 1, 2)
select count(*) n, count(*) filter (where p = label) hits from s""")
def icon_nearest_centroid(spark, sf):
    icons = load(spark, sf, "embeddings")
    got = X.classify_icons(icons, X.icon_centroids(icons).select(F.col("label").cast("bigint").alias("vec_id"), "label", "embedding"), ["vec_id", "label"])
    return got.agg(F.count("*").alias("n"), F.count_if(F.expr("pred_label = label")).alias("hits"))


@query("""with g as (select vec_id gid, label glabel, embedding::double[] ge from embeddings),
s as (select vec_id, label, arg_max(glabel, (round(list_cosine_similarity(embedding::double[], ge), 9), -gid)) p from embeddings, g where gid <> vec_id group by 1, 2)
select count(*) n, count(*) filter (where p = label) hits from s""")
def icon_unseen_control(spark, sf):
    icons = load(spark, sf, "embeddings")
    got = X.classify_icons(icons, icons, ["vec_id", "label"], skip_same=True)
    return got.agg(F.count("*").alias("n"), F.count_if(F.expr("pred_label = label")).alias("hits"))


@query(f"""with known as (select distinct {sql_normalize_name(NAME)} k from documents), p as (select *, {sql_normalize_name('title')} k from ({PAGE}))
select page_id, title, len(string_split(k, ' ')) >= 3 and n_paragraphs >= 2 sound from p where k = '' or k not in (select k from known)""")
def discover_candidates(spark, sf):
    return X.discover_candidates(load(spark, sf, "pages"), load(spark, sf, "documents"))
