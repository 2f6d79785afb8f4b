"""Queries: metadata, rendering, translation, language votes."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_tokens
from catalogflow.operators import extract as X
from catalogflow.operators import metadata as M
from catalogflow.plans.extraction import CAT, NAME, REST
from catalogflow.plans.registry import load, query


def tool_parts(spark, sf):
    """Structured items: a part with its first supplier as producer."""
    first = load(spark, sf, "lineitem").groupBy("l_partkey").agg(F.min("l_suppkey").alias("s"))
    maker = first.join(load(spark, sf, "supplier"), F.col("s") == F.col("s_suppkey"))
    return load(spark, sf, "part").join(maker, F.col("p_partkey") == F.col("l_partkey"), "left").select(
        F.col("p_partkey").alias("item_id"), F.col("p_name").alias("name"), F.concat_ws(" ", "p_type", F.col("p_size").cast("string")).alias("description"),
        F.col("s_name").alias("producer_name"), F.col("p_brand").alias("producer_description"), F.concat(F.lit("https://maker.example/"), F.col("s_suppkey").cast("string")).alias("producer_url"),
        F.lit(None).cast("string").alias("producer_logo"), F.concat(F.lit("https://portal.example/item/"), F.col("p_partkey").cast("string")).alias("url"),
    )


TOOL_ITEMS = """select p_partkey item_id, p_name as name, p_type || ' ' || p_size description, s_name producer_name, p_brand producer_description,
'https://maker.example/' || s_suppkey producer_url, 'https://portal.example/item/' || p_partkey url
from part left join (select l_partkey, min(l_suppkey) s from lineitem group by 1) on l_partkey = p_partkey left join supplier on s = s_suppkey"""
TOOL_TRIPLES = f"""with i as ({TOOL_ITEMS}) select * from (select item_id, 'title' property, 0 ordinal, name as value from i union all select item_id, 'description', 0, description from i
union all select item_id, 'creator', 0, producer_name from i union all select item_id, 'creator', 1, producer_description from i
union all select item_id, 'creator', 2, producer_url from i union all select item_id, 'local_url', 0, url from i) where value is not null and value <> ''"""


@query(TOOL_TRIPLES)
def metadata_tool(spark, sf):
    return M.to_metadata(tool_parts(spark, sf), M.TOOL)


def practice_items(spark, sf):
    docs = X.text_elements(X.with_catalog(load(spark, sf, "documents"))).where("kind = 'practice'")
    return docs.select(F.col("doc_id").alias("item_id"), "name", F.md5("description").alias("description"), F.col("lang").alias("location"), F.concat(F.lit("https://portal.example/practice/"), F.col("doc_id").cast("string")).alias("url"))


@query(f"""with i as (select doc_id item_id, {NAME} nm, md5({REST}) ds, lang, 'https://portal.example/practice/' || doc_id url from documents where {CAT} = 4)
select * from (select item_id, 'title' property, 0 ordinal, nm as value from i union all select item_id, 'description', 0, ds from i union all select item_id, 'address', 0, lang from i
union all select item_id, 'local_url', 0, url from i) where value is not null and value <> ''""")
def metadata_practice(spark, sf):
    return M.to_metadata(practice_items(spark, sf), M.PRACTICE)


@query(f"""select item_id, max(value) filter (property = 'title') title, max(value) filter (property = 'description') description,
string_agg(value, '; ' order by ordinal) filter (property = 'creator') creator, max(value) filter (property = 'local_url') local_url from ({TOOL_TRIPLES}) group by 1""")
def metadata_wide(spark, sf):
    return M.pivot_metadata(M.to_metadata(tool_parts(spark, sf), M.TOOL), ["title", "description", "creator", "local_url"])


@query(f"""select 'element:' || property older, 'term:' || property newer, count(*) n, property <> 'local_url' round_trip from ({TOOL_TRIPLES}) group by property""")
def term_upgrade(spark, sf):
    old = M.to_metadata(tool_parts(spark, sf), M.TOOL).withColumn("older", F.concat(F.lit(M.OLD), "property")).withColumn("property", F.col("older"))
    up = M.upgrade_terms(old).withColumn("newer", F.col("property"))
    back = M.downgrade_terms(up)
    return back.groupBy("older", "newer").agg(F.count("*").alias("n"), F.bool_and(F.col("property") == F.col("older")).alias("round_trip"))


@query(f"""with i as (select doc_id item_id, {NAME} nm, {REST} ds, lang from documents)
select item_id, 'missing title' problem from i where nm = '' union all select item_id, 'missing description' from i where ds = '' union all select item_id, 'unknown lang_guess' from i where lang = 'de'""")
def metadata_problems(spark, sf):
    items = X.text_elements(load(spark, sf, "documents")).select(F.col("doc_id").alias("item_id"), "name", "description", F.expr("case when lang = 'de' then lang end").alias("guess"))
    return M.validate_metadata(M.to_metadata(items, [("title", ["name"]), ("description", ["description"]), ("lang_guess", ["guess"])]), items)


def _esc(c: str) -> str:
    return f"""replace(replace(replace(replace({c}, '&', '&amp;'), '<', '&lt;'), '>', '&gt;'), '"', '&quot;')"""


@query(f"select doc_id item_id, md5('<article><h1>' || {_esc(NAME)} || '</h1><p>' || {_esc(REST)} || '</p></article>') html from documents")
def item_html(spark, sf):
    return M.render_html(X.text_elements(load(spark, sf, "documents")).withColumnRenamed("doc_id", "item_id")).withColumn("html", F.md5("html"))


_MAP = "map {" + ", ".join(f"'{a}': '{b}'" for a, b in M.LEXICON.items()) + "}"


@query(f"""with d as (select doc_id, lang, text, string_split(text, ' ') w from documents)
select doc_id, case when lang = 'es' then md5(array_to_string(list_transform(w, lambda x: coalesce({_MAP}[x], x)), ' ')) else md5(text) end digest,
case when lang = 'es' then len(list_filter(w, lambda x: {_MAP}[x] is not null)) else 0 end replaced from d""")
def translate_lexicon(spark, sf):
    return M.translate_text(load(spark, sf, "documents"), M.LEXICON).select("doc_id", F.md5("translated").alias("digest"), F.col("replaced").cast("bigint").alias("replaced"))


def votes_sql(columns: str = "doc_id, lang") -> str:
    each = ", ".join("len(list_filter(tok, lambda t: t in (" + ", ".join(f"'{w}'" for w in ws.split()) + f"))) v_{x}" for x, ws in M.VOTES.items())
    order = sorted(M.VOTES)
    most = "greatest(" + ", ".join(f"v_{x}" for x in order) + ")"
    return f"""select *, {most} votes, case when {most} = 0 then null {' '.join(f"when v_{x} = {most} then '{x}'" for x in order)} end pred from (select {columns}, {each} from (select *, {sql_tokens()} tok from documents))"""


@query(f"select doc_id, pred, votes from ({votes_sql()})")
def language_votes(spark, sf):
    return M.language_votes(load(spark, sf, "documents")).select("doc_id", "pred", F.col("votes").cast("bigint").alias("votes"))


@query(f"select lang, pred, count(*) n from ({votes_sql()}) group by 1, 2")
def language_accuracy(spark, sf):
    return M.language_votes(load(spark, sf, "documents")).groupBy("lang", "pred").agg(F.count("*").alias("n"))
