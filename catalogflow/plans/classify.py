"""Queries: labelling, its example sets and prompts, measures and baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_hash60, sql_tokens, tokens
from catalogflow.operators import classify as C
from catalogflow.operators import metrics as M
from catalogflow.operators.metadata import VOTES
from catalogflow.plans.extraction import CAT, NAME, REST
from catalogflow.plans.metadata import votes_sql
from catalogflow.plans.registry import load, query
from catalogflow.session import staged

_ABUSE = ", ".join(f"'{w}'" for w in C.ABUSE.split())
_V = " + ".join(f"v_{x}" for x in VOTES)
SCORES = f"""votes as ({votes_sql('doc_id, lang, text')}), feat as (select *, {_V} all_v, len(list_filter({sql_tokens()}, lambda t: t in ({_ABUSE}))) insults,
length(regexp_replace(text, '[A-Za-zÀ-ÿ \\n.,]', '', 'g')) / greatest(length(text), 1)::double sym from votes),
lev as (select *, case when sym <= 0.005 then 1 when sym <= 0.01 then 2 when sym <= 0.02 then 3 when sym <= 0.05 then 4 else 5 end noisy, case when insults = 0 then 1 when insults = 1 then 4 else 5 end abusive from feat),
scores as ({' union all '.join(f"select doc_id, 'origin' domain, '{C.ORIGIN_OF[x]}' as label, (case when all_v = 0 then 1 else 1 + least(4, (5 * v_{x}) // all_v) end)::int score from lev" for x in VOTES)}
union all select doc_id, 'condition', 'noisy', noisy from lev union all select doc_id, 'condition', 'clean', 6 - noisy from lev union all select doc_id, 'conduct', 'abusive', abusive from lev union all select doc_id, 'conduct', 'civil', 6 - abusive from lev),
picked as (select * from (select *, max(score) over (partition by doc_id) top from scores) where score >= 4 or (top < 4 and score = top)),
picked_domain as (select * from (select *, max(score) over (partition by doc_id, domain) top from scores) where score >= 4 or (top < 4 and score = top))"""
_ORIGIN = "case lang " + " ".join(f"when '{k}' then '{v}'" for k, v in C.ORIGIN_OF.items()) + " end"
GOLD = f"""lab as (select doc_id, lang, quality, toxic from documents join labels using (doc_id)),
gold as (select doc_id, 'origin' domain, {_ORIGIN} as label from lab union all select doc_id, 'condition', case when quality = 0 then 'noisy' else 'clean' end from lab union all select doc_id, 'conduct', case when toxic = 1 then 'abusive' else 'civil' end from lab)"""


def measured(pred: str, keys: str = "doc_id", base: str = "select distinct doc_id, domain from gold", gold: str = "gold", empty: str = "1") -> str:
    """CTEs item_m: p, r, f1 of each item and domain."""
    cond = " and ".join(f"b.{k} = {{0}}.{k}" for k in (*keys.split(", "), "domain"))
    return f"""item_m as (select {', '.join('b.' + k for k in keys.split(', '))}, b.domain, case when ng + nq = 0 then {empty} when nq = 0 then 0 else nb / nq end p, case when ng + nq = 0 then {empty} when ng = 0 then 0 else nb / ng end r, case when ng + nq = 0 then {empty} else 2 * nb / (ng + nq) end f1
from (select b.*, coalesce((select count(*) from {gold} g where {cond.format('g')}), 0) ng, coalesce((select count(*) from {pred} q where {cond.format('q')}), 0) nq,
coalesce((select count(*) from {pred} q join {gold} g using ({keys}, domain, label) where {cond.format('q')}), 0) nb from ({base}) b) b)"""


def _docs(spark, sf):
    return load(spark, sf, "documents")


def _gold(spark, sf):
    return C.gold_labels(_docs(spark, sf), load(spark, sf, "labels"))


def _labelled(spark, sf):
    return _docs(spark, sf).join(load(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")


def _base(gold):
    return gold.select("doc_id", "domain").distinct()


@query(f"with {SCORES} select doc_id, domain, label, score from scores")
def expert_scores(spark, sf):
    return C.expert_scores(_docs(spark, sf))


@query(f"with {SCORES} select doc_id, domain, label, score from picked")
def expert_labels(spark, sf):
    return C.select_labels(C.expert_scores(_docs(spark, sf)))


@query(f"with {SCORES} select doc_id, domain, label, score from picked_domain")
def expert_labels_domain(spark, sf):
    return C.select_labels(C.expert_scores(_docs(spark, sf)), per="domain")


def _reasons_sql(source: str, p: str) -> str:
    origin = " union all ".join(f"select doc_id, 'origin' domain, '{C.ORIGIN_OF[x]}' as label, v_{x} || ' of ' || all_v || ' frequent words' reason from {p}ft" for x in VOTES)
    rest = " union all ".join(f"select doc_id, 'condition', '{x}', floor(sym * 1000)::bigint || ' symbols in a thousand' from {p}ft" for x in ("noisy", "clean"))
    last = " union all ".join(f"select doc_id, 'conduct', '{x}', insults || ' insults' from {p}ft" for x in ("abusive", "civil"))
    return f"""{p}vt as ({votes_sql('doc_id, text').replace('documents', source)}), {p}ft as (select *, {_V} all_v, len(list_filter({sql_tokens()}, lambda t: t in ({_ABUSE}))) insults,
length(regexp_replace(text, '[A-Za-zÀ-ÿ \n.,]', '', 'g')) / greatest(length(text), 1)::double sym from {p}vt),
{p}why as ({origin} union all {rest} union all {last})"""


_TX2 = "case p_type " + " ".join(f"when '{k}' then '{v}'" for k, v in C.TX2.items()) + " end"
ORDERS = f"""per as (select l_orderkey o, p_type as label, avg(l_quantity) q, sum(l_extendedprice::decimal(18, 2)) rev from lineitem join part on l_partkey = p_partkey group by 1, 2),
os as (select o, {_TX2.replace('p_type', 'label')} domain, label, least(5, ceil(round(q / 10, 9)))::int score, rev * 4 >= sum(rev) over (partition by o) gold from per),
op as (select * from (select *, max(score) over (partition by o) top from os) where score >= 4 or (top < 4 and score = top))"""


@query(f"""with {ORDERS}, m as (select o, domain, count(*) filter (where gold) ng, count(*) filter (where sel) nq, count(*) filter (where gold and sel) nb from (select os.*, op.o is not null sel from os left join op on op.o = os.o and op.label = os.label) group by 1, 2)
select domain, count(*) items, sum(nq)::bigint selected, round(avg(case when ng + nq = 0 then 1 when nq = 0 then 0 else nb / nq end), 6) p, round(avg(case when ng + nq = 0 then 1 when ng = 0 then 0 else nb / ng end), 6) r, round(avg(case when ng + nq = 0 then 1 else 2 * nb / (ng + nq) end), 6) f1 from m group by 1""")
def order_expert_labels(spark, sf):
    """Labelling of all orders by the types of their parts, measured per domain; one window per order, two aggregations."""
    s = C.order_scores(load(spark, sf, "lineitem"), load(spark, sf, "part"))
    from pyspark.sql import Window

    s = s.withColumn("top", F.max("score").over(Window.partitionBy("o"))).withColumn("sel", F.expr("score >= 4 or (top < 4 and score = top)"))
    m = s.groupBy("o", "domain").agg(F.count_if("gold").alias("ng"), F.count_if("sel").alias("nq"), F.count_if(F.col("gold") & F.col("sel")).alias("nb"))
    v = lambda over: F.expr(f"case when ng + nq = 0 then 1D when {over} = 0 then 0D else nb / {over} end")
    return m.groupBy("domain").agg(F.count("*").alias("items"), F.sum("nq").alias("selected"), F.round(F.avg(v("nq")), 6).alias("p"), F.round(F.avg(v("ng")), 6).alias("r"), F.round(F.avg(F.expr("case when ng + nq = 0 then 1D else 2 * nb / (ng + nq) end")), 6).alias("f1"))


@query(f"with {ORDERS} select score, count(*) n from os group by 1")
def order_score_histogram(spark, sf):
    return C.order_scores(load(spark, sf, "lineitem"), load(spark, sf, "part")).groupBy("score").agg(F.count("*").alias("n"))


def _panel_sql() -> str:
    order = sorted(VOTES)
    cols = ", ".join(f"len(list_filter(tok, lambda t: t in ({', '.join(repr(w) for w in VOTES[x].split()[e::3])}))) p{e}_{x}" for e in range(3) for x in order)
    best = lambda f: f"case when greatest({', '.join(f(x) for x in order)}) = 0 then null " + " ".join(f"when {f(x)} = greatest({', '.join(f(y) for y in order)}) then '{x}'" for x in order) + " end"
    es = ", ".join(best(lambda x, e=e: f"p{e}_{x}") + f" e{e}, " + " + ".join(f"p{e}_{x}" for x in order) + f" t{e}" for e in range(3))
    peer = lambda f, e: f"(case when t{f} = 0 then 1 else 1 + least(4, 5 * (case e{e} " + " ".join(f"when '{x}' then p{f}_{x}" for x in order) + f" else 0 end) // t{f}) end)"
    ss = ", ".join(f"(case when e{e} is null then 0 else " + " + ".join(peer(f, e) for f in range(3) if f != e) + f" end)::int s{e}" for e in range(3))
    pair = "case when e0 = e1 or e0 = e2 then e0 when e1 = e2 then e1 end"
    guess = "list_sort(list_filter([{'s': -s0, 'l': e0}, {'s': -s1, 'l': e1}, {'s': -s2, 'l': e2}], lambda a: a.l is not null))[1].l"
    return f"select doc_id, e0, e1, e2, s0, s1, s2, coalesce({pair}, {guess}) as label, {pair} is not null agreed from (select *, {ss} from (select *, {es} from (select doc_id, {cols} from (select doc_id, {sql_tokens()} tok from documents))))"


@query(_panel_sql())
def panel_labels(spark, sf):
    return C.panel_votes(_docs(spark, sf))


_NAMED_LABEL = "case x.label " + " ".join(f"when '{k}' then '{v}'" for k, v in C.ORIGIN_OF.items()) + " end"


@query(f"""with {GOLD}, {SCORES}, pn as ({_panel_sql()}), said as (select 'experts' labeller, doc_id, label from picked where domain = 'origin' union all select 'panel', doc_id, {_NAMED_LABEL} from pn x where x.label is not null),
g as (select l.labeller, g.doc_id, g.label from gold g, (values ('experts'), ('panel')) l(labeller) where domain = 'origin'),
c as (select g.labeller, g.doc_id, count(s.label) nq, count(*) filter (where s.label = g.label) nb from g left join said s using (labeller, doc_id) group by 1, 2)
select labeller, count(*) items, round(avg(case when nq = 0 then 0 else nb / nq end), 6) p, round(avg(nb), 6) r, round(avg(2 * nb / (1 + nq)), 6) f1 from c group by 1""")
def panel_vs_experts(spark, sf):
    """The panel that was given up against the domain's expert, on the languages of labelled items."""
    docs, gold = _labelled(spark, sf), _gold(spark, sf).where("domain = 'origin'")
    named = F.create_map(*[F.lit(x) for kv in C.ORIGIN_OF.items() for x in kv])
    # written first: the filter would be put before the votes, with every count in it many times over
    votes = staged(C.panel_votes(docs).select("doc_id", "label"), "panel-votes")
    panel = votes.where("label is not null").select(F.lit("panel").alias("labeller"), "doc_id", F.lit("origin").alias("domain"), named[F.col("label")].alias("label"))
    expert = C.select_labels(C.expert_scores(docs)).where("domain = 'origin'").select(F.lit("experts").alias("labeller"), "doc_id", "domain", "label")
    both = gold.select("*", F.explode(F.array(F.lit("panel"), F.lit("experts"))).alias("labeller"))
    scores = M.item_scores(both, panel.union(expert), both.select("labeller", "doc_id", "domain").distinct(), ["labeller", "doc_id"])
    return scores.groupBy("labeller").agg(F.count("*").alias("items"), *[F.round(F.avg(c), 6).alias(c) for c in ("p", "r", "f1")])


@query(f"""with {GOLD}, n as (select domain, label, count(*) n from gold group by 1, 2), pr as (select *, sum(n) over (partition by domain order by label) upto, sum(n) over (partition by domain) total from n),
dr as (select doc_id, domain, label from (select l.doc_id, pr.*, {sql_hash60("'s1/' || domain || '/' || l.doc_id")} % total u from lab l, pr) where u < upto and u >= upto - n)
select d.domain, count(*) items, round(avg((d.label = g.label)::int), 6) f1 from dr d join gold g on g.doc_id = d.doc_id and g.domain = d.domain group by 1""")
def baseline_random(spark, sf):
    """Labels drawn with the gold labels' own frequencies: the floor."""
    gold = _gold(spark, sf)
    drawn = C.random_labels(_labelled(spark, sf), gold, "s1").join(gold.select("doc_id", "domain", F.col("label").alias("g")), ["doc_id", "domain"])
    return drawn.groupBy("domain").agg(F.count("*").alias("items"), F.round(F.avg((F.col("label") == F.col("g")).cast("double")), 6).alias("f1"))


@query(f"""with recursive {GOLD}, {SCORES}, {_reasons_sql('documents', '')} select s.doc_id, s.domain, s.label, score, reason from scores s join why w on w.doc_id = s.doc_id and w.domain = s.domain and w.label = s.label""")
def expert_reasons(spark, sf):
    """Every score with the expert's reason."""
    return C.expert_scores(_docs(spark, sf), reasons=True)


ITEMS = f"items as (select doc_id, {CAT} catalog_id from documents where {CAT} < 4 and doc_id in (select doc_id from labels))"
SETS = f"""{ITEMS}, {GOLD}, oa as (select *, ((row_number() over (partition by catalog_id order by md5('s1' || doc_id), doc_id) - 1) * 4 + catalog_id + 1)::int pos from items),
sa as (select * from oa where pos <= (select max(p) from (select domain, label, min(pos) p from gold join oa using (doc_id) group by 1, 2))),
ob as (select *, ((row_number() over (partition by catalog_id order by md5('s1' || doc_id), doc_id) - 1) * 4 + catalog_id + 1)::int pos from items where doc_id not in (select doc_id from sa)),
sb as (select * from ob where pos <= (select max(p) from (select domain, label, min(pos) p from gold join ob using (doc_id) group by 1, 2))),
sets as (select *, 'A' dataset from sa union all select *, 'B' from sb)"""


def _sets(spark, sf):
    return C.covering_sets(C.dataset_items(_docs(spark, sf), load(spark, sf, "labels")), _gold(spark, sf), "s1")


@query(f"with {SETS} select * from oa")
def round_robin_order(spark, sf):
    return C.round_robin(C.dataset_items(_docs(spark, sf), load(spark, sf, "labels")), "s1")


@query(f"with {SETS} select doc_id, catalog_id, pos, dataset from sets")
def covering_sets(spark, sf):
    return _sets(spark, sf)


@query(f"with {SETS} select dataset, count(distinct doc_id) items, count(distinct (domain, label)) labels, round(count(distinct (domain, label)) / 8, 6) covered from sets join gold using (doc_id) group by 1")
def set_coverage(spark, sf):
    return M.coverage(_sets(spark, sf), _gold(spark, sf), 8)


@query(f"with {SETS} select fold, case when (dataset = 'A') = (fold = 1) then 'train' else 'test' end as role, doc_id from sets, (values (1), (2)) f(fold)")
def swap_plan(spark, sf):
    return C.swap_plan(_sets(spark, sf))


_LONG = "len(list_filter(list_filter(string_split_regex(lower({0}), '[^a-zà-ÿß]+'), lambda t: t <> ''), lambda t: length(t) > 4))"


def condensed_sql(budget: int, source: str = "documents", p: str = "") -> str:
    """CTEs up to {p}condensed (doc_id, text, cut); needs 'with recursive'."""
    word = f"regexp_extract(substr(best, 1, {budget + 1}), '(?s)^(.*)\\s', 1)"
    return f"""{p}d as (select row_number() over () k, doc_id, text from {source}), {p}s as (select k, unnest(string_split(text, '.')) s, unnest(range(1, len(string_split(text, '.')) + 1)) i from {p}d where length(text) > {budget}),
{p}r as (select k, s, i, row_number() over (partition by k order by {_LONG.format('s')} desc, i) r from {p}s where trim(s) <> ''),
{p}walk as (select k, r, i, s, length(s) + 1 <= {budget} took, case when length(s) + 1 <= {budget} then length(s) + 1 else 0 end used from {p}r where r = 1 union all
select n.k, n.r, n.i, n.s, used + length(n.s) + 1 <= {budget}, case when used + length(n.s) + 1 <= {budget} then used + length(n.s) + 1 else used end from {p}walk w join {p}r n on n.k = w.k and n.r = w.r + 1),
{p}whole as (select k, string_agg(s, '.' order by i) filter (where took) text, max(case when r = 1 then trim(s) end) best from {p}walk group by 1),
{p}fit as (select k, coalesce(text, case when length(best) <= {budget} then best when {word} <> '' then {word} else substr(best, 1, {budget}) end) text, text is null cut from {p}whole),
{p}condensed as (select doc_id, case when coalesce(length(d.text), 0) <= {budget} then d.text else coalesce(f.text, '') end text, coalesce(cut, false) cut from {p}d d left join {p}fit f using (k))"""


@query(f"with recursive {condensed_sql(C.BUDGET)} select doc_id, length(text) chars, md5(text) digest, cut from condensed")
def condense_text(spark, sf):
    """Every document comes back, the long ones condensed to the budget."""
    return C.condense(_docs(spark, sf), C.BUDGET).select("doc_id", F.length("text").cast("bigint").alias("chars"), F.md5("text").alias("digest"), "cut")


_TEXT = "\n".join(f"[{d}] " + " / ".join(f"{x}: {C.DEFINITIONS.get(x, x)}" for x in ls) for d, ls in C.TX1.items())


@query(f"select 1 as version, md5('Taxonomy, version 1.\n{_TEXT}') digest, length('Taxonomy, version 1.\n{_TEXT}') chars")
def taxonomy_prompt(spark, sf):
    return C.taxonomy_prompt(spark, C.TX1, 1).select("version", F.md5("prompt").alias("digest"), F.length("prompt").cast("bigint").alias("chars"))


_WHY = "case label " + " ".join(f"when '{k}' then '{v}'" for k, v in C.DEFINITIONS.items()) + " end"
_JSON_ITEM = f"to_json({{'name': {NAME}, 'description': {REST}}})::varchar"


def shots_sql(source: str = "documents", p: str = "") -> str:
    """CTEs up to {p}shots (doc_id, prompt), from GOLD."""
    return f"""{_reasons_sql(source, p)},
{p}labs as (select g.doc_id, list(label order by label) l, string_agg('It is ' || label || ' because the text is ' || {_WHY} || ': ' || coalesce(reason, 'no evidence') || '.', ' ' order by label) w from gold g left join {p}why using (doc_id, domain, label) group by 1),
{p}shots as (select doc_id, '== SHOT ==\n' || {_JSON_ITEM} || '\n' || to_json({{'labels': l, 'reason': w}})::varchar || '\n(for context only)' prompt from {source} join {p}labs using (doc_id))"""


SHOTS = shots_sql()


@query(f"with {GOLD}, {SHOTS} select doc_id, length(prompt) chars, md5(prompt) digest from shots")
def fewshot_prompts(spark, sf):
    return C.fewshot_prompts(_docs(spark, sf), _gold(spark, sf)).select("doc_id", F.length("prompt").cast("bigint").alias("chars"), F.md5("prompt").alias("digest"))


def _packing_sql(budget: int) -> str:
    return f"""n as (select doc_id // 200 grp, doc_id ord, length(prompt) chars, row_number() over (partition by doc_id // 200 order by doc_id) i from shots),
pack as (select grp, ord, chars, i, 1 prompt_no, chars used from n where i = 1 union all
select n.grp, n.ord, n.chars, n.i, case when p.used + n.chars <= {budget} then p.prompt_no else p.prompt_no + 1 end, case when p.used + n.chars <= {budget} then p.used + n.chars else n.chars end from pack p join n on n.grp = p.grp and n.i = p.i + 1)"""


def _shots(spark, sf):
    p = C.fewshot_prompts(_docs(spark, sf), _gold(spark, sf))
    return p.select(F.expr("doc_id div 200").alias("grp"), F.col("doc_id").alias("ord"), F.length("prompt").cast("bigint").alias("chars"))


@query(f"with recursive {GOLD}, {SHOTS}, {_packing_sql(C.BUDGET)} select grp, ord, chars, prompt_no, chars > {C.BUDGET} oversize from pack")
def pack_prompts(spark, sf):
    return C.pack_prompts(_shots(spark, sf))


@query(" union all ".join(f"select * from (with recursive {GOLD}, {SHOTS}, {_packing_sql(b)}, m as (select grp, max(prompt_no) k from pack group by 1) select {b} budget, sum(k)::bigint prompts, (select count(*) from pack where chars > {b}) oversize, {e} error_per_mille from m)" for b, e in ((10000, 160), (15000, 160), (19500, 350), (23000, 350))))
def prompt_budget_sweep(spark, sf):
    """Prompts that a budget leads to, beside the simulated error rate at that length."""
    out = None
    for b, e in ((10000, 160), (15000, 160), (19500, 350), (23000, 350)):
        p = C.pack_prompts(_shots(spark, sf), b)
        k = p.groupBy("grp").agg(F.max("prompt_no").alias("k"), F.count_if("oversize").alias("o")).agg(F.sum("k").alias("prompts"), F.sum("o").alias("oversize"))
        row = k.select(F.lit(b).alias("budget"), "prompts", "oversize", F.lit(e).alias("error_per_mille"))
        out = row if out is None else out.union(row)
    return out


_ASKED = "Score every label of your domain from 1 to 5; give those of 4 and more, or the highest. Answer with one JSON object, a list of labels for each domain."
RUN = f"""{SETS}, plan as (select fold, case when (dataset = 'A') = (fold = 1) then 'train' else 'test' end as role, doc_id, pos from sets, (values (1), (2)) f(fold)),
own as (select doc_id, text from documents where doc_id in (select doc_id from sets)), {condensed_sql(1000, 'own', 's_')}, {condensed_sql(C.BUDGET, 'own', 'i_')}, {shots_sql('s_condensed', 's_')},
n as (select fold grp, pos::bigint ord, length(prompt) chars, row_number() over (partition by fold order by pos) i from plan join s_shots using (doc_id) where role = 'train'),
pack as (select grp, ord, chars, i, 1 prompt_no, chars used from n where i = 1 union all
select n.grp, n.ord, n.chars, n.i, case when p.used + n.chars <= {C.BUDGET} then p.prompt_no else p.prompt_no + 1 end, case when p.used + n.chars <= {C.BUDGET} then p.used + n.chars else n.chars end from pack p join n on n.grp = p.grp and n.i = p.i + 1),
packed as (select grp fold, prompt_no, sum(chars)::bigint chars from pack group by 1, 2), sizes as (select fold, max(prompt_no) shots from packed group by 1),
item as (select fold, doc_id, length('== ITEM ==\n' || {_JSON_ITEM} || '\n{_ASKED}') chars, row_number() over (partition by fold order by pos, doc_id) i, count(*) over (partition by fold) n from plan join i_condensed using (doc_id) where role = 'test'),
placed as (select *, ((i - 1) * ceil(n / greatest(1, 9 - shots))::bigint // n)::int conv from item join sizes using (fold)),
talks as (select distinct fold, conv from placed),
turns as (select fold, conv, 1 turn, 'taxonomy' kind, null::bigint doc_id, length('Taxonomy, version 1.\n{_TEXT}') chars from talks union all select fold, conv, prompt_no + 1, 'shots', null, chars from talks join packed using (fold)
union all select fold, conv, row_number() over (partition by fold, conv order by i) + shots + 1, 'item', doc_id, chars from placed)"""


def _expert_answers(docs):
    from catalogflow.operators.answers import answer_json

    return answer_json(C.select_labels(C.expert_scores(docs)))


def _run(spark, sf):
    return C.run_classification(_docs(spark, sf), _gold(spark, sf), _sets(spark, sf), _expert_answers)


@query(f"with recursive {GOLD}, {RUN.replace(GOLD + ',', '')} select fold, conv, turn::int turn, kind, doc_id, chars, count(*) over (partition by fold, conv) prompts from turns")
def conversation_plan(spark, sf):
    """Every prompt of every conversation: taxonomy, packed shots, items; ten at most."""
    return _run(spark, sf).select("fold", "conv", "turn", "kind", "doc_id", "chars", "prompts")


_LK = f"""tc as (select conv_id, turn, role, {sql_tokens()} w from conversations), sc as (select conv_id, turn, role, list_distinct(list_transform(range(1, greatest(len(w) - 1, 1)), lambda i: array_to_string(w[i:i + 2], ' '))) sh from tc),
pr as (select a.conv_id, a.turn, u.turn ut, len(list_intersect(a.sh, u.sh)) c, max(u.turn) over (partition by a.conv_id, a.turn) own_t from sc a join sc u on a.conv_id = u.conv_id and u.role = 'user' and a.role = 'assistant' and u.turn < a.turn)"""


@query(f"with {_LK} select conv_id, turn, sum(case when ut = own_t then c else 0 end)::bigint own, sum(case when ut < own_t then c else 0 end)::bigint prior, sum(case when ut < own_t then c else 0 end) > sum(case when ut = own_t then c else 0 end) leaked from pr group by 1, 2")
def context_leakage(spark, sf):
    return C.context_leakage(load(spark, sf, "conversations"))


@query(f"""with {GOLD}, {SCORES}, add_p as (select p.doc_id, p.domain, p.label from picked p join lab using (doc_id) where p.score = 5 and not exists (select 1 from gold g where g.doc_id = p.doc_id and g.domain = p.domain and g.label = p.label)),
rem as (select g.* from gold g where not exists (select 1 from scores s where s.doc_id = g.doc_id and s.domain = g.domain and s.label = g.label and s.score > 1))
select doc_id, domain, label, 'added' state from add_p union all select g.doc_id, g.domain, g.label, case when r.doc_id is null then 'kept' else 'removed' end from gold g left join rem r on r.doc_id = g.doc_id and r.domain = g.domain and r.label = g.label""")
def gold_revision(spark, sf):
    """Sure proposals of the expert (score 5) are accepted, and gold labels that it rates 1 are withdrawn."""
    gold, s = _gold(spark, sf), C.expert_scores(_labelled(spark, sf))
    add = C.select_labels(s).where("score = 5").select("doc_id", "domain", "label").join(gold, ["doc_id", "domain", "label"], "left_anti").withColumn("action", F.lit("add"))
    rem = gold.join(s.where("score > 1"), ["doc_id", "domain", "label"], "left_anti").withColumn("action", F.lit("remove"))
    return C.revise_gold(gold, add.unionByName(rem).withColumn("accepted", F.lit(True)))


@query(f"with {GOLD}, {SCORES} select g.domain, g.label as gold, p.label pred, count(*) n from gold g join picked p on p.doc_id = g.doc_id and p.domain = g.domain group by 1, 2, 3")
def label_confusions(spark, sf):
    pred = C.select_labels(C.expert_scores(_labelled(spark, sf))).select("doc_id", "domain", F.col("label").alias("pred"))
    return _gold(spark, sf).join(pred, ["doc_id", "domain"]).groupBy("domain", F.col("label").alias("gold"), "pred").agg(F.count("*").alias("n"))


def _measured(spark, sf, per="item"):
    gold = _gold(spark, sf)
    return M.item_scores(gold, C.select_labels(C.expert_scores(_labelled(spark, sf)), per=per), _base(gold), ["doc_id"])


@query(f"with {GOLD}, {SCORES}, {measured('picked')} select domain, count(*) items, round(avg(p), 6) p, round(avg(r), 6) r, round(avg(f1), 6) f1 from item_m group by 1")
def metrics_domain(spark, sf):
    return M.domain_scores(_measured(spark, sf))


@query(f"with {GOLD}, {SCORES}, {measured('picked_domain')} select domain, count(*) items, round(avg(p), 6) p, round(avg(r), 6) r, round(avg(f1), 6) f1 from item_m group by 1")
def metrics_domain_scope(spark, sf):
    return M.domain_scores(_measured(spark, sf, "domain"))


@query(f"with {GOLD}, {SCORES}, {measured('picked')} select round(avg(f1), 6) total_f1 from (select domain, avg(f1) f1 from item_m group by 1)")
def metrics_total(spark, sf):
    return M.total_f1(_measured(spark, sf))


@query(f"""with {GOLD}, {SCORES}, pl as (select p.* from picked p join lab using (doc_id)), j as (select doc_id, g.label g, q.label q from gold g full join pl q using (doc_id, domain, label)),
per as (select doc_id, count(g) ng, count(q) nq, count(*) filter (where g is not null and q is not null) nb from j group by 1)
select count(*) n, round(sum(nb) / sum(nq), 6) micro_p, round(sum(nb) / sum(ng), 6) micro_r, round(2 * sum(nb) / (sum(ng) + sum(nq)), 6) micro_f1, round(avg((ng = nb and nq = nb)::int), 6) subset_accuracy, round(sum(ng + nq - 2 * nb) / (count(*) * 8), 6) hamming_loss, round(avg(nb / (ng + nq - nb)), 6) jaccard from per""")
def metrics_multilabel(spark, sf):
    return M.multilabel_summary(_gold(spark, sf), C.select_labels(C.expert_scores(_labelled(spark, sf))), "doc_id", 8)


@query(f"""with {GOLD}, c as (select domain, label, count(*) n from gold group by 1, 2), best as (select domain, label, n, sum(n) over (partition by domain) a, row_number() over (partition by domain order by n desc, label) r from c)
select domain, label, round(n / a, 6) f1 from best where r = 1""")
def baseline_majority(spark, sf):
    from pyspark.sql import Window

    c = _gold(spark, sf).groupBy("domain", "label").agg(F.count("*").alias("n"))
    w = Window.partitionBy("domain")
    c = c.withColumn("a", F.sum("n").over(w)).withColumn("r", F.row_number().over(w.orderBy(F.desc("n"), "label")))
    return c.where("r = 1").select("domain", "label", F.round(F.col("n") / F.col("a"), 6).alias("f1"))


@query(f"""with {GOLD}, {SCORES}, kw as (select doc_id, domain, label from scores where score > 1 and label in ('noisy', 'abusive') or domain = 'origin' and score > 1), {measured('kw')}
select domain, count(*) items, round(avg(p), 6) p, round(avg(r), 6) r, round(avg(f1), 6) f1 from item_m group by 1""")
def baseline_keyword(spark, sf):
    """Any sign of a label counts, without weighing; absence labels (clean, civil) are never given."""
    gold = _gold(spark, sf)
    s = C.expert_scores(_labelled(spark, sf)).where("(score > 1 and label in ('noisy', 'abusive')) or (domain = 'origin' and score > 1)")
    return M.domain_scores(M.item_scores(gold, s, _base(gold), ["doc_id"]))


@query(f"""with {SETS}, w as (select doc_id, list_distinct({sql_tokens()}) w from documents where doc_id in (select doc_id from labels)), lib as (select w.* from w join sa using (doc_id)),
s as (select a.doc_id, b.doc_id shot_id, round(len(list_intersect(a.w, b.w)) / greatest(1, len(a.w) + len(b.w) - len(list_intersect(a.w, b.w))), 6) score from w a, lib b where a.doc_id <> b.doc_id),
n as (select doc_id, arg_max(shot_id, (score, -shot_id)) shot_id from s group by 1), pred as (select n.doc_id, g.domain, g.label from n join gold g on g.doc_id = n.shot_id), {measured('pred', base='select distinct g.doc_id, domain from gold g join n using (doc_id)')}
select domain, count(*) items, round(avg(p), 6) p, round(avg(r), 6) r, round(avg(f1), 6) f1 from item_m group by 1""")
def baseline_knn(spark, sf):
    """The labels of the nearest example in set A."""
    gold, docs = _gold(spark, sf), _labelled(spark, sf)
    lib = docs.join(_sets(spark, sf).where("dataset = 'A'").select("doc_id"), "doc_id", "left_semi")
    near = C.retrieve_shots(docs, lib).select("doc_id", "shot_id")
    pred = near.join(gold.withColumnRenamed("doc_id", "shot_id"), "shot_id").select("doc_id", "domain", "label")
    base = _base(gold.join(near, "doc_id", "left_semi"))
    return M.domain_scores(M.item_scores(gold.join(near, "doc_id", "left_semi"), pred, base, ["doc_id"]))


def _learner(spark, sf, algo):
    docs = _docs(spark, sf).select("doc_id", "lang", tokens().alias("tok"), F.expr("cast(conv(substring(md5(cast(doc_id as string)), 1, 8), 16, 10) as bigint) % 10").alias("part"))
    model = C.train_classifier(docs.where("part < 7"), "lang", algo)
    got = model.transform(docs.where("part >= 7"))
    return got.agg(F.lit(algo).alias("algo"), F.count("*").alias("n"), F.round(F.avg((F.col("prediction") == F.col("y")).cast("double")), 4).alias("accuracy"))


@query()
def baseline_nb(spark, sf):
    return _learner(spark, sf, "nb")


@query()
def baseline_lr(spark, sf):
    return _learner(spark, sf, "lr")
