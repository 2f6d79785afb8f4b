"""Queries: answers of simulated models, their faults and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_hash60
from catalogflow.operators import answers as A
from catalogflow.operators import classify as C
from catalogflow.operators import metrics as M
from catalogflow.plans.classify import GOLD, RUN, SCORES, SETS, _gold, _labelled, _run, _sets
from catalogflow.plans.registry import query
from catalogflow.session import staged


def _kinds() -> str:
    out = []
    for m, cuts in A.DEFECTS.items():
        low = 0
        for k, cut in cuts:
            out.append(f"when model = '{m}' and h >= {low} and h < {cut} then '{k}'")
            low = cut
    return "case when model = 'M4' and doc_id % 20 < 3 then 'repeat' " + " ".join(out) + " else 'none' end"


def _l(c: str) -> str:
    return f"""(case when len({c}) = 0 then '[]' else '["' || array_to_string({c}, '","') || '"]' end)"""


def _body(o: str, c: str, t: str) -> str:
    return f"""'{{"origin":' || {o} || ',"condition":' || {c} || ',"conduct":' || {t} || '}}'"""


_O, _C, _T = _l("origin"), _l("condition"), _l("conduct")
ANSWERS = f"""pl as (select p.* from picked p join lab using (doc_id)), per as (select doc_id, {', '.join(f"coalesce(list(label order by label) filter (domain = '{d}'), []) {d}" for d in C.TX1)} from pl group by 1),
grid as (select *, {sql_hash60("model || '/' || run || '/' || doc_id")} % 100 h from per, (values ('M1'), ('M2'), ('M3'), ('M4')) m(model), (values (1), (2)) r(run)),
kinds as (select *, {_kinds()} kind from grid),
ans as (select model, run, doc_id, case kind when 'repeat' then '{A.REPEATED}' when 'missing' then '{{"origin":' || {_O} || ',"condition":' || {_C} || '}}' when 'foreign' then {_body(_O, "'[" + '"shiny"' + "]'", _T)}
when 'split' then {_body(_l("flatten(list_transform(origin, lambda x: string_split(x, ', ')))"), _C, _T)} when 'inner' then {_body(_l("list_transform(origin, lambda x: string_split(x, ', ')[1])"), _C, _T)}
when 'misplaced' then '{{"romance":["fr"],"condition":' || {_C} || ',"conduct":' || {_T} || '}}' when 'inverted' then '{{"clean":["item ' || doc_id || '"]}}' else {_body(_O, _C, _T)} end raw from kinds),
par as (select *, list_sort(json_keys(raw)) ks, {', '.join(f"(raw->'$.{k}')::varchar[] k_{k}" for k in A.KEYS)} from ans)"""


def _in(xs) -> str:
    return "[" + ", ".join(f"'{x}'" for x in xs) + "]"


_VALS = "(coalesce(k_origin, []) || coalesce(k_condition, []) || coalesce(k_conduct, []))"
_KNOWN = [*A.LABELS, *A.INNER, *A.LEAVES]


def _reason(vals: str = _VALS, ks: str = "ks") -> str:
    return f"""case when {ks} is null then 'not json' when list_has_any({ks}, {_in(A.INNER)}) then 'misplaced key' when list_has_any({ks}, {_in(A.LABELS)}) then 'inverted' when not list_has_all({ks}, {_in(C.TX1)}) then 'missing key'
when not list_has_all({_in(_KNOWN)}, {vals}) then 'foreign label' when list_has_any({vals}, {_in(A.INNER)}) and list_has_any({vals}, {_in(A.LEAVES)}) then 'split label' when list_has_any({vals}, {_in(A.INNER)}) then 'incomplete' else 'none' end"""


HEAD = f"{GOLD}, {SCORES}, {ANSWERS}"
REPAIRED = f"""fix as (select *, list_filter({_in(A.COMPOUND)}, lambda c: list_contains(coalesce(k_origin, []), string_split(c, ', ')[1]) and list_contains(coalesce(k_origin, []), string_split(c, ', ')[2])) joined from par),
fix2 as (select *, k_origin is not null or list_has_any(ks, {_in(A.INNER)}) touched, list_sort(list_distinct(list_filter(coalesce(k_origin, []), lambda x: not list_contains(flatten(list_transform(joined, lambda c: string_split(c, ', '))), x)) || joined
|| list_filter(list_transform(coalesce(k_germanic, []), lambda x: 'germanic, ' || x) || list_transform(coalesce(k_romance, []), lambda x: 'romance, ' || x), lambda x: list_contains({_in(A.COMPOUND)}, x)))) new_o from fix),
rep as (select model, run, doc_id, raw, case when touched then new_o else k_origin end k_origin, k_condition, k_conduct, case when touched then list_sort(list_distinct(list_filter(ks, lambda x: not list_contains({_in(A.INNER)}, x)) || ['origin'])) else ks end ks from fix2)"""
REPEATS = """news as (select *, coalesce((raw <> lag(raw) over (partition by model, run, doc_id // 20 order by doc_id))::int, 1) nw from ans),
streaks as (select *, sum(nw) over (partition by model, run, doc_id // 20 order by doc_id rows unbounded preceding) st from news),
flagged as (select model, run, doc_id, raw, count(*) over (partition by model, run, doc_id // 20, st) >= 3 repeated from streaks)"""


def _answers(spark, sf):
    """Written once: the texts are scored once, however many checks follow."""
    return staged(A.simulate_answers(C.select_labels(C.expert_scores(_labelled(spark, sf)))), "answers")


@query(f"with {HEAD} select model, run, doc_id, array_to_string(ks, '|') as keys, len({_VALS})::int n_values from par")
def answers_parsed(spark, sf):
    return A.parse_answers(_answers(spark, sf)).select("model", "run", "doc_id", F.array_join("keys", "|").alias("keys"), F.size(A._values()).alias("n_values"))


@query(f"with {HEAD} select model, run, {_reason()} reason, count(*) n from par group by 1, 2, 3")
def answers_valid(spark, sf):
    return A.check_validity(A.parse_answers(_answers(spark, sf))).groupBy("model", "run", "reason").agg(F.count("*").alias("n"))


@query(f"with {HEAD}, {REPAIRED} select model, run, {_reason()} reason, count(*) n, sum(len(coalesce(k_origin, [])))::bigint origins from rep group by 1, 2, 3")
def answers_repaired(spark, sf):
    fixed = A.check_validity(A.repair(A.parse_answers(_answers(spark, sf))))
    return fixed.groupBy("model", "run", "reason").agg(F.count("*").alias("n"), F.sum(F.coalesce(F.size("origin"), F.lit(0))).alias("origins")).withColumn("origins", F.greatest("origins", F.lit(0)))


@query(f"with {HEAD} select model, run, label, count(*) n from (select model, run, unnest(list_distinct({_VALS})) as label from par) where not list_contains({_in(_KNOWN)}, label) group by 1, 2, 3")
def hallucinated_labels(spark, sf):
    return A.made_up(A.parse_answers(_answers(spark, sf)))


@query(f"with {HEAD}, {REPEATS} select model, run, count(*) n, count(*) filter (where repeated) repeated from flagged group by 1, 2")
def repetition_invalid(spark, sf):
    return A.repetition_filter(_answers(spark, sf)).groupBy("model", "run").agg(F.count("*").alias("n"), F.count_if("repeated").alias("repeated"))


COMPARED = f"""{HEAD}, {REPAIRED}, {REPEATS}, why as (select model, run, doc_id, {_reason()} reason, k_origin, k_condition, k_conduct from rep),
good as (select w.* from why w join flagged f using (model, run, doc_id) where not repeated and reason in ('none', 'incomplete', 'foreign label')),
said as (select model, run, doc_id, domain, label from (select model, run, doc_id, 'origin' domain, unnest(list_distinct(k_origin)) as label from good union all select model, run, doc_id, 'condition', unnest(list_distinct(k_condition)) from good
union all select model, run, doc_id, 'conduct', unnest(list_distinct(k_conduct)) from good) where list_contains({_in(A.LABELS)}, label)),
gold_m as (select model, run, g.* from good join gold g using (doc_id)),
cnt as (select model, run, doc_id, domain, count(g) ng, count(q) nq, count(*) filter (where g is not null and q is not null) nb from (select model, run, doc_id, domain, g.label g, q.label q from gold_m g full join said q using (model, run, doc_id, domain, label)) group by 1, 2, 3, 4),
f as (select model, run, domain, avg(case when ng + nq = 0 then 1 else 2 * nb / (ng + nq) end) f1 from cnt group by 1, 2, 3),
tot as (select model, run, round(avg(f1), 6) total_f1 from f group by 1, 2)"""


def _compared(spark, sf):
    gold = _gold(spark, sf)
    answers = A.repetition_filter(_answers(spark, sf))
    fixed = staged(A.check_validity(A.repair(A.parse_answers(answers))), "answers-checked")
    good = fixed.where("not repeated and reason in ('none', 'incomplete', 'foreign label')")
    pred = A.answer_labels(good)
    gm = good.select("model", "run", "doc_id").join(gold, "doc_id")
    scores = M.item_scores(gm, pred, gm.select("model", "run", "doc_id", "domain").distinct(), ["model", "run", "doc_id"])
    return fixed, scores


@query(f"""with {COMPARED}, k as (select model, run, count(*) n, count(*) filter (where reason = 'foreign label') made_up from why group by 1, 2), v as (select model, run, count(*) valid from good group by 1, 2)
select k.model, k.run, n, coalesce(valid, 0) valid, round(made_up / n, 6) made_up_rate, made_up / n > 0.5 or coalesce(valid, 0) / n < 0.5 discarded, total_f1 from k left join v using (model, run) left join tot using (model, run)""")
def model_comparison(spark, sf):
    """Simulated models M1 to M4 over two runs, measured on their valid answers; those mostly wrong in form or labels are discarded."""
    fixed, scores = _compared(spark, sf)
    ok = F.expr("not repeated and reason in ('none', 'incomplete', 'foreign label')")
    k = fixed.groupBy("model", "run").agg(F.count("*").alias("n"), F.count_if(ok).alias("valid"), F.count_if(F.col("reason") == "foreign label").alias("made_up"))
    out = k.join(M.total_f1(scores, ["model", "run"]), ["model", "run"], "left")
    return out.select("model", "run", "n", "valid", F.round(F.col("made_up") / F.col("n"), 6).alias("made_up_rate"), F.expr("made_up / n > 0.5 or valid / n < 0.5").alias("discarded"), "total_f1")


TESTS = f"""{COMPARED}, {SETS.replace(GOLD + ',', '')}, m as (select c.model, c.run, dataset test, domain, count(*) items, avg(case when ng + nq = 0 then 1 when nq = 0 then 0 else nb / nq end) p, avg(case when ng + nq = 0 then 1 when ng = 0 then 0 else nb / ng end) r,
avg(case when ng + nq = 0 then 1 else 2 * nb / (ng + nq) end) f1 from cnt c join sets using (doc_id) group by 1, 2, 3, 4),
tt as (select model, test, run, avg(f1) total from m group by 1, 2, 3),
k as (select w.model, dataset test, w.run, count(*) n, count(*) filter (where not repeated and reason in ('none', 'incomplete', 'foreign label')) valid, count(*) filter (where reason = 'foreign label') made_up from why w join flagged using (model, run, doc_id) join sets using (doc_id) group by 1, 2, 3)"""


def _tests(spark, sf):
    """Measures of every test: (model, test, run, domain, items, p, r, f1), totals, and counts of answers."""
    fixed, scores = _compared(spark, sf)
    sets = staged(_sets(spark, sf).select("doc_id", F.col("dataset").alias("test")), "answers-sets")
    by = ["model", "test", "run"]
    own = scores.join(sets, "doc_id")
    per = staged(own.groupBy(*by, "domain").agg(F.count("*").alias("items"), *[F.avg(c).alias(c) for c in ("p", "r", "f1")]), "answers-tests")
    totals = per.groupBy(*by).agg(F.avg("f1").alias("total"))
    ok = F.expr("not repeated and reason in ('none', 'incomplete', 'foreign label')")
    k = fixed.join(sets, "doc_id").groupBy(*by).agg(F.count("*").alias("n"), F.count_if(ok).alias("valid"), F.count_if(F.col("reason") == "foreign label").alias("made_up"))
    return per, totals, k


@query(f"""with {TESTS} select k.model, k.test, k.run, d.domain, coalesce(items, 0) items, round(p, 6) p, round(r, 6) r, round(f1, 6) f1, round(total, 6) total_f1, n, valid, made_up / n > 0.5 or valid / n < 0.5 discarded
from k cross join (values ('origin'), ('condition'), ('conduct')) d(domain) left join m using (model, test, run, domain) left join tt using (model, test, run)""")
def model_tests(spark, sf):
    """SIMULATED models, each twice on set B with set A's examples and twice the other way: precision, recall, F1 per domain on valid answers, and the total."""
    per, totals, k = _tests(spark, sf)
    by = ["model", "test", "run"]
    grid = k.select("*", F.explode(F.array(*[F.lit(d) for d in C.TX1])).alias("domain"))
    out = grid.join(per, [*by, "domain"], "left").join(totals, by, "left")
    return out.select(
        *by, "domain", F.coalesce("items", F.lit(0)).alias("items"), *[F.round(c, 6).alias(c) for c in ("p", "r", "f1")], F.round("total", 6).alias("total_f1"), "n", "valid",
        F.expr("made_up / n > 0.5 or valid / n < 0.5").alias("discarded"),
    )


@query(f"with {TESTS} select model, test, count(*) runs, round(avg(total), 6) mean, round(max(total) - min(total), 6) spread, round(stddev_samp(total), 6) sd from tt group by 1, 2")
def metrics_variability(spark, sf):
    return M.variability(_tests(spark, sf)[1].withColumnRenamed("total", "total_f1"), ["model", "test"])


_SCORED = SCORES.replace("doc_id, lang, text", "doc_id, text").replace("from documents", "from i_condensed")


@query(f"""with recursive {GOLD}, {RUN.replace(GOLD + ',', '')}, {_SCORED}, al as (select t.fold, g.* from turns t join gold g using (doc_id)), pl as (select t.fold, p.doc_id, p.domain, p.label from turns t join picked p using (doc_id)),
c as (select fold, doc_id, domain, count(a) na, count(b) nb, count(*) filter (where a is not null and b is not null) nx from (select fold, doc_id, domain, al.label a, pl.label b from al full join pl using (fold, doc_id, domain, label)) group by 1, 2, 3),
calls as (select fold, count(*) calls, sum(chars)::bigint chars, max(prompts) longest_talk, count(doc_id) items from (select *, count(*) over (partition by fold, conv) prompts from turns) group by 1)
select fold, domain, any_value(items) items, any_value(calls) calls, any_value(chars) chars, any_value(longest_talk) longest_talk, any_value(items) valid, round(avg(case when na + nb = 0 then 1 when nb = 0 then 0 else nx / nb end), 6) p,
round(avg(case when na + nb = 0 then 1 when na = 0 then 0 else nx / na end), 6) r, round(avg(case when na + nb = 0 then 1 else 2 * nx / (na + nb) end), 6) f1 from c join calls using (fold) group by 1, 2""")
def classification_run(spark, sf):
    """From sets to measures: prompts of both folds, the experts' answers as JSON, parsed, repaired, checked, and measured per domain."""
    run = staged(_run(spark, sf), "run")
    calls = run.groupBy("fold").agg(F.count("*").alias("calls"), F.sum("chars").alias("chars"), F.max("prompts").alias("longest_talk"), F.count("doc_id").alias("items"))
    answers = run.where("kind = 'item'").select(F.lit("experts").alias("model"), F.col("fold").alias("run"), "doc_id", "raw")
    good = staged(A.check_validity(A.repair(A.parse_answers(answers))).where("reason in ('none', 'incomplete', 'foreign label')"), "run-valid")
    gold = good.select("model", "run", "doc_id").join(_gold(spark, sf), "doc_id")
    scores = M.item_scores(gold, A.answer_labels(good), gold.select("model", "run", "doc_id", "domain").distinct(), ["model", "run", "doc_id"])
    per = scores.groupBy(F.col("run").alias("fold"), "domain").agg(*[F.round(F.avg(c), 6).alias(c) for c in ("p", "r", "f1")])
    valid = good.groupBy(F.col("run").alias("fold")).agg(F.count("*").alias("valid"))
    return per.join(calls, "fold").join(valid, "fold").select("fold", "domain", "items", "calls", "chars", "longest_talk", "valid", "p", "r", "f1")


@query(f"with {GOLD}, {SCORES}, pl as (select p.* from picked p join lab using (doc_id)) select doc_id, '{{' || string_agg(part, ',' order by k) || '}}' raw from (select doc_id, d.k, '\"' || d.domain || '\":' || (case when count(p.label) = 0 then '[]' else '[\"' || string_agg(p.label, '\",\"' order by p.label) || '\"]' end) part from (select distinct doc_id from pl) cross join (values (1, 'origin'), (2, 'condition'), (3, 'conduct')) d(k, domain) left join pl p using (doc_id, domain) group by 1, d.k, d.domain) group by 1")
def answer_json(spark, sf):
    return A.answer_json(C.select_labels(C.expert_scores(_labelled(spark, sf))))
