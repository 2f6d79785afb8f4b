"""Queries: context calibration."""

from __future__ import annotations

from pyspark.sql import functions as F

from catalogflow.functions.text import sql_hash60
from catalogflow.operators import probe as P
from catalogflow.operators.metadata import VOTES
from catalogflow.plans.registry import load, query

SEED = "s1"
NEEDLE = "Le nom est dans la liste des villes et pour une raison les habitants du pays qui est petit"
_IN = lambda ws: "(" + ", ".join(f"'{w}'" for w in ws) + ")"
_OWN = VOTES["en"].split()
_OTHER = [w for x, ws in VOTES.items() if x != "en" for w in ws.split() if w not in _OWN]
_COUNT = lambda ws: f"len(list_filter(string_split_regex(lower(s), '[^a-zà-ÿß]+'), lambda t: t in {_IN(ws)}))"
_DRAW = lambda kind: sql_hash60(f"'{SEED}{kind}' || h") + " % 1000"
GRID = f"""d as (select test, doc_id, text, {sql_hash60(f"'{SEED}/' || test || '/' || doc_id")} k from documents, range(1, 5) t(test) where lang = 'en' and text is not null),
bef as (select *, coalesce(sum(length(text) + 1) over (partition by test order by k, doc_id rows between unbounded preceding and 1 preceding), 0) b from d),
hays as (select test, string_agg(text, ' ' order by b) body from bef where b < 23000 group by 1),
grid as (select test::int test, level::int as level, attempt::int attempt, {sql_hash60(f"'{SEED}/' || test || '/' || level || '/' || attempt")} h from range(1, 5) t(test), range(10000, 23001, 500) l(level), range(1, 7) a(attempt)),
placed as (select *, (1 + h % level)::int pos, least(4, 1 + (4 * (h % level)) // level)::int quartile from grid),
cut as (select p.*, substr(body, 1, p.level) hay from placed p join hays using (test)),
stops as (select *, case when strpos(substr(hay, pos), '.') = 0 then length(hay) else pos - 1 + strpos(substr(hay, pos), '.') end stop from cut),
full_text as materialized (select * exclude (hay, stop), substr(hay, 1, stop) || ' ' || '{NEEDLE}.' || substr(hay, stop + 1) text from stops),
sent as (select test, level, attempt, i, trim(s[i]) s from (select *, unnest(range(1, len(s) + 1)) i from (select *, list_filter(string_split(text, '.'), lambda x: trim(x) <> '') s from full_text))),
best as (select test, level, attempt, arg_max(s, ({_COUNT(_OTHER)} - {_COUNT(_OWN)}, -i)) s from sent group by 1, 2, 3),
answers as (select 'exact' finder, test, level, attempt, pos, quartile, contains(text, '{NEEDLE}') correct, true json_ok from full_text
union all select 'outlier', f.test, f.level, f.attempt, pos, quartile, contains(s, '{NEEDLE}'), true from full_text f join best using (test, level, attempt)
union all select 'simulated', test, level, attempt, pos, quartile, {_DRAW('e')} >= (case when level > 19000 then 350 else 160 end) + (case when quartile <= 2 then 60 else -60 end), {_DRAW('j')} < 850 from placed),
firsts as (select *, min(attempt) filter (where correct) over (partition by finder, test, level) fi from answers),
kept as (select * from firsts where fi is null or attempt <= fi),
trials as (select k.finder, k.test, k.level, attempt, pos, quartile, correct, json_ok from kept k where not exists (select 1 from kept d where d.finder = k.finder and d.test = k.test and d.level < k.level and d.fi is null))"""


def _planted(spark, sf):
    """The needle in real text, for every trial that a ladder could need."""
    trials = P.place_needle(P.ladder_grid(spark), SEED)
    return P.plant(trials, P.haystacks(load(spark, sf, "documents"), 4, SEED, "en"), NEEDLE)


def _trials(spark, sf):
    """Three readers of the same texts: one that can't fail, one that looks for the odd sentence, and a SIMULATED model."""
    planted = _planted(spark, sf)
    out = None
    for name, got in (("exact", P.exact_finder(planted)), ("outlier", P.outlier_finder(planted, "en")), ("simulated", P.simulated_finder(planted, SEED))):
        part = P.grade_needle(got).select(F.lit(name).alias("finder"), "test", "level", "attempt", "pos", "quartile", "correct", "json_ok")
        out = part if out is None else out.union(part)
    return P.run_ladder(out, ["finder"])


@query(f"with {GRID} select finder, test, level, attempt, pos, quartile, correct, json_ok from trials")
def needle_trials(spark, sf):
    return _trials(spark, sf)


@query(f"with {GRID} select finder, test, max(level) filter (where correct) reached, count(*) filter (where correct) successes, count(*) filter (where not correct) errors from trials group by 1, 2")
def needle_ladder(spark, sf):
    return _trials(spark, sf).groupBy("finder", "test").agg(F.max(F.when(F.col("correct"), F.col("level"))).alias("reached"), F.count_if("correct").alias("successes"), F.count_if(~F.col("correct")).alias("errors"))


@query(f"with {GRID} select finder, quartile, count(*) n, count(*) filter (where not correct) errors, round(count(*) filter (where not correct) / count(*), 6) share from trials group by 1, 2")
def needle_by_quartile(spark, sf):
    return P.errors_by_quartile(_trials(spark, sf), ["finder"])


@query(f"with {GRID}, b as (select *, case when level <= 19000 then 'low' else 'high' end band from trials) select finder, band, level, count(*) n, count(*) filter (where not correct) errors from b group by grouping sets ((finder, band, level), (finder, band), (finder))")
def needle_by_limit(spark, sf):
    return P.errors_by_limit(_trials(spark, sf), ["finder"])


@query(f"with {GRID} select finder, quartile, count(*) n, count(*) filter (where json_ok) conform, round(count(*) filter (where json_ok) / count(*), 6) rate from trials group by grouping sets ((finder, quartile), (finder))")
def needle_conformance(spark, sf):
    per = _trials(spark, sf).groupingSets([["finder", "quartile"], ["finder"]], "finder", "quartile").agg(F.count("*").alias("n"), F.count_if("json_ok").alias("conform"))
    return per.withColumn("rate", F.round(F.col("conform") / F.col("n"), 6))


@query(f"""with {GRID}, per as (select finder, level, count(*) n, count(*) filter (where not correct) e from trials group by 1, 2),
run as (select finder, level, sum(e) over w / sum(n) over w share from per window w as (partition by finder order by level)), bad as (select finder, level, max((share > 0.3)::int) over (partition by finder order by level) b from run)
select finder, max(level) filter (where b = 0)::int budget from bad group by 1""")
def needle_budget(spark, sf):
    return P.choose_budget(_trials(spark, sf), 0.3, ["finder"])


@query(f"with {GRID} select test, level, quartile, contains(s, '{NEEDLE}') correct from best join placed using (test, level, attempt) where attempt = 1")
def needle_outlier_finder(spark, sf):
    """First attempts of the reader that looks for the odd sentence, whether a ladder would have come so far or not."""
    first = P.outlier_finder(_planted(spark, sf).where("attempt = 1"), "en")
    return P.grade_needle(first).select("test", "level", "quartile", "correct")


_FORM = P.FORM.replace("'", "''")
_ASK = P.ASK.replace("'", "''")


@query(f"""with {GRID}, p as (select position, test, level, attempt, case position when 'start' then concat_ws(chr(10), '{_FORM}', '{_ASK}', text) when 'middle' then concat_ws(chr(10), '{_ASK}', '{_FORM}', text) else concat_ws(chr(10), '{_ASK}', text, '{_FORM}') end prompt,
{_DRAW('j')} < case position when 'start' then 780 when 'middle' then 740 else 850 end json_ok from full_text, (values ('start'), ('middle'), ('end')) v(position))
select position, count(*) n, count(*) filter (where json_ok) conform, round(avg(strpos(prompt, '{_FORM}') / length(prompt)), 6) place, sum(length(prompt))::bigint chars from p group by 1""")
def needle_conformance_position(spark, sf):
    """Prompts with the demand for JSON really moved; the reader is SIMULATED, its rates are invented but for the end."""
    planted = _planted(spark, sf)
    out = None
    for position in P.JSON_RATES:
        p = P.grade_needle(P.simulated_finder(P.needle_prompt(planted, position), SEED, position))
        part = p.agg(F.lit(position).alias("position"), F.count("*").alias("n"), F.count_if("json_ok").alias("conform"), F.round(F.avg(F.instr("prompt", F.lit(P.FORM)) / F.length("prompt")), 6).alias("place"), F.sum(F.length("prompt")).alias("chars"))
        out = part if out is None else out.union(part)
    return out


@query("select doc_id, item_id, strpos(d.text, b.text)::int pos, least(4, 1 + (4 * (strpos(d.text, b.text) - 1)) // length(d.text))::int quartile from documents d join benchmark b on contains(d.text, b.text) and b.text <> ''")
def needle_passages(spark, sf):
    return P.find_passages(load(spark, sf, "documents"), load(spark, sf, "benchmark"))
