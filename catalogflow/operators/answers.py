"""Answers of labelling models: simulation of their failures, parsing, validity, repair, repetition, made-up labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.functions.text import hash60
from catalogflow.operators.classify import INNER, TX1

LABELS = [x for ls in TX1.values() for x in ls]
COMPOUND = [x for x in LABELS if ", " in x]
LEAVES = [x.split(", ")[1] for x in COMPOUND]
KEYS = [*TX1, *INNER]
#: Per simulated model: defect kinds with their cumulative per cent. Rates are invented to exercise the checks.
DEFECTS = {
    "M1": [("missing", 70)], "M2": [("foreign", 60)], "M3": [("split", 20), ("inner", 30), ("foreign", 35)], "M4": [("misplaced", 10), ("foreign", 15), ("inverted", 16)],
}
REPEATED = '{"origin":["germanic, en"],"condition":["clean"],"conduct":["civil"]}'


def _list(c: Column) -> Column:
    return F.when(F.size(c) == 0, F.lit("[]")).otherwise(F.concat(F.lit('["'), F.array_join(c, '","'), F.lit('"]')))


def simulate_answers(picked: DataFrame, runs: int = 2) -> DataFrame:
    """(model, run, doc_id, raw): SIMULATED answers: the expert's labels with the defects of DEFECTS, one kind per row.

    M4 also repeats one answer over the first three items of each twenty.
    """
    lab = lambda d: F.array_sort(F.collect_list(F.when(F.col("domain") == d, F.col("label"))))
    per = picked.groupBy("doc_id").agg(*[lab(d).alias(d) for d in TX1])
    grid = F.explode(F.array(*[F.struct(F.lit(m).alias("model"), F.lit(r).alias("run")) for m in DEFECTS for r in range(1, runs + 1)])).alias("g")
    rows = per.select("*", grid).select("g.model", "g.run", "doc_id", *TX1)
    rows = rows.withColumn("h", hash60("concat(model, '/', cast(run as string), '/', cast(doc_id as string))") % 100)
    kind = F.lit("none")
    for m, cuts in DEFECTS.items():
        low = 0
        for k, cut in cuts:
            kind = F.when((F.col("model") == m) & (F.col("h") >= low) & (F.col("h") < cut), F.lit(k)).otherwise(kind)
            low = cut
    rows = rows.withColumn("kind", F.when((F.col("model") == "M4") & (F.col("doc_id") % 20 < 3), F.lit("repeat")).otherwise(kind))
    o, c, t = _list(F.col("origin")), _list(F.col("condition")), _list(F.col("conduct"))
    inner = lambda f: F.transform("origin", lambda x: f(F.split(x, ", ")))
    body = lambda o_, c_, t_: F.concat(F.lit('{"origin":'), o_, F.lit(',"condition":'), c_, F.lit(',"conduct":'), t_, F.lit("}"))
    raw = (
        F.when(F.col("kind") == "repeat", F.lit(REPEATED)).when(F.col("kind") == "missing", F.concat(F.lit('{"origin":'), o, F.lit(',"condition":'), c, F.lit("}")))
        .when(F.col("kind") == "foreign", body(o, F.lit('["shiny"]'), t)).when(F.col("kind") == "split", body(_list(F.flatten(F.transform("origin", lambda x: F.split(x, ", ")))), c, t))
        .when(F.col("kind") == "inner", body(_list(inner(lambda p: p[0])), c, t))
        .when(F.col("kind") == "misplaced", F.concat(F.lit('{"romance":["fr"],"condition":'), c, F.lit(',"conduct":'), t, F.lit("}")))
        .when(F.col("kind") == "inverted", F.concat(F.lit('{"clean":["item '), F.col("doc_id").cast("string"), F.lit('"]}'))).otherwise(body(o, c, t))
    )
    return rows.select("model", "run", "doc_id", raw.alias("raw"))


def parse_answers(answers: DataFrame) -> DataFrame:
    """Adds keys (sorted; null where raw is no JSON object) and one list per key of KEYS (null where absent)."""
    parsed = F.from_json("raw", "map<string,array<string>>")
    out = answers.withColumn("m_", parsed).withColumn("keys", F.array_sort(F.map_keys("m_")))
    for k in KEYS:
        out = out.withColumn(k, F.try_element_at("m_", F.lit(k)))
    return out.drop("m_")


def _values() -> Column:
    some = [F.coalesce(F.col(k), F.array().cast("array<string>")) for k in TX1]
    return F.concat(*some)


def check_validity(parsed: DataFrame) -> DataFrame:
    """Adds reason: none, or the first of not JSON, misplaced key, inverted, missing key, foreign label, split label, incomplete."""
    lit = lambda xs: F.array(*[F.lit(x) for x in xs])
    v = _values()
    inner, leaf = F.array_intersect(v, lit(INNER)), F.array_intersect(v, lit(LEAVES))
    reason = (
        F.when(F.col("keys").isNull(), "not json").when(F.arrays_overlap("keys", lit(INNER)), "misplaced key").when(F.arrays_overlap("keys", lit(LABELS)), "inverted")
        .when(F.size(F.array_except(lit(TX1), F.col("keys"))) > 0, "missing key").when(F.size(F.array_except(v, lit([*LABELS, *INNER, *LEAVES]))) > 0, "foreign label")
        .when((F.size(inner) > 0) & (F.size(leaf) > 0), "split label").when(F.size(inner) > 0, "incomplete").otherwise("none")
    )
    return parsed.withColumn("reason", reason)


def repair(parsed: DataFrame) -> DataFrame:
    """Split labels are joined again and inner keys moved below their domain; nothing is invented for incomplete answers."""
    lit = lambda xs: F.array(*[F.lit(x) for x in xs])
    none = F.array().cast("array<string>")
    joined = F.filter(lit(COMPOUND), lambda c: F.array_contains(F.coalesce(F.col("origin"), none), F.split(c, ", ")[0]) & F.array_contains(F.coalesce(F.col("origin"), none), F.split(c, ", ")[1]))
    used = F.flatten(F.transform(joined, lambda c: F.split(c, ", ")))
    moved = F.concat(*[F.transform(F.coalesce(F.col(k), none), lambda x: F.concat(F.lit(k + ", "), x)) for k in INNER])
    new = F.array_sort(F.array_distinct(F.concat(F.array_except(F.coalesce(F.col("origin"), none), used), joined, F.array_intersect(moved, lit(COMPOUND)))))
    touched = F.col("keys").isNotNull() & (F.col("origin").isNotNull() | F.arrays_overlap("keys", lit(INNER)))
    keys = F.when(touched, F.array_sort(F.array_union(F.array_except("keys", lit(INNER)), lit(["origin"])))).otherwise(F.col("keys"))
    return parsed.withColumn("origin", F.when(touched, new).otherwise(F.col("origin"))).withColumn("keys", keys)


def made_up(parsed: DataFrame) -> DataFrame:
    """(model, run, label, n): values that no taxonomy label, inner node or leaf accounts for."""
    known = [*LABELS, *INNER, *LEAVES]
    return parsed.select("model", "run", F.explode(F.array_distinct(_values())).alias("label")).where(~F.col("label").isin(*known)).groupBy("model", "run", "label").agg(F.count("*").alias("n"))


def repetition_filter(answers: DataFrame, least: int = 3, talk: int = 20) -> DataFrame:
    """Adds repeated: the answer stands in a row of ``least`` equal ones within its talk (``talk`` items of a run)."""
    w = Window.partitionBy("model", "run", F.expr(f"doc_id div {talk}")).orderBy("doc_id")
    out = answers.withColumn("new_", F.coalesce((F.col("raw") != F.lag("raw").over(w)).cast("int"), F.lit(1)))
    out = out.withColumn("streak_", F.sum("new_").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    n = F.count("*").over(Window.partitionBy("model", "run", F.expr(f"doc_id div {talk}"), "streak_"))
    return out.withColumn("repeated", n >= least).drop("new_", "streak_")


def answer_labels(parsed: DataFrame) -> DataFrame:
    """(model, run, doc_id, domain, label) of the labels that belong to their domain."""
    per = []
    for d, labels in TX1.items():
        own = F.array(*[F.lit(x) for x in labels])
        per.append(parsed.select("model", "run", "doc_id", F.lit(d).alias("domain"), F.explode(F.array_intersect(F.coalesce(F.col(d), F.array().cast("array<string>")), own)).alias("label")))
    out = per[0]
    for p in per[1:]:
        out = out.union(p)
    return out


def answer_json(picked: DataFrame) -> DataFrame:
    """(doc_id, raw): one key per domain with its labels, also where there are none."""
    lab = lambda d: F.array_sort(F.collect_list(F.when(F.col("domain") == d, F.col("label"))))
    return picked.groupBy("doc_id").agg(F.to_json(F.struct(*[lab(d).alias(d) for d in TX1])).alias("raw"))
