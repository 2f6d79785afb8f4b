"""Measures of multi-label answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def item_scores(gold: DataFrame, pred: DataFrame, base: DataFrame, keys: list[str], empty: str = "one") -> DataFrame:
    """keys + (domain, p, r, f1) for each row of base (keys, domain). Both sets empty: 1 ('one'), 0 ('zero') or left out ('skip')."""
    on = [*keys, "domain", "label"]
    j = gold.select(*on).withColumn("g", F.lit(1)).join(pred.select(*on).withColumn("q", F.lit(1)), on, "full")
    n = j.groupBy(*keys, "domain").agg(F.count("g").alias("ng"), F.count("q").alias("nq"), F.count(F.expr("case when g = 1 and q = 1 then 1 end")).alias("nb"))
    b = base.join(n, [*keys, "domain"], "left").fillna(0, ["ng", "nq", "nb"])
    both = {"one": 1.0, "zero": 0.0, "skip": 0.0}[empty]
    if empty == "skip":
        b = b.where("ng + nq > 0")
    share = lambda over: F.expr(f"case when ng + nq = 0 then {both}D when {over} = 0 then 0D else nb / {over} end")
    return b.select(*keys, "domain", share("nq").alias("p"), share("ng").alias("r"), F.expr(f"case when ng + nq = 0 then {both}D else 2 * nb / (ng + nq) end").alias("f1"))


def domain_scores(scores: DataFrame, by: list[str] = ()) -> DataFrame:
    """Mean over items: F1 is averaged per item, not made from the mean precision and recall."""
    return scores.groupBy(*by, "domain").agg(F.count("*").alias("items"), *[F.round(F.avg(c), 6).alias(c) for c in ("p", "r", "f1")])


def total_f1(scores: DataFrame, by: list[str] = ()) -> DataFrame:
    per = scores.groupBy(*by, "domain").agg(F.avg("f1").alias("f1"))
    return per.groupBy(*by).agg(F.round(F.avg("f1"), 6).alias("total_f1"))


def variability(totals: DataFrame, by: list[str]) -> DataFrame:
    """Over runs: mean, range and sample deviation of total F1."""
    return totals.groupBy(*by).agg(F.count("*").alias("runs"), F.round(F.avg("total_f1"), 6).alias("mean"), F.round(F.max("total_f1") - F.min("total_f1"), 6).alias("spread"), F.round(F.stddev_samp("total_f1"), 6).alias("sd"))


def multilabel_summary(gold: DataFrame, pred: DataFrame, item: str, n_labels: int) -> DataFrame:
    """One row: micro precision, recall and F1, subset accuracy, Hamming loss, mean Jaccard over items."""
    on = [item, "domain", "label"]
    j = gold.select(*on).withColumn("g", F.lit(1)).join(pred.select(*on).withColumn("q", F.lit(1)), on, "full")
    per = j.groupBy(item).agg(F.count("g").alias("ng"), F.count("q").alias("nq"), F.count(F.expr("case when g = 1 and q = 1 then 1 end")).alias("nb"))
    s = per.agg(F.count("*").alias("n"), F.sum("ng").alias("g"), F.sum("nq").alias("q"), F.sum("nb").alias("b"), F.avg(F.expr("cast(ng = nb and nq = nb as double)")).alias("subset"), F.avg(F.expr("nb / (ng + nq - nb)")).alias("jac"), F.sum(F.expr("ng + nq - 2 * nb")).alias("wrong"))
    return s.select("n", F.round(F.col("b") / F.col("q"), 6).alias("micro_p"), F.round(F.col("b") / F.col("g"), 6).alias("micro_r"), F.round(2 * F.col("b") / (F.col("g") + F.col("q")), 6).alias("micro_f1"), F.round("subset", 6).alias("subset_accuracy"), F.round(F.col("wrong") / (F.col("n") * n_labels), 6).alias("hamming_loss"), F.round("jac", 6).alias("jaccard"))


def coverage(sets: DataFrame, gold: DataFrame, n_labels: int) -> DataFrame:
    """Size of each dataset and the share of labels that it holds."""
    return sets.join(gold, "doc_id").groupBy("dataset").agg(F.countDistinct("doc_id").alias("items"), F.countDistinct("domain", "label").alias("labels")).withColumn("covered", F.round(F.col("labels") / n_labels, 6))


def call_budget(prompts: DataFrame, chars: str = "chars") -> DataFrame:
    """What a run would send to a model: calls and characters, counted before any call."""
    return prompts.agg(F.count("*").alias("calls"), F.sum(chars).alias("chars"), F.max(chars).alias("longest"))
