"""Operator 5: mix sources to target weights by hash thresholds, without sorting.

Every document has a 60-bit hash of its id. For each source and budget a threshold is sought so that the documents
whose hash is at most the threshold hold as many tokens as fit in the budget. Tokens are summed by source and the
hash's leading 12 bits; the bucket in which the budget runs out is summed again by the next 12 bits, and so on, until
the threshold is exact (five rounds at most, each over one bucket's documents per source and budget). Budgets that rise
give thresholds that rise, so smaller samples are contained in larger ones.

Defined cases: null ``source`` is a source of its own, named ''; null ``doc_id`` hashes as 'null', and rows with the same
id (ties, repeated rows) are taken or left together; null or empty text has no tokens and is taken at the lowest
hash positions like any row. A source of weight 0 or without tokens is left out of the total (its budget is 0, so that at most rows without
tokens are taken of it); where no source has both, every budget is 0.
Empty table: empty result. Extra columns aren't read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.llm.order import free_name
from catalogflow.session import broadcast_small, staged

HASH = "cast(conv(substring(md5(coalesce(cast(doc_id as string), 'null')), 1, 15), 16, 10) as bigint)"
BITS, STEP = 60, 12


def word_count(text: str = "text") -> Column:
    """Words between white space (blank, tab, line feed, carriage return), as bigint; 0 for null."""
    return F.expr(f"cast(coalesce(length(regexp_replace({text}, '[^ \\\\t\\\\n\\\\r]+', 'x')) - length(regexp_replace({text}, '[^ \\\\t\\\\n\\\\r]+', '')), 0) as bigint)")


def light_rows(docs: DataFrame, tokens: Column | None = None) -> DataFrame:
    """(doc_id, source, tokens, h): all that the method needs, written once so that texts are read once."""
    t = word_count() if tokens is None else tokens
    return staged(docs.select("doc_id", F.coalesce("source", F.lit("")).alias("source"), t.alias("tokens"), F.expr(HASH).alias("h")), "mix-light")


def budgets(light: DataFrame, weights: dict[str, int], default_weight: int, percents: list[int], temperature: float | None = None) -> DataFrame:
    """(source, level, budget): whole numbers.

    For given weights they are met exactly: the total is the largest that no source falls short of. By ``temperature`` the total is that
    of the whole corpus, shared out by weight; a source that falls short of its share gives all that it has, so that a tiny one
    changes no other's budget by more than its own part of the corpus.
    """
    have = light.groupBy("source").agg(F.sum("tokens").alias("have"))
    if temperature is not None:
        have = have.withColumn("w", F.greatest(F.lit(1), F.round(F.pow(F.col("have").cast("double"), F.lit(temperature)))).cast("bigint"))
    elif weights:
        pick = F.create_map(*[F.lit(x) for kv in weights.items() for x in kv])
        have = have.withColumn("w", F.coalesce(F.try_element_at(pick, F.col("source")), F.lit(default_weight)).cast("bigint"))
    else:
        have = have.withColumn("w", F.lit(default_weight).cast("bigint"))
    some = have.where("w > 0 and have > 0")
    if temperature is None:
        unit = some.agg(F.min(F.expr("(have * 1000000) div w")).alias("unit"))
    else:
        unit = some.agg(F.expr("cast((cast(sum(have) as decimal(32,0)) * 1000000) div sum(w) as bigint)").alias("unit"))
    share = "cast(unit as decimal(38,0)) * w" if temperature is None else "least(cast(unit as decimal(38,0)) * w, cast(have as decimal(38,0)) * 1000000)"
    unit = unit.select(F.coalesce("unit", F.lit(0)).alias("unit"))  # no source has both weight and tokens
    levels = F.explode(F.array(*[F.struct(F.lit(i + 1).alias("level"), F.lit(p).cast("bigint").alias("p")) for i, p in enumerate(sorted(percents))])).alias("x")
    return (
        have.crossJoin(unit).select("source", "w", "have", "unit", levels)
        .select("source", F.col("x.level").alias("level"), F.expr(f"cast(({share}) * x.p div 100000000 as bigint)").alias("budget"))
    )


def thresholds(light: DataFrame, limits: DataFrame) -> DataFrame:
    """(source, level, threshold): the largest hash up to which the tokens fit in the budget; -1 where none does.

    Tables that grow with sources x levels only (at most 4,096 buckets each) go through the windows. The frontier has one row per
    source and level; it is counted, and broadcast only if it is small.
    """
    front = staged(limits.select("source", "level", F.col("budget").alias("left"), F.lit(0).cast("bigint").alias("low")), "mix-front")
    done = None
    for shift in range(BITS - STEP, -1, -STEP):
        width = 1 << (shift + STEP)
        part = light.join(broadcast_small(front), "source").where((F.col("h") >= F.col("low")) & (F.col("h") < F.col("low") + F.lit(width)))
        hist = part.groupBy("source", "level", "low", "left", F.shiftright(F.col("h") - F.col("low"), shift).alias("bucket")).agg(F.sum("tokens").alias("t"))
        run = Window.partitionBy("source", "level").orderBy("bucket")
        hist = hist.withColumn("upto", F.sum("t").over(run))
        hit = (
            hist.where("upto > left").groupBy("source", "level")
            .agg(F.min("bucket").alias("bucket"), F.min_by(F.col("left") - (F.col("upto") - F.col("t")), "bucket").alias("rest"))
        )
        step = staged(front.join(hit, ["source", "level"], "left"), "mix-step")
        # no bucket overflows: everything up to the end of this range fits
        ended = step.where("bucket is null").select("source", "level", (F.col("low") + F.lit(width - 1)).alias("threshold"))
        go = step.where("bucket is not null").select("source", "level", F.col("rest").alias("left"), (F.col("low") + F.col("bucket") * F.lit(1 << shift)).alias("low"))
        done = ended if done is None else done.union(ended)
        front = go
        if front.isEmpty():
            return done
    return done.union(front.select("source", "level", (F.col("low") - 1).alias("threshold")))


def mix_levels(docs: DataFrame, weights: dict[str, int] | None = None, default_weight: int = 1, percents: list[int] = (100,), tokens: Column | None = None, temperature: float | None = None) -> DataFrame:
    """(doc_id, source, tokens, level) of the chosen documents; level is the smallest budget that takes the document."""
    light = light_rows(docs, tokens)
    cut = thresholds(light, budgets(light, weights or {}, default_weight, list(percents), temperature))
    wide = staged(cut.groupBy("source").agg(F.array_sort(F.collect_list(F.struct("level", "threshold"))).alias("cuts")), "mix-cuts")
    level = F.expr("get(filter(cuts, c -> c.threshold >= h), 0).level")
    return light.join(broadcast_small(wide), "source").withColumn("level", level).where("level is not null").select("doc_id", "source", "tokens", "level")


def mix_documents(docs: DataFrame, weights: dict[str, int] | None = None, default_weight: int = 1, tokens: Column | None = None, temperature: float | None = None) -> DataFrame:
    """The rows of ``docs`` that the full budgets take, with their own columns: a filter on the hash, no join on ids."""
    light = light_rows(docs, tokens)
    cut = thresholds(light, budgets(light, weights or {}, default_weight, [100], temperature)).select("source", "threshold")
    # one struct column under a name that no column of docs has
    name = free_name(docs, "mix_cut")
    cut = staged(cut.select(F.struct("source", "threshold").alias(name)), "mix-cuts")
    kept = docs.join(broadcast_small(cut), F.coalesce(docs["source"], F.lit("")) == F.col(f"{name}.source"))
    return kept.where(F.expr(HASH) <= F.col(f"{name}.threshold")).drop(name)
