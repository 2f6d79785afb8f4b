"""Operator 6: URL filter by empirical-Bayes reputation of hosts.

Labelled pages are Bernoulli outcomes (bad or not). Hosts lie below registered domains, those below suffixes, those below the
whole. At each level a node's prior is a beta distribution whose mean is the parent's posterior mean and whose strength is estimated
from the spread of the nodes of that level by the method of moments (between ``least`` and ``most`` pseudo-outcomes).
Hosts without labels get their parents' belief. A URL is dropped if the lower posterior bound of its host's bad rate,
mean - z * standard deviation of the beta posterior, lies above ``cutoff``.

Hosts: authority of the URL, lower case, without user, port and final dot. Suffix: the longest of ``suffixes`` that the host ends
with, else the last label. Registered domain: the suffix and one label more. Defined cases: null, empty or unparsable URLs
have host '' and are kept, unjudged (rate null), and so are URLs of any length that don't parse; null ids: one output row per input
row, without outcome; pages without outcome don't count; r rows of one page with q outcomes count r x q times, so a row that stands
four times with one label is four outcomes; no outcomes at all: the prior mean is ``start``. Empty table: empty result. Extra columns
aren't read, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from catalogflow.session import staged

LEVELS = ("suffix", "domain", "host")


def host_of(url: str) -> Column:
    text = F.lower(F.regexp_extract(F.coalesce(F.col(url), F.lit("")), r"^[A-Za-z][A-Za-z0-9+.\-]*://([^/?#]*)", 1))
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(text, r"^.*@", ""), r":[0-9]*$", ""), r"[.]$", "")


def split_host(pages: DataFrame, suffixes: tuple[str, ...] = (), url: str = "url") -> DataFrame:
    """Adds host, domain and suffix."""
    out = pages.withColumn("host", host_of(url))
    known = [F.when(F.col("host").endswith("." + s) | (F.col("host") == s), F.lit(s)) for s in sorted(suffixes, key=len, reverse=True)]
    out = out.withColumn("suffix", F.coalesce(*known, F.substring_index("host", ".", -1)))
    inner = F.expr("case when host = suffix then '' else substring(host, 1, length(host) - length(suffix) - 1) end")
    return out.withColumn("domain", F.when(inner == "", F.col("host")).otherwise(F.concat_ws(".", F.substring_index(inner, ".", -1), F.col("suffix"))))


def _strength(nodes: DataFrame, least: float, most: float) -> float:
    """Pseudo-outcomes of the prior, from nodes (k bad of n, prior mean m).

    Moments: E[(k/n - m)^2] = m (1 - m) / n * (1 + (n - 1) / (s + 1)).
    """
    x = nodes.where("n > 1").agg(
        F.sum(F.expr("n * power(k / n - m, 2)")).alias("spread"), F.sum(F.expr("m * (1 - m)")).alias("within"), F.sum(F.expr("m * (1 - m) * (n - 1)")).alias("between")
    ).first()
    rho = (x["spread"] - x["within"]) / x["between"] if (x["between"] or 0) > 0 else 0.0
    return max(least, min(most, 1 / rho - 1 if rho > 0 else most))


def reputation(outcomes: DataFrame, least: float = 2.0, most: float = 200.0, start: float = 0.1) -> DataFrame:
    """(host, domain, suffix, n, k, mean, sd) of all hosts; outcomes: (host, domain, suffix, n, k), k bad ones among n.

    Outcomes are summed to hosts first; all later steps are on hosts and coarser. Hosts and each level's beliefs are written, so
    that no level is computed twice; what comes to the driver is one row per level.
    """
    total = [F.sum("n").cast("double").alias("n"), F.sum("k").cast("double").alias("k")]
    hosts = staged(outcomes.where("host <> ''").groupBy("host", "domain", "suffix").agg(*total), "host-sums")
    whole = hosts.agg(F.expr(f"(coalesce(sum(k), 0) + {start} * {least}) / (coalesce(sum(n), 0) + {least})").alias("m")).first()["m"]
    belief = None
    for level in LEVELS:
        own = LEVELS[: LEVELS.index(level) + 1]
        sums = hosts if level == LEVELS[-1] else hosts.groupBy(*own).agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
        nodes = staged(sums.withColumn("m", F.lit(whole)) if belief is None else sums.join(belief, list(own[:-1])), f"host-{level}")
        nodes = nodes.withColumn("s", F.lit(_strength(nodes, least, most))).withColumn("mean", F.expr("(k + s * m) / (n + s)"))
        belief = nodes.select(*own, F.col("mean").alias("m"))
    return nodes.select("host", "domain", "suffix", "n", "k", "mean", F.expr("sqrt(mean * (1 - mean) / (n + s + 1))").alias("sd"))


def filter_urls(pages: DataFrame, labelled: DataFrame, suffixes: tuple[str, ...] = (), z: float = 1.645, cutoff: float = 0.25, key: str | Column = "page_id", **options) -> DataFrame:
    """(page_id, url, host, domain, n, mean, bound, kept); labelled: (page_id, bad 0/1), where page_id is the value of ``key`` for a page."""
    key = F.col(key) if isinstance(key, str) else key
    own = split_host(pages.select("page_id", "url", key.alias("key_")), suffixes)
    # summed by key first: a page row meets one row, however often it or its label is repeated
    outcome = labelled.where("bad is not null and page_id is not null").groupBy(F.col("page_id").alias("lab_id")).agg(F.count("*").alias("n"), F.sum("bad").alias("k"))
    seen = own.select("key_", "host", "domain", "suffix").join(outcome, F.col("key_") == F.col("lab_id"), "left")
    rep = reputation(seen.select("host", "domain", "suffix", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("k", F.lit(0)).alias("k")), **options)
    rep = rep.select(F.col("host").alias("host_"), "n", "mean", (F.col("mean") - z * F.col("sd")).alias("bound"))
    return own.join(rep, F.col("host") == F.col("host_"), "left").select(
        "page_id", "url", "host", "domain", F.coalesce(F.col("n"), F.lit(0.0)).cast("bigint").alias("n"), F.round("mean", 6).alias("mean"), F.round("bound", 6).alias("bound"),
        F.coalesce(F.col("bound") <= cutoff, F.lit(True)).alias("kept"),
    )
