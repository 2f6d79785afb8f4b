"""Metadata records, their validation and rendering, translation and language votes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from catalogflow.functions.text import TOKEN_SPLIT

#: The fifteen core properties: name and whether an item must have it.
PROPERTIES = {p: p in ("title", "description") for p in ("contributor", "coverage", "creator", "date", "description", "format", "identifier", "language", "publisher", "relation", "rights", "source", "subject", "title", "type")}
EXTENDED = {"address": False, "local_url": False}
OLD, NEW = "element:", "term:"

VOTES = {
    "en": "the and of to is that it was for with", "de": "der die und von den das sich zu mit nicht",
    "fr": "et le des les du pour une est dans qui", "es": "el los del las se por con para es una",
}
LEXICON = {"de": "of", "la": "the", "que": "that", "el": "the", "en": "in", "y": "and", "los": "the", "del": "of", "las": "the", "por": "by", "con": "with", "para": "for", "una": "a", "su": "its", "al": "to"}


def to_metadata(items: DataFrame, mapping: list[tuple[str, list[str]]]) -> DataFrame:
    """(item_id, property, ordinal, value): each property's elements in order; empty ones are left out."""
    parts = [F.struct(F.lit(p).alias("property"), F.lit(i).alias("ordinal"), F.col(c).cast("string").alias("value")) for p, cols in mapping for i, c in enumerate(cols)]
    return items.select("item_id", F.inline(F.array(*parts))).where("value is not null and value <> ''")


TOOL = [("title", ["name"]), ("description", ["description"]), ("creator", ["producer_name", "producer_description", "producer_url", "producer_logo"]), ("local_url", ["url"])]
PRACTICE = [("title", ["name"]), ("description", ["description"]), ("address", ["location"]), ("local_url", ["url"])]


def pivot_metadata(triples: DataFrame, properties: list[str]) -> DataFrame:
    """One row per item; several values of a property are joined in order."""
    value = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", "value"))), lambda s: s["value"]), "; ")
    return triples.groupBy("item_id").pivot("property", properties).agg(value)


def upgrade_terms(triples: DataFrame) -> DataFrame:
    return triples.withColumn("property", F.regexp_replace("property", f"^{OLD}", NEW))


def downgrade_terms(triples: DataFrame) -> DataFrame:
    """Only the fifteen core properties have an older twin."""
    core = F.expr(f"substring(property, {len(NEW) + 1})").isin(*PROPERTIES)
    return triples.withColumn("property", F.when(core, F.regexp_replace("property", f"^{NEW}", OLD)).otherwise(F.col("property")))


def validate_metadata(triples: DataFrame, items: DataFrame) -> DataFrame:
    """(item_id, problem): unknown properties, and required ones that an item lacks. The property list is a constant."""
    known = {**PROPERTIES, **EXTENDED}
    unknown = triples.where(~F.col("property").isin(*known)).select("item_id", F.concat(F.lit("unknown "), "property").alias("problem")).distinct()
    must = items.select("item_id", F.explode(F.array(*[F.lit(p) for p, need in known.items() if need])).alias("property"))
    lacking = must.join(triples, ["item_id", "property"], "left_anti").select("item_id", F.concat(F.lit("missing "), "property").alias("problem"))
    return unknown.union(lacking)


def escape(c: str | Column) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    for a, b in (("&", "&amp;"), ("<", "&lt;"), (">", "&gt;"), ('"', "&quot;")):
        c = F.replace(c, F.lit(a), F.lit(b))
    return c


def render_html(items: DataFrame) -> DataFrame:
    return items.select("item_id", F.concat(F.lit("<article><h1>"), escape("name"), F.lit("</h1><p>"), escape("description"), F.lit("</p></article>")).alias("html"))


def translate_text(items: DataFrame, lexicon: dict[str, str], src: str = "es") -> DataFrame:
    """Adds translated and replaced (words changed); other languages pass through. The lexicon is a literal."""
    pick = F.create_map(*[F.lit(x) for kv in lexicon.items() for x in kv])
    parts = F.split("text", " ")
    new = F.array_join(F.transform(parts, lambda t: F.coalesce(F.try_element_at(pick, t), t)), " ")
    hits = F.size(F.filter(parts, lambda t: t.isin(*lexicon)))
    own = F.col("lang") == src
    return items.withColumn("translated", F.when(own, new).otherwise(F.col("text"))).withColumn("replaced", F.when(own, hits).otherwise(0))


def language_votes(docs: DataFrame, more: tuple[str, ...] | None = None) -> DataFrame:
    """Adds v_<lang> (tokens among ten frequent words each), pred (ties: alphabetical; none without votes).

    Tokens pass once, against one set of all words; what is left is counted. With ``more`` words the list left is kept, as tok_.
    """
    every = sorted({w for ws in VOTES.values() for w in ws.split()} | set(more or ()))
    out = docs.withColumn("tok_", F.filter(F.split(F.lower("text"), TOKEN_SPLIT), lambda t: t.isin(*every)))
    for lang, words in VOTES.items():
        own = words.split()
        out = out.withColumn(f"v_{lang}", F.size(F.filter("tok_", lambda t: t.isin(*own))))
    order = sorted(VOTES)
    most = F.greatest(*[F.col(f"v_{x}") for x in order])
    pred = F.when(most == 0, F.lit(None).cast("string"))
    for x in order:
        pred = pred.when(F.col(f"v_{x}") == most, F.lit(x))
    out = out.withColumn("pred", pred).withColumn("votes", most)
    return out if more else out.drop("tok_")
