"""Extraction: catalogues, elements of items and pages, contacts, regions, icons, candidates from pages."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from catalogflow.functions.text import CATALOG, normalize_name
from catalogflow.session import staged

PHONE = r"\+1 \([0-9]{3}\) [0-9]{3}-[0-9]{4}"
EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+"
ADDRESS = r"[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}"
LINK = r"https?://[A-Za-z0-9./?=&_%-]+"

#: (element, mode in family S, in family A, in family P); mode: X present, AI read by a model, blank not offered.
ELEMENTS = [
    ("name", "X", "X", ""), ("description", "X", "X", ""), ("producer_name", "X", "X", ""), ("producer_description", "X", "X", ""),
    ("producer_logo", "X", "X", ""), ("producer_url", "X", "X", ""), ("scope", "X", "", ""), ("destination_type", "AI", "X", ""),
    ("solution_type", "AI", "AI", ""), ("producer_contact", "", "X", ""), ("producer_address", "", "X", ""), ("code", "", "X", ""),
    ("initiative_title", "", "", "X"), ("initiative_location", "", "", "X"), ("initiative_description", "", "", "X"),
    ("initiative_url", "", "", "X"), ("initiative_images", "", "", "X"),
]


def family(catalog: str = "catalog_id") -> Column:
    return F.expr(f"case when {catalog} in (0, 1) then 'S' when {catalog} in (2, 3) then 'A' else 'P' end")


def with_catalog(docs: DataFrame) -> DataFrame:
    """Adds catalog_id, family, edition, kind from the source name."""
    return (
        docs.withColumn("catalog_id", F.expr(CATALOG)).withColumn("family", family())
        .withColumn("edition", F.expr("case when catalog_id = 4 then 1 else catalog_id % 2 + 1 end"))
        .withColumn("kind", F.expr("case when catalog_id = 4 then 'practice' else 'tool' end"))
    )


def catalogs(docs: DataFrame) -> DataFrame:
    return with_catalog(docs.select("source", "lang")).groupBy("catalog_id", "family", "edition", "kind").agg(
        F.count("*").alias("items"), F.countDistinct("lang").alias("langs"), F.countDistinct("source").alias("sources")
    )


def tool_items(docs: DataFrame) -> DataFrame:
    """Practice catalogues describe uses of tools and aren't labelled."""
    return with_catalog(docs).where("kind = 'tool'")


def text_elements(docs: DataFrame) -> DataFrame:
    """Adds name (first sentence) and description (the rest)."""
    first = F.regexp_extract("text", "^([^.\n]*)", 1)
    return docs.withColumn("name", F.trim(first)).withColumn("description", F.trim(F.expr("substring(text, length(regexp_extract(text, '^([^.\\n]*)', 1)) + 2)")))


def element_matrix(spark) -> DataFrame:
    rows = [(e, f, m) for e, *modes in ELEMENTS for f, m in zip("SAP", modes) if m]
    return spark.createDataFrame(rows, "element string, family string, mode string")


def audit_elements(docs: DataFrame) -> DataFrame:
    """(family, element, mode, filled, missing) of all elements that the family offers; filled and missing are null where text can't show them."""
    items = text_elements(with_catalog(docs))
    has = lambda pattern: F.col("text").rlike(pattern)
    shown = {
        "name": F.col("name") != "", "description": F.col("description") != "", "producer_contact": has(PHONE) | has(EMAIL), "producer_url": has(LINK),
        "initiative_title": F.col("name") != "", "initiative_description": F.col("description") != "", "initiative_url": has(LINK),
    }
    counts = items.groupBy("family").agg(F.count("*").alias("all"), *[F.count_if(c).alias(e) for e, c in shown.items()])
    long = counts.unpivot(["family", "all"], list(shown), "element", "filled")
    # both sides are of a few rows: elements by families
    return element_matrix(docs.sparkSession).join(long, ["element", "family"], "left").select("family", "element", "mode", "filled", (F.col("all") - F.col("filled")).alias("missing"))


def extract_page(pages: DataFrame) -> DataFrame:
    """(page_id, site, title, h1, body, n_links, n_paragraphs): scripts, styles, comments, advertisements and navigation go first."""
    unescape = lambda c: F.replace(F.replace(F.replace(c, F.lit("&lt;"), F.lit("<")), F.lit("&gt;"), F.lit(">")), F.lit("&amp;"), F.lit("&"))
    body = F.col("html")
    for pattern in ("<script[^>]*>[^<]*</script>", "<style[^>]*>[^<]*</style>", "<!--[^>]*-->", '<div class="ad">[^<]*</div>', "(?s)<nav>.*?</nav>", "(?s)<head>.*?</head>"):
        body = F.regexp_replace(body, pattern, " ")
    body = F.trim(F.regexp_replace(F.regexp_replace(body, "<[^>]*>", " "), "[ \n\t\r]+", " "))
    count = lambda s: F.expr(f"cast((length(html) - length(replace(html, '{s}', ''))) / {len(s)} as bigint)")
    return pages.select(
        "page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("site"), unescape(F.regexp_extract("html", "<title>([^<]*)</title>", 1)).alias("title"),
        unescape(F.regexp_extract("html", "<h1>([^<]*)</h1>", 1)).alias("h1"), unescape(body).alias("body"), count('href="').alias("n_links"), count("<p>").alias("n_paragraphs"),
    )


def page_links(pages: DataFrame) -> DataFrame:
    return pages.select("page_id", F.posexplode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("ord", "href"))


def extract_contacts(docs: DataFrame) -> DataFrame:
    """(doc_id, kind, ord, value); a substring test guards each expression."""
    def found(kind, guard, pattern):
        hits = F.when(F.contains("text", F.lit(guard)), F.expr(f"regexp_extract_all(text, r'{pattern}', 0)")).otherwise(F.array().cast("array<string>"))
        return F.transform(hits, lambda v: F.struct(F.lit(kind).alias("kind"), v.alias("value")))

    each = [found("phone", "+1 (", PHONE), found("email", "@", EMAIL), found("ip", ".", ADDRESS), found("url", "http", LINK)]
    exploded = [docs.select("doc_id", F.posexplode(e).alias("ord", "x")) for e in each]
    out = exploded[0]
    for e in exploded[1:]:
        out = out.union(e)
    return out.select("doc_id", "x.kind", "ord", "x.value")


def locate_by_prefix(contacts: DataFrame, nation: DataFrame, region: DataFrame) -> DataFrame:
    """Phones with their region; mobiles (prefix 5xx, 6xx) stay without. The dimension tables have fixed, few rows."""
    phones = contacts.where("kind = 'phone'").withColumn("prefix", F.expr("cast(substring(value, 5, 3) as int)"))
    phones = phones.withColumn("nationkey", F.expr("case when prefix div 100 in (5, 6) then null else prefix % 25 end"))
    where = nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return phones.join(F.broadcast(where), F.col("nationkey") == F.col("n_nationkey"), "left").select(
        "doc_id", "value", "prefix", F.col("n_name").alias("nation"), F.col("r_name").alias("region"), F.expr("nationkey * 5 - 60").alias("lat"),
        F.expr("nationkey * 14 - 180").alias("lon"), F.col("nationkey").isNotNull().alias("resolved"),
    )


def icon_variants(icons: DataFrame, levels=(4, 8, 16)) -> DataFrame:
    """Copies at several resolutions: values rounded to 1/level."""
    level = F.explode(F.array(*[F.lit(x) for x in levels])).alias("level")
    return icons.select("vec_id", "label", "embedding", level).withColumn("embedding", F.transform("embedding", lambda x: F.round(x.cast("double") * F.col("level")) / F.col("level")))


def augment(icons: DataFrame, factor: int = 3, seed: str = "s1") -> DataFrame:
    """``factor`` rows per icon: itself, mirrored, and jittered copies with noise from a hash."""
    copy = F.explode(F.sequence(F.lit(0), F.lit(factor - 1))).alias("copy")
    e = F.transform("embedding", lambda x: x.cast("double"))
    noise = F.transform(e, lambda x, i: x + (F.pmod(F.xxhash64(F.lit(seed), F.col("vec_id"), F.col("copy"), i), F.lit(1000)) - 500) / 100000.0)
    return icons.select("vec_id", "label", "embedding", copy).select("vec_id", "label", "copy", F.when(F.col("copy") == 0, e).when(F.col("copy") == 1, F.reverse(e)).otherwise(noise).alias("embedding"))


def classify_icons(icons: DataFrame, glossary: DataFrame, ids: list[str], limit: int = 500_000, skip_same: bool = False) -> DataFrame:
    """Nearest glossary icon by cosine: ``ids`` columns and (pred_id, pred_label, sim).

    The glossary's rows are counted: up to ``limit`` it is broadcast; a larger one is compared in shuffled blocks. Ties go to the smaller id.
    """
    as_double = F.transform("embedding", lambda x: x.cast("double"))
    g = glossary.select("vec_id", "label", as_double.alias("e"))
    rows = g.count()
    if rows > limit:
        return _classify_in_blocks(icons, g, rows, ids, skip_same)
    names, labels, base = _unit(g.orderBy("vec_id").toArrow())
    shared = icons.sparkSession.sparkContext.broadcast((names, labels, base))

    def run(batches):
        names, labels, x = shared.value
        step = max(1, min(1024, (1 << 22) // max(1, len(x))))  # scores of 32 MB at most
        for whole in batches:
            for i in range(0, whole.num_rows, step):
                part = whole.slice(i, step)
                v = np.array(part.column("embedding").to_pylist(), dtype=float).reshape(part.num_rows, -1)
                top, sim = _nearest(part.column("vec_id").to_numpy() if skip_same else None, v, names, x)
                yield pa.RecordBatch.from_arrays([*[part.column(c) for c in ids], pa.array(names[top], pa.int64()), pa.array(labels[top], pa.int32()), pa.array(sim)], [*ids, "pred_id", "pred_label", "sim"])

    cols = list(dict.fromkeys([*ids, "vec_id", "embedding"]))
    src = icons.withColumn("embedding", as_double).select(*cols)
    fields = ", ".join(f"{c} {src.schema[c].dataType.simpleString()}" for c in ids)
    return src.mapInArrow(run, f"{fields}, pred_id bigint, pred_label int, sim double")


def _unit(glossary: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, labels and vectors of length 1, by id."""
    names = glossary.column("vec_id").to_numpy()
    order = np.argsort(names, kind="stable")
    base = glossary.column("e").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(names), -1)[order]
    base /= np.maximum(np.linalg.norm(base, axis=1, keepdims=True), 1e-30)
    return names[order], glossary.column("label").to_numpy()[order], base


def _nearest(own: np.ndarray | None, v: np.ndarray, names: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Place and cosine of the nearest row of ``x`` for each row of ``v``; rows named like ``own`` come last."""
    s = np.round(v @ x.T / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-30), 9)
    if own is not None:
        s[own[:, None] == names[None, :]] = -2
    top = s.argmax(axis=1)
    return top, s[np.arange(len(top)), top]


def _classify_in_blocks(icons: DataFrame, glossary: DataFrame, rows: int, ids: list[str], skip_same: bool, block_rows: int = 32_768) -> DataFrame:
    """``classify_icons`` for a glossary of any size: each pair of an icon block and a glossary block is one task."""
    vector = F.transform("embedding", lambda x: x.cast("double"))
    src = staged(icons.withColumn("embedding", vector).withColumn("row_", F.monotonically_increasing_id()), "icons")
    count = src.count()
    # keys of both sides are of one type, or equal keys would be hashed to different partitions
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(max(1, -(-n // block_rows)) - 1).cast("bigint")))
    own = lambda c, n: F.pmod(F.xxhash64(c), F.lit(max(1, -(-n // block_rows))).cast("bigint"))
    left = src.select(own("row_", count).alias("qb"), every(rows).alias("gb"), "row_", "vec_id", "embedding")
    right = glossary.select(own("vec_id", rows).alias("gb"), every(count).alias("qb"), "vec_id", "label", "e")

    def compare(a: pa.Table, b: pa.Table) -> pa.Table:
        out = []
        if a.num_rows and b.num_rows:
            names, labels, x = _unit(b)
            step = max(1, (1 << 22) // len(x))
            for i in range(0, a.num_rows, step):
                part = a.slice(i, step).combine_chunks()
                v = part.column("embedding").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1)
                top, sim = _nearest(part.column("vec_id").to_numpy() if skip_same else None, v, names, x)
                out.append((part.column("row_").to_numpy(), names[top], labels[top], sim))
        cols = [np.concatenate(c) for c in zip(*out)] if out else [[], [], [], []]
        return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.float64()))], ["row_", "pred_id", "pred_label", "sim"])

    hits = left.groupBy("qb", "gb").cogroup(right.groupBy("qb", "gb")).applyInArrow(compare, "row_ bigint, pred_id bigint, pred_label int, sim double")
    best = hits.groupBy("row_").agg(F.max_by(F.struct("pred_id", "pred_label", "sim"), F.struct("sim", -F.col("pred_id"))).alias("x"))
    return src.select("row_", *ids).join(best, "row_").select(*ids, "x.*")


def icon_centroids(icons: DataFrame) -> DataFrame:
    each = icons.select("label", F.posexplode(F.transform("embedding", lambda x: x.cast("double"))).alias("i", "x"))
    mean = each.groupBy("label", "i").agg(F.avg("x").alias("x"))
    return mean.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("embedding"))


def label_elements(items: DataFrame, preds: DataFrame, glossary: DataFrame) -> DataFrame:
    """Items with the label that their catalogue's glossary gives to the recognised icon."""
    return items.join(preds, "item_id").join(F.broadcast(glossary), ["catalog_id", "pred_label"], "left")


def unify_destination(items: DataFrame) -> DataFrame:
    """One list of destination labels, from text (family A) or from icons (family S)."""
    some = lambda c: F.coalesce(F.col(c), F.array().cast("array<string>"))
    return items.withColumn("destination", F.array_sort(F.array_union(some("destination_text"), some("destination_icon"))))


def discover_candidates(pages: DataFrame, docs: DataFrame) -> DataFrame:
    """(page_id, title, sound) of pages whose title isn't a known item's name; sound: a title of 3 words and 2 paragraphs at least."""
    known = text_elements(docs).select(normalize_name("name").alias("known")).where("known <> ''").distinct()
    p = extract_page(pages).withColumn("key", normalize_name("title"))
    sound = F.expr("size(split(key, ' ')) >= 3 and n_paragraphs >= 2")
    return p.join(known, p["key"] == known["known"], "left_anti").select("page_id", "title", sound.alias("sound"))


def apply_validation(candidates: DataFrame, decisions: DataFrame) -> DataFrame:
    """Candidates with a person's decision; undecided ones stay open."""
    return candidates.join(decisions.select("page_id", "accepted"), "page_id", "left").withColumn("state", F.expr("case when accepted is null then 'open' when accepted then 'accepted' else 'refused' end"))


def decode_codes(files: DataFrame, decoder=None) -> DataFrame:
    """(path, payload) from rows (path, content) by a decoder of images, given by the user; the default finds links in bytes."""
    def run(batches):
        import re

        read = decoder or (lambda b: [m.decode() for m in re.findall(rb"https?://[\w./?=&%-]+", b)])
        for batch in batches:
            pairs = [(p, x) for p, c in zip(batch.column("path").to_pylist(), batch.column("content").to_pylist()) for x in read(c or b"")]
            yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in pairs], pa.string()), pa.array([x for _, x in pairs], pa.string())], ["path", "payload"])

    return files.select("path", "content").mapInArrow(run, "path string, payload string")


def run_extraction(docs: DataFrame, nation: DataFrame, region: DataFrame) -> DataFrame:
    """One row per item: catalogue, name, description, contacts by kind and the region that a landline's prefix tells.

    Texts stay in the map side; only contacts are grouped.
    """
    contacts = extract_contacts(docs)
    kinds = contacts.groupBy("doc_id").pivot("kind", ["email", "ip", "phone", "url"]).agg(F.array_sort(F.collect_set("value")))
    where = locate_by_prefix(contacts, nation, region).where("resolved").groupBy("doc_id").agg(F.min("region").alias("region"))
    items = text_elements(with_catalog(docs)).select("doc_id", "catalog_id", "kind", "name", "description", "lang")
    return items.join(kinds, "doc_id", "left").join(where, "doc_id", "left")
