"""Duplicate removal between catalogues: names, type blocking with fallback, judging, composites, groups, near copies of text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.functions.text import TOKEN_SPLIT, normalize_name, shingles, tokens
from catalogflow.operators.extract import text_elements, with_catalog
from catalogflow.operators.graph import connected_groups
from catalogflow.session import broadcast_small, staged

#: (concept, catalogue, type); LARGE is associated nowhere, concept 3 lacks catalogue 1.
ASSOCIATIONS = [
    (1, 0, "ECONOMY"), (1, 0, "PROMO"), (1, 1, "ECONOMY"), (1, 2, "PROMO"), (1, 3, "PROMO"), (2, 0, "STANDARD"), (2, 1, "STANDARD"),
    (2, 2, "STANDARD"), (2, 3, "MEDIUM"), (3, 0, "SMALL"), (3, 2, "SMALL"), (3, 3, "SMALL"),
]


def items_of(part: DataFrame) -> DataFrame:
    """(id, catalog_id, name, producer, type) from the part table."""
    return part.select(F.col("p_partkey").alias("id"), F.expr("cast(p_partkey % 4 as int)").alias("catalog_id"), normalize_name("p_name").alias("name"), F.col("p_brand").alias("producer"), F.col("p_type").alias("type"))


def associations(spark, rows=None) -> DataFrame:
    return spark.createDataFrame(rows or ASSOCIATIONS, "concept int, catalog_id int, type string")


def match_by_name(items: DataFrame, on=("name", "producer")) -> DataFrame:
    """Pairs (a, b), a < b, of two catalogues that agree on ``on``. Shuffles on the key only."""
    key = list(on)
    a, b = items.select(F.col("id").alias("a"), F.col("catalog_id").alias("cat_a"), *key), items.select(F.col("id").alias("b"), F.col("catalog_id").alias("cat_b"), *key)
    return a.join(b, key).where("a < b and cat_a <> cat_b").select("a", "b", "cat_a", "cat_b")


def name_links(items: DataFrame, on=("name", "producer")) -> DataFrame:
    """(a, b): the smallest id of each key that items of two catalogues have, with each other id of the key.

    Links the same items as the pairs of ``match_by_name``, as any two items of a key are linked there directly or by one of
    another catalogue; a row per item instead of one per pair.
    """
    key = list(on)
    rows = items.where("id is not null and catalog_id is not null").select("id", "catalog_id", *key)
    first = rows.groupBy(*key).agg(F.min("id").alias("a"), F.min("catalog_id").alias("lo"), F.max("catalog_id").alias("hi")).where("lo <> hi").drop("lo", "hi")
    return rows.join(first, key).where("id <> a").select("a", F.col("id").alias("b")).distinct()


def pairs_across(items: DataFrame, on=("name", "producer")) -> DataFrame:
    """(on, pairs) of each key that items of two catalogues have: how many pairs ``match_by_name`` has for it, from the number of ids by catalogue, no pairs made."""
    key = list(on)
    ids = items.dropna(subset=["id", "catalog_id", *key]).groupBy(*key, "id").agg(F.min("catalog_id").alias("lo"), F.max("catalog_id").alias("hi"))
    per = ids.groupBy(*key, F.when(F.col("lo") == F.col("hi"), F.col("lo")).alias("only")).agg(F.count("*").alias("n"))
    own = F.sum(F.when(F.col("only").isNotNull(), F.col("n") * (F.col("n") - 1))).alias("own")
    return per.groupBy(*key).agg(F.sum("n").alias("n"), own).select(*key, F.expr("(n * (n - 1) - coalesce(own, 0)) div 2").alias("pairs")).where("pairs > 0")


def type_pairs(assoc: DataFrame, types: DataFrame) -> DataFrame:
    """(cat_a, type_a, cat_b, type_b, rule): which types of another catalogue an item is compared with.

    types: (catalog_id, type) that occur. Associated types first; a type without counterpart in the other catalogue falls back to
    those types there that aren't associated with this catalogue. Dimension tables of a few rows.
    """
    a = assoc.select("concept", F.col("catalog_id").alias("cat_a"), F.col("type").alias("type_a"))
    b = assoc.select("concept", F.col("catalog_id").alias("cat_b"), F.col("type").alias("type_b"))
    direct = a.join(b, "concept").where("cat_a <> cat_b").select("cat_a", "type_a", "cat_b", "type_b").distinct()
    ta = types.select(F.col("catalog_id").alias("cat_a"), F.col("type").alias("type_a"))
    tb = types.select(F.col("catalog_id").alias("cat_b"), F.col("type").alias("type_b"))
    lone = ta.crossJoin(tb.select("cat_b").distinct()).where("cat_a <> cat_b").join(direct, ["cat_a", "type_a", "cat_b"], "left_anti")
    free = tb.crossJoin(ta.select("cat_a").distinct()).where("cat_a <> cat_b").join(direct, ["cat_b", "type_b", "cat_a"], "left_anti")
    fallback = lone.join(free, ["cat_a", "cat_b"]).select("cat_a", "type_a", "cat_b", "type_b")
    return direct.withColumn("rule", F.lit("associated")).union(fallback.withColumn("rule", F.lit("unassociated")))


def undirected(pairs: DataFrame) -> DataFrame:
    """Each unordered pair of (catalogue, type) once; 'associated' wins."""
    flip = F.col("cat_a") > F.col("cat_b")
    pick = lambda x, y: F.when(flip, F.col(y)).otherwise(F.col(x))
    out = pairs.select(pick("cat_a", "cat_b").alias("cat_a"), pick("type_a", "type_b").alias("type_a"), pick("cat_b", "cat_a").alias("cat_b"), pick("type_b", "type_a").alias("type_b"), "rule")
    return out.groupBy("cat_a", "type_a", "cat_b", "type_b").agg(F.min("rule").alias("rule"))


def candidates(items: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, cat_a, cat_b, rule): items of the two sides of each pair of types, cat_a < cat_b.

    The bridge is broadcast: it has one row per pair of catalogue types, never per item.
    """
    a = items.select(F.col("id").alias("a"), F.col("catalog_id").alias("cat_a"), F.col("type").alias("type_a"), F.col("name").alias("name_a"), F.col("producer").alias("producer_a"))
    b = items.select(F.col("id").alias("b"), F.col("catalog_id").alias("cat_b"), F.col("type").alias("type_b"), F.col("name").alias("name_b"), F.col("producer").alias("producer_b"))
    return a.join(F.broadcast(pairs), ["cat_a", "type_a"]).join(b, ["cat_b", "type_b"])


def candidate_counts(items: DataFrame, pairs: DataFrame) -> DataFrame:
    """(cat_a, cat_b, rule, n) from block sizes, without making the pairs."""
    size = items.groupBy("catalog_id", "type").agg(F.count("*").alias("n"))
    a = size.select(F.col("catalog_id").alias("cat_a"), F.col("type").alias("type_a"), F.col("n").alias("na"))
    b = size.select(F.col("catalog_id").alias("cat_b"), F.col("type").alias("type_b"), F.col("n").alias("nb"))
    return pairs.join(a, ["cat_a", "type_a"]).join(b, ["cat_b", "type_b"]).groupBy("cat_a", "cat_b", "rule").agg(F.sum(F.col("na") * F.col("nb")).alias("candidates"))


def candidate_sums(items: DataFrame, pairs: DataFrame) -> DataFrame:
    """(cat_a, cat_b, n, id_sum): number of candidates and sum of their ids, from the sizes and sums of blocks, without making the pairs."""
    size = items.groupBy("catalog_id", "type").agg(F.count("*").alias("n"), F.count("id").alias("k"), F.sum(F.col("id").cast("decimal(20,0)")).alias("t"))
    side = lambda s: size.select(F.col("catalog_id").alias(f"cat_{s}"), F.col("type").alias(f"type_{s}"), *[F.col(c).alias(f"{c}{s}") for c in "nkt"])
    both = F.col("ta") * F.col("kb").cast("decimal(15,0)") + F.col("tb") * F.col("ka").cast("decimal(15,0)")
    return pairs.join(side("a"), ["cat_a", "type_a"]).join(side("b"), ["cat_b", "type_b"]).groupBy("cat_a", "cat_b").agg(F.sum(F.col("na") * F.col("nb")).alias("n"), F.sum(both).cast("bigint").alias("id_sum"))


def blocking_stats(items: DataFrame, pairs: DataFrame) -> DataFrame:
    """(cat_a, cat_b, candidates, all_pairs, reduction)."""
    n = items.groupBy("catalog_id").agg(F.count("*").alias("n"))
    every = n.select(F.col("catalog_id").alias("cat_a"), F.col("n").alias("na")).crossJoin(n.select(F.col("catalog_id").alias("cat_b"), F.col("n").alias("nb"))).where("cat_a < cat_b")
    own = candidate_counts(items, pairs).groupBy("cat_a", "cat_b").agg(F.sum("candidates").alias("candidates"))
    full = every.join(own, ["cat_a", "cat_b"], "left").select("cat_a", "cat_b", F.coalesce("candidates", F.lit(0)).alias("candidates"), (F.col("na") * F.col("nb")).alias("all_pairs"))
    return full.withColumn("reduction", F.round(1 - F.col("candidates") / F.col("all_pairs"), 6))


def token_overlap(a: Column, b: Column) -> tuple[Column, Column]:
    """(Jaccard, containment in the other) of two token lists."""
    both = F.size(F.array_intersect(a, b)).cast("double")
    return both / F.size(F.array_union(a, b)), both / F.least(F.size(F.array_distinct(a)), F.size(F.array_distinct(b)))


def judge_named(candidates: DataFrame, same: float = 0.7) -> DataFrame:
    """Adds score and verdict from names and producers; stands where a language model would judge descriptions."""
    words = lambda n, p: F.concat(F.split(n, " "), F.array(F.lower(p)))
    score, _ = token_overlap(words("name_a", "producer_a"), words("name_b", "producer_b"))
    return candidates.withColumn("score", F.round(score, 6)).withColumn("verdict", F.when(F.col("score") >= same, "same").otherwise("different"))


def judge_pairs(pairs: DataFrame, judge) -> DataFrame:
    """(a, b, verdict, score, reason) by a judge given as a function of Arrow batches (an endpoint's client lives per partition)."""
    return pairs.mapInArrow(judge, "a bigint, b bigint, verdict string, score double, reason string")


def similar_names(names: DataFrame, same: float) -> DataFrame:
    """(k_a, k_b, score), both ways, of different rows of ``names`` (k, name, producer) that ``judge_named`` calls 'same'; same > 0.

    Words are ordered from rare to common; two sets that reach the threshold share one among the first n - ceil(t n) + 1, so only
    those are joined.
    """
    # 0.0000005 below is rounded up to the threshold
    head = f"slice(w, 1, size(w) - cast(ceil({same - 0.000001:.9f} * size(w)) as int) + 1)"
    words = names.where("name is not null").select("k", F.explode(F.array_distinct(F.array_compact(F.concat(F.split("name", " "), F.array(F.lower("producer")))))).alias("w"))
    often = words.groupBy("w").agg(F.count("*").alias("df"))
    lists = words.join(often, "w").groupBy("k").agg(F.array_sort(F.collect_list(F.struct("df", "w"))).alias("x")).select("k", F.col("x.w").alias("w"))
    lists = staged(lists.join(names, "k"), "name-words", tidy=True)
    heads = lists.select("k", F.expr(f"explode({head}) s"))
    near = heads.select(F.col("k").alias("k_a"), "s").join(heads.select(F.col("k").alias("k_b"), "s"), "s").where("k_a < k_b").select("k_a", "k_b").distinct()
    side = lambda x: lists.select(*[F.col(c).alias(f"{c}_{x}") for c in ("k", "w", "name", "producer")])
    score = F.round(token_overlap(F.col("w_a"), F.col("w_b"))[0], 6).alias("score")
    kept = near.join(side("a"), "k_a").join(side("b"), "k_b").where("not (name_a = name_b and producer_a = producer_b)").select("k_a", "k_b", score).where(F.col("score") >= same)
    kept = staged(kept, "similar-names", tidy=True)
    return kept.union(kept.select(F.col("k_b"), F.col("k_a"), "score"))


def judged_by_blocks(items: DataFrame, pairs: DataFrame, same: float = 0.4, chunk: int = 1024) -> DataFrame:
    """(a, b, score): residual pairs judged 'same', found from distinct names and producers.

    The verdict depends on names and producers alone, so each two of them are judged once, whatever their catalogues and types, and
    then expanded: ids that share catalogue, type, name and producer travel in lists of at most ``chunk``. Pairs that agree on name and
    producer were matched before and are left out.
    """
    distinct = staged(items.select("name", "producer").distinct(), "names", tidy=True)
    names = staged(distinct.withColumn("k", F.monotonically_increasing_id()), "numbered-names")
    known = names.select("k", F.col("name").alias("n"), F.col("producer").alias("p"))
    slim = items.join(broadcast_small(known), F.col("name").eqNullSafe(F.col("n")) & F.col("producer").eqNullSafe(F.col("p"))).select("id", "catalog_id", "type", "k")
    nth = F.row_number().over(Window.partitionBy("catalog_id", "type", "k").orderBy("id"))
    cells = slim.withColumn("part", F.floor((nth - 1) / chunk)).groupBy("catalog_id", "type", "k", "part").agg(F.collect_list("id").alias("ids"))
    cells = staged(cells, "name-cells", tidy=True)
    side = lambda x: cells.select(*[F.col(c).alias(f"{n}_{x}") for c, n in (("catalog_id", "cat"), ("type", "type"), ("k", "k"), ("ids", "ids"))])
    met = side("a").join(F.broadcast(pairs), ["cat_a", "type_a"]).join(similar_names(names, same), "k_a").join(side("b"), ["cat_b", "type_b", "k_b"])
    return met.withColumn("a", F.explode("ids_a")).withColumn("b", F.explode("ids_b")).select("a", "b", "cat_a", "cat_b", "rule", "score")


def later_items(pairs: DataFrame) -> DataFrame:
    """Ids that go when of each pair the earlier item stays."""
    return pairs.select(F.greatest("a", "b").alias("id")).distinct()


def find_duplicates(items: DataFrame, assoc: DataFrame, same: float = 0.4) -> DataFrame:
    """(a, b, stage): names first; items they leave over go through type blocks to the judge."""
    named = match_by_name(items).select("a", "b").withColumn("stage", F.lit("name"))
    rest = items.join(named.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "id", "left_anti")
    pairs = undirected(type_pairs(assoc, items.select("catalog_id", "type").distinct()))
    judged = judged_by_blocks(rest, pairs, same).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).withColumn("stage", F.lit("judge"))
    return named.union(judged)


def remove_duplicates(items: DataFrame, duplicates: DataFrame) -> DataFrame:
    return items.join(later_items(duplicates), "id", "left_anti")


def dedup_report(duplicates: DataFrame) -> DataFrame:
    return duplicates.groupBy("stage").agg(F.count("*").alias("pairs"), F.countDistinct(F.greatest("a", "b")).alias("items_removed"))


def exact_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, first_id, copies): first_id is the smallest id with this text. The shuffle carries digests, not texts."""
    w = Window.partitionBy("digest")
    return docs.select("doc_id", F.md5("text").alias("digest")).select("doc_id", F.min("doc_id").over(w).alias("first_id"), F.count("*").over(w).alias("copies"))


def shingle_rows(docs: DataFrame, k: int = 5) -> DataFrame:
    """(doc_id, n, s): hashed distinct shingles of each document and their number."""
    return docs.select("doc_id", shingles(tokens(), k).alias("sh")).select("doc_id", F.size("sh").alias("n"), F.explode("sh").alias("s"))


def shared_shingles(docs: DataFrame, k: int = 5, keep: list[str] = ()) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n, sh): of one document for each text, the hashed shingles that other texts have too, from rare to common; (rep, doc_id): who has its text.

    n counts all its shingles. Those of one text only, most of them, end in the first shuffle: nothing can be common there, so what
    follows is exact without them. Copies of a text cost one row each, whatever their number; ``keep``: more columns of these rows.
    """
    long_enough = F.lower("text").rlike(f"([a-zà-ÿß]+{TOKEN_SPLIT}){{{k - 1}}}[a-zà-ÿß]")
    keyed = docs.where(long_enough).select("doc_id", *keep, F.md5("text").alias("digest"))
    first = keyed.groupBy("digest").agg(F.min("doc_id").alias("rep"))
    copies = staged(keyed.join(first, "digest").select("rep", "doc_id", *keep), "copies", tidy=True)
    one = docs.join(broadcast_small(copies.where("rep <> doc_id").select("doc_id")), "doc_id", "left_anti")
    # explode_outer: for explode, a filter on the array is put before it, which would make the shingles twice
    rows = one.select("doc_id", shingles(tokens(), k).alias("sh")).select("doc_id", F.size("sh").alias("n"), "sh").select("doc_id", "n", F.explode_outer("sh").alias("s")).where("s is not null")
    df = F.count("*").over(Window.partitionBy("s"))
    shared = rows.withColumn("df", df).where("df > 1").repartition("doc_id")  # lists that are put together before the shuffle take more bytes
    ranked = shared.groupBy("doc_id", "n").agg(F.transform(F.array_sort(F.collect_list(F.struct("df", "s"))), lambda x: x["s"]).alias("sh"))
    return staged(ranked, "ranked", tidy=True), copies


def _heads(ranked: DataFrame, threshold: float, x: str) -> DataFrame:
    """(x, nx, rx, s): the shared ones among a text's first n - ceil(t n) + 1 shingles, and how many shared ones there are from each on."""
    length = F.col("n") - F.ceil(F.col("n") * threshold).cast("int") + 1 - (F.col("n") - F.size("sh"))
    heads = ranked.where(length > 0).select("doc_id", "n", F.size("sh").alias("m"), F.posexplode(F.slice("sh", F.lit(1), length)).alias("i", "s"))
    return heads.select(F.col("doc_id").alias(x), F.col("n").alias(f"n{x}"), (F.col("m") - F.col("i")).alias(f"r{x}"), "s")


def _common(pairs: DataFrame, ranked: DataFrame) -> DataFrame:
    """Adds na, nb and both, the number of common shingles, to (a, b)."""
    side = lambda x: ranked.select(F.col("doc_id").alias(x), F.col("n").alias(f"n{x}"), F.col("sh").alias(f"s{x}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").withColumn("both", F.size(F.array_intersect("sa", "sb"))).select("a", "b", "na", "nb", "both")


def near_classes(ranked: DataFrame, threshold: float) -> DataFrame:
    """(a, b, jaccard), a < b, of different texts: exact, by prefix filtering.

    Shingles are ordered from rare to common; two sets that reach the threshold share one among the first n - ceil(t n) + 1, so only
    those are joined, with the number of shared ones behind and the set's size: what can still be common behind both places must
    suffice. Candidates are verified on the lists of shared shingles.
    """
    # nothing before the first shingle in common is common, so there the rest bounds the overlap; a pair that fails at a later one was kept there
    fit = f"a < b and least(na, nb) >= {threshold} * greatest(na, nb) and least(ra, rb) >= ceil({threshold / (1 + threshold):.12f} * (na + nb) - 0.000001)"
    near = _heads(ranked, threshold, "a").join(_heads(ranked, threshold, "b"), "s").where(fit).select("a", "b").distinct()
    return _common(near, ranked).withColumn("jaccard", F.round(F.col("both") / (F.col("na") + F.col("nb") - F.col("both")), 6)).where(F.col("jaccard") >= threshold).select("a", "b", "jaccard")


def held_classes(ranked: DataFrame, least: float) -> DataFrame:
    """(a, b, share) of different texts: that share of a's shingles lies in b, which has as many or more. Prefix filter as above, with a's list alone deciding how long its prefix is."""
    rest = ranked.select(F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.size("sh").alias("m"), F.posexplode("sh").alias("i", "s")).withColumn("rb", F.col("m") - F.col("i"))
    fit = f"a <> b and nb >= na and least(ra, rb) >= ceil({least} * na - 0.000001)"
    near = _heads(ranked, least, "a").join(rest, "s").where(fit).select("a", "b").distinct()
    return _common(near, ranked).withColumn("share", F.round(F.col("both") / F.col("na"), 6)).where(F.col("share") >= least).select("a", "b", "share")


def _copied(copies: DataFrame) -> DataFrame:
    """(a, b, 1.0) with a = b for each text that several documents have."""
    return copies.where("rep <> doc_id").select(F.col("rep").alias("a"), F.col("rep").alias("b"), F.lit(1.0)).distinct()


def _expanded(classes: DataFrame, copies: DataFrame, keep: list[str] = ()) -> DataFrame:
    """(x, y) and what ``classes`` has for all documents with the texts a and b, with ``keep`` of x and y as ``keep``_x and ``keep``_y."""
    side = lambda c, x: copies.select(F.col("rep").alias(c), F.col("doc_id").alias(x), *[F.col(k).alias(f"{k}_{x}") for k in keep])
    return classes.join(side("a", "x"), "a").join(side("b", "y"), "b")


def near_text_pairs(docs: DataFrame, threshold: float = 0.7, k: int = 5) -> DataFrame:
    """(a, b, jaccard) of all pairs whose shingle Jaccard reaches the threshold; copies of a text are compared once and put in at the end."""
    ranked, copies = shared_shingles(docs, k)
    x = _expanded(near_classes(ranked, threshold).union(_copied(copies)), copies)
    return x.where("a <> b or x < y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "jaccard")


def contained_pairs(docs: DataFrame, least: float = 0.8, k: int = 5) -> DataFrame:
    """(part, whole, share): documents of which that share of shingles lies in a larger one (equal sizes: both ways)."""
    ranked, copies = shared_shingles(docs, k)
    x = _expanded(held_classes(ranked, least).union(_copied(copies)), copies)
    return x.where("x <> y").select(F.col("x").alias("part"), F.col("y").alias("whole"), "share")


#: Languages stand for the types of text items; Spanish has no counterpart in catalogue 1 and falls back to what is free there.
TEXT_ASSOCIATIONS = [(c, k, t) for c, t in enumerate(("en", "de", "fr", "es"), 1) for k in range(5) if (t, k) != ("es", 1)]


def text_items(docs: DataFrame) -> DataFrame:
    """(doc_id, catalog_id, edition, name, type, text) of documents taken as items; their type is the language."""
    d = text_elements(with_catalog(docs))
    return d.select("doc_id", "catalog_id", "edition", normalize_name("name").alias("name"), F.col("lang").alias("type"), "text")


def judged_classes(items: DataFrame, same: float, within: float, keep: list[str]) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(a, b, jaccard), (a, b, share) and copies (rep, doc_id, ``keep``): different texts that are alike, a < b, and those of which b holds a without being alike."""
    ranked, copies = shared_shingles(items, keep=keep)
    near = staged(near_classes(ranked, same), "near-texts", tidy=True)
    both = near.select("a", "b").union(near.select("b", "a"))
    # texts that are alike are left out before copies are put in
    return near, staged(held_classes(ranked, within).join(both, ["a", "b"], "left_anti"), "held-texts", tidy=True), copies


def judge_descriptions(items: DataFrame, same: float = 0.7, within: float = 0.8) -> DataFrame:
    """(a, b, verdict, score, reason) of items of two catalogues, a < b or part a and whole b; pairs not given are 'different'.

    'same': as much of both texts is common; 'composite': b bundles a and at least one more item of other catalogues, of which it
    holds that share each. Exact for all pairs, by prefix filters, so that blocks of types only have to drop pairs.
    """
    near, held, copies = judged_classes(items, same, within, ["catalog_id"])
    across = lambda p, where: _expanded(p, copies, ["catalog_id"]).where("catalog_id_x <> catalog_id_y").where(where)
    alike = across(near.union(_copied(copies)), "a <> b or x < y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "jaccard")
    held = across(held, "true").select(F.col("x").alias("a"), F.col("y").alias("b"), F.col("share").alias("score"))
    held = staged(held, "judged-held", tidy=True)
    whole = held.groupBy("b").agg(F.count("*").alias("parts")).where("parts >= 2")
    percent = lambda c: F.floor(F.col(c) * 100).cast("string")
    first = alike.select("a", "b", F.lit("same").alias("verdict"), F.col("jaccard").alias("score"), F.concat(percent("jaccard"), F.lit(" % of the words of both are common")).alias("reason"))
    return first.union(held.join(whole, "b").select("a", "b", F.lit("composite"), "score", F.concat(F.lit("one of "), F.col("parts").cast("string"), F.lit(" items held, to "), percent("score"), F.lit(" %"))))


def text_cascade(items: DataFrame, assoc: DataFrame, fallback: bool = True, composites: bool = True, judged: DataFrame | None = None, links: bool = False) -> DataFrame:
    """(a, b, stage): pairs of items of two catalogues by name and type; then what the judge says of pairs that blocks of types allow.

    Items matched by name don't go on. Of composites b is the whole. All of them are found before anything is removed.
    links: of the pairs by name only as many as link the same items, which is all that ``removed_items`` needs.
    """
    named = items.select(F.col("doc_id").alias("id"), "catalog_id", "name", "type").where("name <> ''")
    named = (name_links if links else match_by_name)(named, on=("name", "type")).select("a", "b")
    named = staged(named, "text-named", tidy=True)
    out = named.withColumn("stage", F.lit("name"))
    known = named.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    rest = items.join(known, "doc_id", "left_anti").select("doc_id", "catalog_id", "type")
    bridge = type_pairs(assoc, items.select("catalog_id", "type").where("type is not null").distinct())
    bridge = (bridge if fallback else bridge.where("rule = 'associated'")).drop("rule").distinct()
    side = lambda x: rest.select(F.col("doc_id").alias(x), F.col("catalog_id").alias(f"cat_{x}"), F.col("type").alias(f"type_{x}"))
    judged = judge_descriptions(items) if judged is None else judged
    pairs = judged.join(side("a"), "a").join(side("b"), "b").join(bridge, ["cat_a", "type_a", "cat_b", "type_b"], "left_semi")
    # the parts that blocks leave to a whole are counted again
    whole = pairs.where("verdict = 'composite'").groupBy("b").agg(F.count("*").alias("parts")).where("parts >= 2").select("b")
    out = out.union(pairs.where("verdict = 'same'").select("a", "b", F.lit("same")))
    return out.union(pairs.where("verdict = 'composite'").join(whole, "b", "left_semi").select("a", "b", F.lit("composite"))) if composites else out


def baseline_quality(items: DataFrame, assoc: DataFrame, same: float = 0.7, within: float = 0.8) -> DataFrame:
    """(method, pairs, hits, precision, recall, f1) of the cascade and what it is compared with, against all that the judge says of all pairs.

    What ``text_cascade``, ``match_by_name`` and ``judge_descriptions`` list as pairs is counted: by keys, and for the judge by cells, the
    documents of one text that have catalogue and type in common. All pairs of two cells share their fate, as a name depends on the
    text only. Ids stand for one text and one catalogue each; rows may be repeated.
    """
    items = items.withColumn("named", F.when(F.col("name") != "", F.unhex(F.md5("name"))))
    near, held, copies = judged_classes(items, same, within, ["catalog_id", "type", "named"])  # takes most of the disk, so it goes first
    facts = staged(items.select(F.col("doc_id").alias("id"), "catalog_id", "type", "named", F.unhex(F.md5("text")).alias("digest")), "facts")
    by_name = staged(pairs_across(facts, ("named", "type")), "name-pairs", tidy=True)
    by_text = pairs_across(facts, ("digest",))

    # m: rows of each id, n: ids
    ids = copies.groupBy("rep", "doc_id", "catalog_id", "type", "named").agg(F.count("*").alias("m"))
    ids = ids.join(by_name.select("named", "type", F.lit(True).alias("known")), ["named", "type"], "left")
    cells = ids.groupBy("rep", F.col("catalog_id").alias("cat"), "type", "named", "known", "m").agg(F.count("*").alias("n"))
    cells = staged(cells.select("rep", F.struct("rep", "cat", "type", "named", "known", "m", "n").alias("cell")), "cells", tidy=True)
    rules = type_pairs(assoc, items.select("catalog_id", "type").where("type is not null").distinct())
    rules = rules.groupBy("cat_a", "type_a", "cat_b", "type_b").agg(F.bool_or(F.col("rule") == "associated").alias("rules"))

    def across(classes: DataFrame) -> DataFrame:
        """Cells x and y of the texts a and b; open: what blocks of types allow of them, direct: without fallback."""
        side = lambda c, x: cells.select(F.col("rep").alias(c), F.col("cell").alias(x))
        both = classes.join(side("a", "x"), "a").join(side("b", "y"), "b").where("x.cat <> y.cat").select("x", "y")
        met = both.join(F.broadcast(rules), F.expr("x.cat = cat_a and x.type = type_a and y.cat = cat_b and y.type = type_b"), "left")
        met = met.withColumn("open", F.expr("rules is not null and x.known is null and y.known is null"))
        return met.select("x", "y", "open", F.expr("open and rules").alias("direct"))

    alike = across(near.select("a", "b").union(_copied(copies).select("a", "b"))).where("x.rep <> y.rep or x.cat < y.cat").withColumn("same", F.lit(True))
    # a whole has as many parts as rows of the judge name it; those that blocks leave to it are counted again, over rows of both its ids and theirs
    of = Window.partitionBy("y")
    rows = F.expr("x.n * x.m * y.m")
    left = lambda c: F.sum(F.when(F.col(c), rows * F.expr("x.m * y.m"))).over(of)
    bundled = across(held.select("a", "b")).select("x", "y", F.sum(rows).over(of).alias("parts"), (F.col("open") & (left("open") >= 2)).alias("open"), (F.col("direct") & (left("direct") >= 2)).alias("direct")).where("parts >= 2")
    # texts of one size may hold each other: one pair
    bundled = bundled.groupBy(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).agg(F.coalesce(F.bool_or("open"), F.lit(False)).alias("open"), F.coalesce(F.bool_or("direct"), F.lit(False)).alias("direct"))
    met = alike.union(bundled.withColumn("same", F.lit(False))).withColumn("pairs", F.expr("x.n * y.n"))
    count = lambda where, name: F.coalesce(F.sum(F.when(F.expr(where), F.col("pairs"))), F.lit(0)).alias(name)
    found = met.agg(
        count("true", "all_true"), count("x.named = y.named and x.type = y.type", "named"), count("same", "same"), count("x.rep = y.rep", "exact"),
        count("direct", "direct"), count("same and open", "open_same"), count("open", "open"),
    )
    total = lambda df, name: df.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias(name))
    row = found.crossJoin(total(by_name, "all_named")).crossJoin(total(by_text, "all_exact"))
    # what the judge adds to the names is disjoint from them, as items with a name in common don't go on
    methods = {
        "names_only": ("all_named", "named"), "all_pairs": ("same", "same"), "no_fallback": ("all_named + direct", "named + direct"),
        "no_composites": ("all_named + open_same", "named + open_same"), "cascade": ("all_named + open", "named + open"), "exact_text": ("all_exact", "exact"),
    }
    per = row.select("all_true", F.inline(F.array(*[F.struct(F.lit(m).alias("method"), F.expr(p).alias("pairs"), F.expr(h).alias("hits")) for m, (p, h) in methods.items()])))
    return _rates(per.where("pairs > 0"))


def removed_items(items: DataFrame, found: DataFrame) -> DataFrame:
    """(doc_id, stage, kept_id): what goes. Of linked items that of the latest edition stays, then the smallest id; wholes go, their parts stay.

    stage: name, same or composite, the first that an item goes by; kept_id is null for composites.
    """
    found = staged(found, "text-found", tidy=True)
    groups = staged(connected_groups(found.where("stage <> 'composite'")), "text-groups")
    best = groups.join(items.select(F.col("doc_id").alias("id"), "edition"), "id").groupBy("group_id").agg(F.max_by("id", F.struct("edition", -F.col("id"))).alias("kept_id"))
    by = found.where("stage <> 'composite'").select(F.explode(F.array("a", "b")).alias("id"), "stage").groupBy("id").agg(F.min("stage").alias("stage"))
    same = groups.join(best, "group_id").where("id <> kept_id").join(by, "id").select(F.col("id").alias("doc_id"), "stage", "kept_id")
    whole = found.where("stage = 'composite'").select(F.col("b").alias("doc_id")).distinct().join(same, "doc_id", "left_anti")
    return same.union(whole.select("doc_id", F.lit("composite"), F.lit(None).cast("bigint")))


def resolve_composites(contained: DataFrame, least_parts: int = 2) -> DataFrame:
    """(whole, parts): items that hold two or more distinct smaller ones; they go, their parts stay."""
    return contained.groupBy("whole").agg(F.countDistinct("part").alias("parts")).where(F.col("parts") >= least_parts)


def _rates(per: DataFrame) -> DataFrame:
    """(method, pairs, hits, precision, recall, f1) from (method, pairs, hits, all_true). The recall of nothing is no number, as in SQL."""
    recall = F.round(F.when(F.col("all_true") > 0, F.col("hits") / F.col("all_true")).otherwise(float("nan")), 6).alias("recall")
    return per.select("method", "pairs", "hits", F.round(F.col("hits") / F.col("pairs"), 6).alias("precision"), recall, F.round(2 * F.col("hits") / (F.col("pairs") + F.col("all_true")), 6).alias("f1"))


def pair_quality(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row per method: (method, pairs, hits, precision, recall, f1); found: (method, a, b), truth: (a, b)."""
    all_true = truth.agg(F.count("*").alias("all_true"))
    hit = found.join(truth.withColumn("hit", F.lit(1)), ["a", "b"], "left")
    per = hit.groupBy("method").agg(F.count("*").alias("pairs"), F.count("hit").alias("hits")).crossJoin(F.broadcast(all_true))
    return _rates(per)
