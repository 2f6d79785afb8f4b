"""Operator 7: near-duplicate documents by ProbMinHash, banding and exact verification.

Shingles are runs of ``k`` words, weighted by how often they occur. Each is a Poisson process whose rate is its
weight: arrivals fall on random registers, a register keeps the shingle that arrives first, and a shingle stops as
soon as its next arrival is later than all registers' (nothing later can matter). The share of equal registers
estimates probability Jaccard. ``bands`` bands of ``rows`` registers make buckets.

Pairs: exact copies are collapsed first by a digest of the text, so that a group of any size costs one member. Within a
bucket each member is compared with the bucket's smallest id; those that fail are compared with all other members of the
bucket, whether these failed or passed, but for pairs that the first comparisons of any bucket have already put in one group.
So no partner is capped: each pair of a bucket is in one group, or verified by exact probability Jaccard on the texts, or its registers
differ in more than a pair at the threshold would but for 3.5 standard deviations (about 1 in 3,000 of such pairs, and ever fewer above
it), which is told from four bits of each register before any text is moved. Groups are the connected components of the verified pairs.

Defined cases: null or empty texts, or texts without letters and digits, resemble nothing but are copies of the same
text (null apart from empty); shorter texts than ``k`` words are one shingle. Rows without ``doc_id`` stay alone
(group_id null, kept). Rows that repeat a doc_id are one document: one row of result, and one kept row in
``drop_near_duplicates``; where their texts differ, the text with the smallest digest (a null text last) stands for the document in
all steps. Extra columns aren't read, whatever their names. Ties go to the smallest doc_id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.llm import text as tx
from catalogflow.llm.order import free_name
from catalogflow.operators.graph import connected_groups
from catalogflow.session import staged

U64 = np.uint64
DIGEST = "coalesce(md5(text), 'null')"


def weighted(texts: pa.Array, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, shingle, count), sorted by document and shingle; shingles are cut to 44 bits."""
    doc, code, _, _, _ = tx.words(texts)
    n = len(texts)
    d, s = tx.shingles(doc, code, n, k)
    if n > 1 << 20:
        raise ValueError("at most 2**20 texts at once")
    key, count = np.unique((d.astype(U64) << U64(44)) | (s >> U64(20)), return_counts=True)
    return (key >> U64(44)).astype(np.int64), key & U64((1 << 44) - 1), count


def signatures(doc: np.ndarray, item: np.ndarray, weight: np.ndarray, n_docs: int, m: int) -> np.ndarray:
    """n_docs x m registers, each the item that arrived there first (0 for documents without items)."""
    first = np.full(n_docs * m, np.inf)
    who = np.zeros(n_docs * m, U64)
    rate = 1.0 / weight
    seed = tx.mix(item + U64(0x9E3779B97F4A7C15))
    time = np.zeros(len(item))
    step = 0
    while len(doc):
        step += 1
        draw = tx.mix(seed ^ U64((step * 0xD1342543DE82EF95) % (1 << 64)))
        time = time - np.log(((draw >> U64(11)) + U64(1)) * 2.0**-53) * rate
        slot = doc * m + ((tx.mix(draw + U64(0x632BE59BD9B4E019)) >> U64(20)) % U64(m)).astype(np.int64)
        early = time < first[slot]
        slot_e, time_e, item_e = slot[early], time[early], item[early]
        np.minimum.at(first, slot_e, time_e)
        won = first[slot_e] == time_e
        who[slot_e[won]] = item_e[won]
        last = first.reshape(n_docs, m).max(axis=1)
        go = time < last[doc]
        doc, item, rate, seed, time = doc[go], item[go], rate[go], seed[go], time[go]
    return who.reshape(n_docs, m)


def band_hashes(who: np.ndarray, bands: int, rows: int) -> np.ndarray:
    out = np.zeros((len(who), bands), U64)
    for r in range(rows):
        out = tx.mix(out + who[:, r::rows][:, :bands] * U64(0x9FB21C651E98DF25) + U64(r + 1))
    return out


def probability_jaccard(a_item, a_weight, b_item, b_weight) -> float:
    """Exact value for two weight vectors given as sorted distinct items with weights."""
    items = np.union1d(a_item, b_item)
    if not len(items):
        return 0.0
    x, y = np.zeros(len(items)), np.zeros(len(items))
    x[np.searchsorted(items, a_item)] = a_weight
    y[np.searchsorted(items, b_item)] = b_weight
    with np.errstate(divide="ignore"):
        ratio = y / x
    order = np.argsort(ratio, kind="stable")
    x, y = x[order], y[order]
    below = np.cumsum(x)
    above = y.sum() - np.cumsum(y)
    both = (x > 0) & (y > 0)
    # equal ratios give the same maximum whichever side of the cut they stand on
    return float((1.0 / (below[both] / x[both] + above[both] / y[both])).sum())


def packed(who: np.ndarray) -> pa.StructArray:
    """Four bits of each register, sixteen registers to a number: (s0, s1, ...)."""
    n, m = who.shape
    words = -(-m // 16)
    bits = np.zeros((n, words * 16), U64)
    bits[:, :m] = tx.mix(who + U64(0x2545F4914F6CDD1D)) >> U64(60)
    bits = np.bitwise_or.reduce(bits.reshape(n, words, 16) << (U64(4) * np.arange(16, dtype=U64)), axis=2).view(np.int64)
    return pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(bits[:, i])) for i in range(words)], [f"s{i}" for i in range(words)])


def differing(a: str, b: str, words: int) -> Column:
    """How many registers differ between two columns of ``packed``; all in generated code."""
    def one(i):
        x = f"({a}.s{i} ^ {b}.s{i})"
        return f"bit_count(({x} | shiftrightunsigned({x}, 1) | shiftrightunsigned({x}, 2) | shiftrightunsigned({x}, 3)) & 1229782938247303441L)"

    return F.expr(" + ".join(one(i) for i in range(words)))


def most_differing(m: int, threshold: float, deviations: float = 3.5) -> int:
    """Registers of ``m`` that differ at most in a pair at the threshold, but for chance beyond so many standard deviations."""
    return int(np.floor(m * (1 - threshold) + deviations * np.sqrt(m * threshold * (1 - threshold))))


def _bands(docs: DataFrame, k: int, bands: int, rows: int) -> DataFrame:
    """(doc_id, digest, bands, sig): one row per input row; bands is null where there is no shingle."""
    m = bands * rows
    words = -(-m // 16)

    def run(batches):
        tx.low_memory()
        for part in tx.slices(batches, "text"):
            d, item, n = weighted(part.column("text"), k)
            registers = signatures(d, item, n, part.num_rows, m)
            who = band_hashes(registers, bands, rows).view(np.int64)
            some = np.zeros(part.num_rows, bool)
            some[d] = True
            at = np.concatenate([[0], np.cumsum(np.where(some, bands, 0))]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(at), pa.array(who[some].ravel()), mask=pa.array(~some) if not some.all() else None)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("digest"), lists, packed(registers)], ["doc_id", "digest", "bands", "sig"])

    src = docs.select("doc_id", F.expr(DIGEST).alias("digest"), "text")
    return src.mapInArrow(run, f"doc_id bigint, digest string, bands array<bigint>, sig struct<{', '.join(f's{i}: bigint' for i in range(words))}>")


def _verify(pairs: DataFrame, docs: DataFrame, k: int, threshold: float, small: int) -> DataFrame:
    """(a, b, score) of those pairs whose probability Jaccard reaches the threshold."""
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    ids = staged(ids, "nd-ids")
    few = ids.count() <= small
    texts = docs.select(F.col("doc_id").alias("id"), "text").join(F.broadcast(ids) if few else ids, "id", "left_semi")
    first = F.min(F.struct(F.expr(DIGEST).alias("digest"), "text"))  # the row that the digest and the bands of an id come from
    texts = staged(texts.groupBy("id").agg(first["text"].alias("text")), "nd-texts")
    both = (
        pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b")
        .join(texts.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a")
        .select("a", "b", "text_a", "text_b")
    )

    def run(batches):
        tx.low_memory()
        for whole in tx.slices(batches, "text_b"):
            for part in tx.slices([whole], "text_a"):
                n = part.num_rows
                sides = []
                for c in ("text_a", "text_b"):
                    d, item, w = weighted(part.column(c), k)
                    sides.append((np.searchsorted(d, np.arange(n + 1)), item, w))
                (ia, xa, wa), (ib, xb, wb) = sides
                score = np.array([probability_jaccard(xa[ia[i] : ia[i + 1]], wa[ia[i] : ia[i + 1]], xb[ib[i] : ib[i + 1]], wb[ib[i] : ib[i + 1]]) for i in range(n)])
                ok = score >= threshold
                yield pa.RecordBatch.from_arrays([part.column("a"), part.column("b"), pa.array(score, pa.float64())], ["a", "b", "score"]).filter(pa.array(ok))

    return both.mapInArrow(run, "a bigint, b bigint, score double")


def near_pairs(light: DataFrame, docs: DataFrame, k: int, threshold: float, small: int, registers: int = 0) -> DataFrame:
    """Verified pairs (a, b, score) among representatives, enough to connect each group.

    light: (doc_id, bands), and sig, of so many ``registers``, by which hopeless pairs are left out; with 0 all pairs are verified.
    """
    bucket = Window.partitionBy("band", "h")
    rows = (
        light.where("bands is not null").select(F.col("doc_id").alias("b"), F.posexplode("bands").alias("band", "h"))
        .withColumn("a", F.min("b").over(bucket)).where("a <> b")
    )
    rows = staged(rows, "nd-buckets")
    stars = rows.select("a", "b").distinct()
    likely = stars
    if registers:
        alike = differing("sig", "other", -(-registers // 16)) <= most_differing(registers, threshold)
        sig = light.select(F.col("doc_id").alias("b"), "sig")
        likely = stars.join(sig, "b").join(sig.select(F.col("b").alias("a"), F.col("sig").alias("other")), "a").where(alike).select("a", "b")
    first = staged(_verify(likely, docs, k, threshold, small), "nd-first")
    linked = connected_groups(first).withColumnRenamed("id", "b")
    members = (
        rows.join(first.select("a", "b", F.lit(True).alias("ok")), ["a", "b"], "left").join(linked, "b", "left")
        .select("band", "h", "b", F.coalesce("group_id", "b").alias("g"), F.col("ok").isNull().alias("failed"))
    )
    members = staged(members.join(sig, "b") if registers else members, "nd-members")
    failed = members.where("failed").select("band", "h", F.col("b").alias("c"), F.col("g").alias("cg"), *([F.col("sig").alias("other")] if registers else []))
    # failed with failed once, failed with passed always; never two that are in one group already
    others = failed.join(members, ["band", "h"]).where("cg <> g and (not failed or c < b)")
    others = (
        (others.where(alike) if registers else others).select(F.least("b", "c").alias("a"), F.greatest("b", "c").alias("b")).distinct()
        .join(stars, ["a", "b"], "left_anti")
    )
    others = staged(others, "nd-rest")
    if others.isEmpty():
        return first
    return first.union(staged(_verify(others, docs, k, threshold, small), "nd-second"))


def near_duplicate_groups(docs: DataFrame, k: int = 3, threshold: float = 0.5, bands: int = 24, rows: int = 3, small: int = 2_000_000) -> DataFrame:
    """(doc_id, group_id, copies, kept) for every document.

    copies: documents with exactly this text. kept: it is the one that stays of its group. small: up to so many candidate ids
    (8 bytes each) their set is broadcast to pick their texts from the scan; beyond, that join is shuffled.
    """
    light = staged(_bands(docs, k, bands, rows), "nd-light")
    named = light.where("doc_id is not null")
    one = named.groupBy("doc_id").agg(F.min(F.struct("digest", "bands", "sig")).alias("x")).select("doc_id", "x.*")
    texts = one.groupBy("digest").agg(F.min(F.struct("doc_id", "bands", "sig")).alias("x"), F.count("*").alias("copies"))
    texts = staged(texts.select("digest", F.col("x.doc_id").alias("rep"), "copies", "x.bands", "x.sig"), "nd-texts")
    pairs = near_pairs(texts.select(F.col("rep").alias("doc_id"), "bands", "sig"), docs.where("doc_id is not null"), k, threshold, small, bands * rows)
    groups = connected_groups(pairs)
    labelled = texts.join(groups, F.col("rep") == F.col("id"), "left").select("digest", "copies", F.coalesce("group_id", "rep").alias("group_id"))
    found = one.select("doc_id", "digest").join(labelled, "digest").select("doc_id", "group_id", F.col("copies").cast("bigint"), (F.col("doc_id") == F.col("group_id")).alias("kept"))
    alone = light.where("doc_id is null").select("doc_id", F.lit(None).cast("bigint").alias("group_id"), F.lit(1).cast("bigint").alias("copies"), F.lit(True).alias("kept"))
    return found.union(alone)


def drop_near_duplicates(docs: DataFrame, small: int = 2_000_000, **options) -> DataFrame:
    """The rows of ``docs`` that stay: one of each group, one of rows that repeat a doc_id, and all rows without one."""
    groups = staged(near_duplicate_groups(docs, small=small, **options), "nd-groups")
    gone = groups.where("not kept").select("doc_id")
    few = gone.count() <= small
    left = docs.join(F.broadcast(gone) if few else gone, "doc_id", "left_anti").select(*docs.columns)
    again = left.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    again = staged(again, "nd-again")
    if again.isEmpty():
        return left
    single = left.join(again, "doc_id", "left_anti").select(*docs.columns)
    name = free_name(docs, "nd_rank")
    several = left.join(again, "doc_id", "left_semi").withColumn(name, F.row_number().over(Window.partitionBy("doc_id").orderBy(F.expr(DIGEST))))
    return single.unionByName(several.where(F.col(name) == 1).select(*docs.columns))
