"""Operator 3: I-Match fingerprints.

A lexicon holds the terms whose document frequency lies in a band of shares of the corpus. A document's distinct
lexicon terms, sorted, are hashed together; so are those of several random subsets of the lexicon, so that a term that one
copy lacks spoils only some of the hashes. Both ends of the band are shares of the number of documents: with the lower share
``low`` the lexicon has at most (mean distinct terms of a document) / ``low`` terms however large the corpus is, which bounds
what every worker reads. A term that stands in one document only is never in the lexicon, whatever ``low`` says: it can't be shared.

Terms: lower case, split at everything but letters a-z, à-ÿ, ß and digits. Defined cases: null or empty text, or text
without lexicon terms: n_terms 0 and null hashes; null ``doc_id`` and repeated rows: one output row per input row, each
counts as a document; empty table: empty result. Repeated terms count once; extra columns aren't read.
"""

from __future__ import annotations

import hashlib
import sys

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from catalogflow.llm import text as tx
from catalogflow.session import fresh_path

SPLIT = r"[^a-z0-9ß-öø-ÿà]+"


def distinct_terms(texts: pa.Array) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """(document of each pair, the batch's terms, term of each pair): distinct pairs in order of document."""
    parts = pc.split_pattern_regex(pc.utf8_lower(pc.fill_null(texts, "")), pattern=SPLIT)
    doc = pc.list_parent_indices(parts).to_numpy(zero_copy_only=False).astype(np.int64)
    enc = parts.flatten().dictionary_encode()
    term = enc.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    n = max(1, len(enc.dictionary))
    empty = pc.index(enc.dictionary, pa.scalar("", enc.dictionary.type)).as_py() if len(enc.dictionary) else -1
    pair = np.unique((doc * n + term)[term != empty])
    return pair // n, enc.dictionary, pair % n


def lexicon(docs: DataFrame, low: float, high: float, subsets: int) -> str:
    """Path of the written lexicon (term, bits); bit k of ``bits``: the term belongs to random subset k."""

    def count(batches):
        tx.low_memory()
        for whole in batches:
            found: list[pa.Table] = []
            rows = 0
            for part in tx.slices([whole], "text", 1_000_000):
                doc, terms, term = distinct_terms(part.column("text"))
                n = np.bincount(term, minlength=len(terms))
                hit = np.flatnonzero(n)
                found.append(pa.table({"term": terms.take(pa.array(hit)), "n": pa.array(n[hit], pa.int64())}))
                rows += part.num_rows
            found.append(pa.table({"term": pa.array([None], pa.string()), "n": pa.array([rows], pa.int64())}))
            merged = pa.concat_tables(found).group_by("term").aggregate([("n", "sum")]).rename_columns(["term", "n"])
            yield from merged.combine_chunks().to_batches(max_chunksize=200_000)

    spark = docs.sparkSession
    counted = docs.select("text").mapInArrow(count, "term string, n bigint").groupBy("term").agg(F.sum("n").alias("n"))
    path = fresh_path(spark, "imatch-df")
    counted.write.parquet(path)
    df = spark.read.parquet(path)
    total = df.where("term is null").select(F.col("n").alias("docs"))
    bits = F.lit(0)
    for k in range(subsets):
        bits = bits + F.when(F.substring(F.md5(F.concat(F.lit(f"{k}:"), F.col("term"))), 1, 1) < "a", F.lit(1 << k)).otherwise(0)
    chosen = (
        df.where("term is not null").crossJoin(F.broadcast(total))
        .where((F.col("n") >= F.ceil(F.col("docs") * low)) & (F.col("n") <= F.floor(F.col("docs") * high)) & (F.col("n") >= 2))
        .select("term", bits.cast("int").alias("bits"))
    )
    out = fresh_path(spark, "imatch-lexicon")
    chosen.write.parquet(out)
    return out


def _load(path: str) -> tuple[pa.Array, np.ndarray]:
    """The lexicon sorted by term, once per worker process."""
    import pyarrow.dataset as ds
    from pyarrow import fs

    kept = sys.modules[__name__].__dict__.setdefault("_loaded", {})
    if path not in kept:
        kept.clear()
        system, inner = fs.FileSystem.from_uri(path)
        t = ds.dataset(inner, filesystem=system, format="parquet", exclude_invalid_files=True).to_table()
        t = t.sort_by("term").combine_chunks()
        term = t.column("term")
        kept[path] = ((term.combine_chunks() if isinstance(term, pa.ChunkedArray) else term), t.column("bits").to_numpy())
    return kept[path]


def fingerprints(docs: DataFrame, low: float = 0.0005, high: float = 0.1, subsets: int = 4) -> DataFrame:
    """(doc_id, n_terms, full_hash, hash_0 ...): md5 of the sorted lexicon terms, of all and of each random subset."""
    path = lexicon(docs, low, high, subsets)
    names = ["full_hash"] + [f"hash_{k}" for k in range(subsets)]

    def run(batches):
        tx.low_memory()
        lex, bits = _load(path)
        lex = lex.cast(pa.string())
        for part in tx.slices(batches, "text", 1_000_000):
            n_docs = part.num_rows
            doc, terms, term = distinct_terms(part.column("text"))
            rank = pc.fill_null(pc.index_in(terms, value_set=lex), -1).to_numpy(zero_copy_only=False)[term] if len(terms) else term
            doc, rank = doc[rank >= 0], rank[rank >= 0]
            pair = np.sort(doc * (len(lex) + 1) + rank)
            doc, rank = pair // (len(lex) + 1), pair % (len(lex) + 1)
            cols = [part.column("doc_id"), pa.array(np.bincount(doc, minlength=n_docs).astype(np.int64))]
            for k in range(-1, subsets):
                use = np.ones(len(doc), bool) if k < 0 else (bits[rank] >> k) & 1 == 1
                d, r = doc[use], rank[use]
                at = np.searchsorted(d, np.arange(n_docs + 1)).astype(np.int32)
                joined = pc.binary_join(pa.ListArray.from_arrays(pa.array(at), lex.take(pa.array(r))), " ").to_pylist()
                cols.append(pa.array([hashlib.md5(s.encode()).hexdigest() if s else None for s in joined], pa.string()))
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_terms", *names])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_terms bigint, " + ", ".join(f"{n} string" for n in names))
