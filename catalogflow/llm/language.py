"""Operator 4: languages of each document and their proportions, by expectation-maximisation.

Model: byte trigrams inside words without digits (word ends count as a blank), hashed to ``buckets``; their relative
frequencies per language are counted over all rows with a label. A word's likelihood in a language is the
product over its trigrams; a document is a mixture of languages and of an "other" component that is uniform
over trigrams. EM estimates the mixture, for each document until its own proportions stand still; among the nested sets of the
largest languages the one with the best likelihood less ``penalty * |set| * log(1 + words)`` is taken. When a bound on the likelihood
of all languages together doesn't pay for a second one, no set between can, and these are not fitted.

Defined cases: null or empty text, or text without words of letters: no words, ``li_pred`` null,
``li_rejected`` true. Null ``doc_id`` or repeated rows: one output row per input row. Rows without a label
(null) don't train. No labelled row at all: every row is rejected. Ties go to the first language in
alphabetical order. Columns other than doc_id, text and the label aren't read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from catalogflow.llm import text as tx

RESULT = "li_pred string, li_langs string, li_share double, li_other double, li_words bigint, li_rejected boolean"


def trigrams(texts: pa.Array, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bucket of each byte of a word, where each word begins among them, document of each word)."""
    doc, _, start, end, low = tx.words(texts)
    digits = np.concatenate([[0], np.cumsum((low >= 48) & (low <= 57))])
    plain = digits[end] == digits[start]
    doc, start, end = doc[plain], start[plain], end[plain]
    if not len(start):
        return np.zeros(0, np.int64), start, doc
    size = end - start
    first = np.concatenate([[0], np.cumsum(size)])[:-1]
    at = np.repeat(start - first, size) + np.arange(int(size.sum()))
    ch = low[at].astype(np.uint32)
    left, right = np.empty_like(ch), np.empty_like(ch)
    left[1:], right[:-1] = ch[:-1], ch[1:]
    left[first] = 32
    right[first + size - 1] = 32
    code = (left << np.uint32(16)) | (ch << np.uint32(8)) | right
    code = (code * np.uint32(2654435761)) >> np.uint32(32 - (buckets.bit_length() - 1))
    return code.astype(np.int64), first, doc


def fit(docs: DataFrame, label: str = "lang", buckets: int = 1 << 16, smooth: float = 0.5) -> tuple[list[str], np.ndarray]:
    """(languages, log probability per language and bucket), counted over all labelled rows.

    What comes to the driver is at most languages x ``buckets`` numbers, whatever the corpus.
    """

    def count(batches):
        tx.low_memory()
        seen: dict[str, np.ndarray] = {}
        for part in tx.slices(batches, "text"):
            code, first, doc = trigrams(part.column("text"), buckets)
            tags = part.column("tag").dictionary_encode()
            names, of = tags.dictionary.to_pylist(), tags.indices.to_numpy(zero_copy_only=False)
            size = np.diff(np.append(first, len(code)))
            of_code = np.repeat(of[doc], size)
            for i, name in enumerate(names):
                seen.setdefault(name, np.zeros(buckets, np.int64))
                seen[name] += np.bincount(code[of_code == i], minlength=buckets)
        for name, n in seen.items():
            hit = np.flatnonzero(n)
            yield pa.RecordBatch.from_pydict({"tag": pa.array([name] * len(hit), pa.string()), "bucket": pa.array(hit, pa.int64()), "n": pa.array(n[hit], pa.int64())})

    counted = (
        docs.select("text", F.col(label).alias("tag")).where("tag is not null and text is not null")
        .mapInArrow(count, "tag string, bucket bigint, n bigint").groupBy("tag", "bucket").agg(F.sum("n").alias("n"))
    ).toPandas()
    names = sorted(counted["tag"].unique())
    table = np.full((len(names), buckets), smooth)
    for i, name in enumerate(names):
        own = counted[counted["tag"] == name]
        table[i, own["bucket"].to_numpy()] += own["n"].to_numpy()
    return names, np.log(table / table.sum(axis=1, keepdims=True)).astype(np.float32) if names else table.astype(np.float32)


def mixture(like: np.ndarray, first: np.ndarray, size: np.ndarray, allowed: np.ndarray, least: float = 1e-3) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(proportions per component and document, log likelihood, what it lacks of the optimum at most), by EM from equal proportions.

    like: component x word, scaled likelihoods; allowed: component x document. A document is left when no proportion of its own moves
    by ``least`` any more, so its result doesn't depend on the documents beside it. The log likelihood is concave in the
    proportions, so it lacks at most (largest slope towards a component) - (words).
    """
    share = allowed / np.maximum(allowed.sum(axis=0), 1)
    live, words, at, n = np.arange(len(size)), like, first, size
    while len(live):
        parts = np.repeat(share[:, live], n, axis=1) * words
        new = np.add.reduceat(parts / (parts.sum(axis=0) + 1e-300), at, axis=1) / n
        go = np.abs(new - share[:, live]).max(axis=0) >= least
        share[:, live] = new
        if not go.all():
            words, live, n = words[:, np.repeat(go, n)], live[go], n[go]
            at = np.concatenate([[0], np.cumsum(n)])[:-1]
    total = (np.repeat(share, size, axis=1) * like).sum(axis=0) + 1e-300
    slope = np.where(allowed > 0, np.add.reduceat(like / total, first, axis=1), 0).max(axis=0)
    return share, np.add.reduceat(np.log(total), first), np.maximum(slope - size, 0)


def infer(texts: pa.Array, names: list[str], table: np.ndarray, penalty: float = 1.0, max_other: float = 0.8) -> dict[str, list]:
    """The columns of RESULT for the texts."""
    n_docs, n_lang, buckets = len(texts), len(names), table.shape[1]
    pred: list = [None] * n_docs
    langs: list = [None] * n_docs
    top, other = np.zeros(n_docs), np.ones(n_docs)
    code, at, doc = trigrams(texts, buckets)
    words = np.bincount(doc, minlength=n_docs)
    if len(at) and n_lang:
        ll = np.stack([np.add.reduceat(table[i][code], at) for i in range(n_lang)] + [-np.log(buckets) * np.diff(np.append(at, len(code)))])
        like = np.exp(ll - ll.max(axis=0))
        some = np.flatnonzero(words)
        size = words[some]
        first = np.concatenate([[0], np.cumsum(size)])[:-1]
        every = np.ones((n_lang + 1, len(some)))
        share, best, lack = mixture(like, first, size, every)
        order = np.argsort(-share[:-1], axis=0, kind="stable")
        rank = np.argsort(order, axis=0, kind="stable")
        cost = penalty * np.log1p(size)
        one = np.vstack([rank == 0, np.ones((1, len(some)), bool)]).astype(float)
        chosen, ll_one, _ = mixture(like, first, size, one)
        score, k_best = ll_one - cost, np.ones(len(some), int)
        more = np.flatnonzero(best + lack - 2 * cost > score) if n_lang > 1 else np.zeros(0, int)
        if len(more):
            of = np.repeat(np.isin(np.arange(len(some)), more), size)
            sub, sub_size = like[:, of], size[more]
            sub_first = np.concatenate([[0], np.cumsum(sub_size)])[:-1]
            for k in range(2, n_lang + 1):
                allow = np.vstack([rank[:, more] < k, np.ones((1, len(more)), bool)]).astype(float)
                s, v = mixture(sub, sub_first, sub_size, allow)[:2] if k < n_lang else (share[:, more], best[more])
                v = v - k * cost[more]
                better = v > score[more]
                score[more[better]], k_best[more[better]] = v[better], k
                chosen[:, more[better]] = s[:, better]
        order = np.argsort(-chosen[:-1], axis=0, kind="stable")
        for j, d in enumerate(some):
            pred[d] = names[order[0, j]]
            langs[d] = ",".join(names[i] for i in order[: k_best[j], j])
        top[some], other[some] = chosen[:-1].max(axis=0), chosen[-1]
    reject = (words == 0) | (other > max_other) | (n_lang == 0)
    return {"li_pred": pred, "li_langs": langs, "li_share": np.round(top, 4), "li_other": np.round(other, 4), "li_words": words.astype(np.int64), "li_rejected": reject}


def identify(docs: DataFrame, model: tuple[list[str], np.ndarray], keep: list[str] | None = None, accepted_only: bool = False, **options) -> DataFrame:
    """``keep`` columns (doc_id unless given) and the columns of RESULT; only accepted rows, without RESULT, if so asked."""
    keep = ["doc_id"] if keep is None else keep
    read = list(dict.fromkeys([*keep, "text"]))
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)
    fields = [docs.schema[c] for c in keep]
    out = T.StructType(fields if accepted_only else fields + T.StructType.fromDDL(RESULT).fields)
    types = [pa.string(), pa.string(), pa.float64(), pa.float64(), pa.int64(), pa.bool_()]

    def run(batches):
        tx.low_memory()
        names, table = shared.value
        for part in tx.slices(batches, "text"):
            got = infer(part.column("text"), names, table, **options)
            kept = [part.column(c) for c in keep]
            if accepted_only:
                yield pa.RecordBatch.from_arrays(kept, keep).filter(pa.array(~got["li_rejected"]))
            else:
                yield pa.RecordBatch.from_arrays(kept + [pa.array(v, t) for v, t in zip(got.values(), types)], keep + list(got))

    return docs.select(*read).mapInArrow(run, out)
