"""Operator 2: code length of documents under context-tree weighting.

A byte is eight binary decisions; each decision, in the context of the last 0 to ``depth`` bytes, has a Krichevsky-Trofimov estimate from
the whole corpus, and weights mix the estimates of all depths: at a node, one half for its own estimate and one half for its
children's product, so the predictive probability is w * KT + (1 - w) * (the deeper node's), w being the node's posterior weight. The
sum of -log2 over a document's bytes is its code length, reported per byte.

Counts are of whole (depth + 1)-grams over all documents. Documents are spread over chunks by a hash, written once, a file for each
chunk; tasks count a chunk's distinct n-grams where they read it, and read their code lengths back when they score it, so texts are shuffled
once, nothing that grows with the corpus is broadcast and no row is made per byte. N-grams are weighted in groups of whole pairs of
newest context bytes, of which there are up to 65,536; the levels above, the root and the newest byte's, at most 256 x 255 nodes, pass
through the driver. What bounds a group is its largest pair of bytes, a few per cent of the distinct n-grams.

Defined cases: null or empty text has 0 bytes and null code length; null ``doc_id`` and repeated rows: one output row per input
row, each counts; bytes before a document's start are 0; empty table: empty result. Extra columns aren't read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from catalogflow.llm import text as tx
from catalogflow.llm.packing import HASH
from catalogflow.session import fresh_path, staged

U64 = np.uint64
LOG2 = np.log(2.0)


def log_gamma(x: np.ndarray) -> np.ndarray:
    """For x > 0, by recurrence and Stirling's series (error below 1e-12)."""
    y = x + 8.0
    less = np.log(x * (x + 1) * (x + 2) * (x + 3)) + np.log((x + 4) * (x + 5) * (x + 6) * (x + 7))
    inv = 1.0 / y
    return (y - 0.5) * np.log(y) - y + 0.9189385332046727 + inv / 12 - inv**3 / 360 + inv**5 / 1260 - less


def log_kt(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return log_gamma(a + 0.5) + log_gamma(b + 0.5) - log_gamma(a + b + 1.0) - np.log(np.pi)


def grams(texts: pa.Array, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(n-gram that ends at each byte, document of each byte); the newest byte is the lowest, older ones are higher."""
    body, at = tx.raw(texts)
    size = np.diff(at)
    doc = np.repeat(np.arange(len(size)), size)
    padded = np.zeros(len(body) + depth * len(size) + depth, U64)
    place = np.arange(len(body)) + depth * (doc + 1)
    padded[place] = body
    code = padded.copy()
    for k in range(1, depth + 1):
        code[k:] |= padded[:-k] << U64(8 * k)
    return code[place], doc


class Tree:
    """Nodes of all depths >= 1 for n-grams that share their newest context byte (or of all depths, for a brute-force test)."""

    def __init__(self, gram: np.ndarray, n: np.ndarray, depth: int, top: int = 1):
        self.depth, self.top, self.levels = depth, top, {}
        self.gram = gram
        below = None
        for d in range(depth, top - 1, -1):
            context = (gram >> U64(8)) & U64((1 << (8 * d)) - 1)
            byte = gram & U64(255)
            ids = np.concatenate([(context << U64(8)) | (U64(1 << k) | (byte >> U64(8 - k))) for k in range(8)])
            bit = np.concatenate([(byte >> U64(7 - k)) & U64(1) for k in range(8)])
            node, of = np.unique(ids, return_inverse=True)
            ones = np.bincount(of, weights=np.tile(n, 8) * bit, minlength=len(node))
            zeros = np.bincount(of, weights=np.tile(n, 8) * (bit == 0), minlength=len(node))
            own = log_kt(zeros, ones)
            if below is None:
                weighted, stay = own, np.ones(len(node))
            else:
                child_node, child_w = below
                up = ((child_node >> U64(8)) & U64((1 << (8 * d)) - 1)) << U64(8) | (child_node & U64(255))
                product = np.bincount(np.searchsorted(node, up), weights=child_w, minlength=len(node))
                weighted = np.logaddexp(own, product) - LOG2
                stay = np.exp(own - LOG2 - weighted)
            self.levels[d] = (node, of, zeros, ones, stay, weighted)
            below = (node, weighted)
        self.bit = bit

    def predict(self) -> np.ndarray:
        """8 x n-grams: probability of each actual bit, mixed over the depths from the deepest to ``top``."""
        q = None
        for d in range(self.depth, self.top - 1, -1):
            _, of, zeros, ones, stay, _ = self.levels[d]
            kt = (np.where(self.bit == 1, ones[of], zeros[of]) + 0.5) / (zeros[of] + ones[of] + 1.0)
            q = kt if q is None else stay[of] * kt + (1 - stay[of]) * q
        return q.reshape(8, -1)


class Lookup:
    """Open addressing for 64-bit keys that are all present."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        bits = max(4, int(2 * len(keys)).bit_length())
        self.mask, self.shift = (1 << bits) - 1, U64(64 - bits)
        self.key, self.value = np.full(1 << bits, (1 << 64) - 1, U64), np.zeros(1 << bits, np.float32)
        slot, rest = self.slot(keys), np.arange(len(keys))
        while len(rest):
            free = self.key[slot] == U64((1 << 64) - 1)
            self.key[slot[free]] = keys[rest[free]]
            got = self.key[slot] == keys[rest]
            self.value[slot[got]] = values[rest[got]]
            slot, rest = (slot[~got] + 1) & self.mask, rest[~got]

    def slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * U64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        slot = self.slot(keys)
        out = self.value[slot]
        miss = np.flatnonzero(self.key[slot] != keys)
        slot = slot[miss]
        while len(miss):
            slot = (slot + 1) & self.mask
            out[miss] = self.value[slot]
            far = self.key[slot] != keys[miss]
            miss, slot = miss[far], slot[far]
        return out


def merged(found: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    code, of = np.unique(np.concatenate([c for c, _ in found]), return_inverse=True)
    return code, np.bincount(of, weights=np.concatenate([n for _, n in found]), minlength=len(code)).astype(np.int64)


def head(nodes, leaf: bool) -> list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(mask, zeros, ones, stay) of the levels above the groups' trees, the deeper first, indexed by node & mask.

    nodes: the level below them summed by newest byte and prefix (node, zeros, ones, weighted), at most 65,280 rows. leaf: the
    trees begin at that level, so that only the root is above.
    """
    table = np.zeros((3, 1 << 16))
    table[:, nodes["node"].to_numpy()] = nodes[["zeros", "ones", "weighted"]].to_numpy().T
    out = []
    if not leaf:
        own = log_kt(table[0], table[1])
        mixed = np.logaddexp(own, table[2]) - LOG2
        out.append(((1 << 16) - 1, table[0], table[1], np.exp(own - LOG2 - mixed)))
        table[2] = np.where(table[0] + table[1] > 0, mixed, 0)
    root = table.reshape(3, 256, 256).sum(axis=1)
    own = log_kt(root[0], root[1])
    out.append((255, root[0], root[1], np.exp(own - LOG2 - (np.logaddexp(own, root[2]) - LOG2))))
    return out


def code_lengths(docs: DataFrame, depth: int = 4, chunk_chars: int = 16_000_000, group_grams: int = 1_000_000) -> DataFrame:
    """(doc_id, n_bytes, bits, bits_per_byte).

    depth: bytes of context, 1 to 6; chunk_chars: text of one chunk; group_grams: about so many n-grams are weighted in one Python group.
    """
    if not 1 <= depth <= 6:
        raise ValueError("depth must be 1 to 6")
    spark = docs.sparkSession
    total = docs.agg(F.sum(F.length("text"))).first()[0] or 0
    chunks = max(1, -(-total // chunk_chars))
    # the one shuffle of texts: each chunk becomes one file, whose rows both passes read in a row
    keyed = docs.select((F.expr(HASH) % chunks).cast("int").alias("chunk"), "doc_id", "text").repartitionById(chunks, "chunk")
    texts = staged(keyed, "ctw-texts")

    def runs(batches):
        """(chunk, rows) in slices that lie in one chunk."""
        for part in tx.slices(batches, "text"):
            chunk = part.column("chunk").to_numpy()
            edge = [0, *(np.flatnonzero(np.diff(chunk)) + 1).tolist(), len(chunk)]
            for i, j in zip(edge, edge[1:]):
                yield int(chunk[i]), part.slice(i, j - i)

    def count(batches):
        tx.low_memory()
        now, found, seen = None, [], 0

        def flush():
            code, n = merged(found)
            if len(code):
                yield pa.RecordBatch.from_pydict({"chunk": pa.array(np.full(len(code), now), pa.int32()), "gram": pa.array(code.view(np.int64)), "n": pa.array(n)})

        for chunk, part in runs(batches):
            if chunk != now:
                if found:
                    yield from flush()
                now, found, seen = chunk, [], 0
            found.append(np.unique(grams(part.column("text"), depth)[0], return_counts=True))
            seen += len(found[-1][0])
            if seen > 4_000_000:
                found = [merged(found)]
                seen = 0
        if found:
            yield from flush()

    split = min(2, depth)  # newest context bytes by which n-grams are grouped
    partial = staged(texts.select("chunk", "text").mapInArrow(count, "chunk int, gram bigint, n bigint"), "ctw-partial")
    counts = staged(partial.groupBy("gram").agg(F.sum("n").alias("n")), "ctw-counts")
    groups = max(1, -(-counts.count() // group_grams))
    lead = F.shiftright("gram", 8).bitwiseAND(F.lit((1 << (8 * split)) - 1))
    counts = counts.withColumn("g", F.pmod(F.xxhash64(lead), F.lit(groups)))

    def ordered(rows):
        gram, n = rows.column("gram").to_numpy().view(U64), rows.column("n").to_numpy()
        order = np.argsort(gram, kind="stable")
        return gram[order], n[order].astype(float)

    def tops(key, rows):
        tx.low_memory()
        node, _, zeros, ones, _, weighted = Tree(*ordered(rows), depth, split).levels[split]
        return pa.table({"node": pa.array((node & U64(0xFFFF)).astype(np.int64)), "zeros": pa.array(zeros), "ones": pa.array(ones), "weighted": pa.array(weighted)})

    top = (
        counts.groupBy("g").applyInArrow(tops, "node bigint, zeros double, ones double, weighted double")
        .groupBy("node").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"), F.sum("weighted").alias("weighted"))
    ).toPandas()
    upper = spark.sparkContext.broadcast(head(top, split == 1))

    def lengths(key, rows):
        tx.low_memory()
        gram, n = ordered(rows)
        q = Tree(gram, n, depth, split).predict()
        byte, newest = (gram & U64(255)).astype(np.int64), (gram & U64(0xFF00)).astype(np.int64)
        bits = np.zeros(len(gram))
        for k in range(8):
            node, bit, p = newest | (1 << k) | (byte >> (8 - k)), (byte >> (7 - k)) & 1, q[k]
            for mask, zeros, ones, stay in upper.value:
                at = node & mask
                p = stay[at] * (np.where(bit == 1, ones[at], zeros[at]) + 0.5) / (zeros[at] + ones[at] + 1.0) + (1 - stay[at]) * p
            bits -= np.log2(p)
        return pa.table({"gram": pa.array(gram.view(np.int64)), "bits": pa.array(bits.astype(np.float32))})

    bits = counts.groupBy("g").applyInArrow(lengths, "gram bigint, bits float")
    path = fresh_path(spark, "ctw-bits")
    known = partial.select("chunk", "gram").join(bits, "gram")
    known.repartitionById(chunks, "chunk").write.partitionBy("chunk").parquet(path)

    def score(batches):
        from pyarrow import dataset, fs

        tx.low_memory()
        system, root = fs.FileSystem.from_uri(path)
        now, find = None, None
        for chunk, part in runs(batches):
            code, doc = grams(part.column("text"), depth)
            if len(code) and chunk != now:
                find = None
                right = dataset.dataset(f"{root}/chunk={chunk}", filesystem=system, format="parquet", exclude_invalid_files=True).to_table(columns=["gram", "bits"])
                gram, value = right.column("gram").to_numpy().view(U64), right.column("bits").to_numpy()
                one, at = np.unique(gram, return_index=True)  # a chunk that two tasks counted stands twice
                now, find = chunk, Lookup(one, value[at])
            n = np.bincount(doc, minlength=part.num_rows)
            b = np.bincount(doc, weights=find(code), minlength=part.num_rows) if len(code) else np.zeros(part.num_rows)
            none = n == 0
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), pa.array(n, pa.int64()), pa.array(b, mask=none), pa.array(b / np.maximum(n, 1), mask=none)], ["doc_id", "n_bytes", "bits", "bits_per_byte"]
            )

    return texts.mapInArrow(score, "doc_id bigint, n_bytes bigint, bits double, bits_per_byte double")
