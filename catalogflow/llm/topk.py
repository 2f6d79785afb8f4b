"""Operator 8: exact top-k neighbours by inner product, with Fagin's threshold algorithm.

Every row is searched; the queries are all rows, or those that ``asked`` picks. Rows are ordered by their leading dimension and cut into data blocks, each written once, as one file, with one
sorted list per dimension and the least and most value of each. Queries come in blocks too. One task takes a block of queries, in groups,
through the data blocks, those with the highest bound for the group first, and carries each query's k best along: a block whose bound is
below every kth score of the group is never opened. In a block the lists are read from the end that a query's sign asks for, in steps that
double; rows not seen before get their full scores for the whole group at once (one matrix product), and a query leaves as soon as
its bound, the inner product with the values at the reading positions, is below its kth best score (no unseen row can then
enter), or all rows are seen.

So no vector is shuffled more often where there are more blocks. Where the bounds don't tell blocks apart, as on random vectors, all
pairs of a query and a row are still scored, queries times rows, and all blocks are read by every block of queries.

Defined cases: rows with null id or vector, of another length than the commonest, or with null or non-finite numbers are neither queries
nor neighbours; ``asked`` is a condition on ``vec_id``, and where it is null the row is no query; repeated ids count once (smallest vector); a row isn't its own neighbour; ties go to the smaller id; with fewer than k other rows, all
are given; scores are rounded to 9 digits before they are compared (above 1e15, where doubles are coarser, not at all); where finite numbers are so
large that a score overflows, it is plus or minus infinity, and one that is no number counts as minus infinity (which of these a sum gives
whose terms overflow both ways is up to the arithmetic). Empty table: empty result. Extra columns aren't read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from catalogflow.session import fresh_path, staged


NONE = np.iinfo(np.int64).max


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row the k largest scores with their ids; ties by smaller id. Needs at least k columns."""
    kth = -np.partition(-scores, k - 1, axis=1)[:, k - 1]
    take = scores >= kth[:, None]
    for row in np.flatnonzero(take.sum(axis=1) > k):
        edge = np.flatnonzero(scores[row] == kth[row])
        spare = take[row].sum() - k
        take[row, edge[np.argsort(ids[row, edge])[len(edge) - spare :]]] = False
    return scores[take].reshape(-1, k), ids[take].reshape(-1, k)


def rounded(scores: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore", invalid="ignore"):
        out = np.where(np.abs(scores) < 1e15, np.round(scores, 9), scores)
    return np.nan_to_num(out, nan=-np.inf, posinf=np.inf, neginf=-np.inf)


class Lists:
    """A data block with its sorted lists."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, order: np.ndarray | None = None):
        self.ids, self.x = ids, vectors
        self.order = np.argsort(vectors, axis=0, kind="stable") if order is None else order
        self.value = np.take_along_axis(vectors, self.order, axis=0)

    def search(self, q_ids: np.ndarray, q: np.ndarray, k: int, first: int = 32, top: np.ndarray | None = None, who: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, int]:
        """(scores, ids) of q's k best rows other than themselves, -inf and NONE where there are fewer; and how many rows were scored.

        top, who: the k best so far, from other blocks; unchanged.
        """
        n = len(self.ids)
        top = np.full((len(q), k), -np.inf) if top is None else top.copy()
        who = np.full((len(q), k), NONE, np.int64) if who is None else who.copy()
        seen, live, at, step, scored = np.zeros(n, bool), np.arange(len(q)), 0, first, 0
        while len(live) and at < n:
            to = min(n, at + step)
            up, down = (q[live] > 0).any(axis=0), (q[live] < 0).any(axis=0)
            if (q[live] == 0).all(axis=1).any():  # every score of a zero query is 0: smaller ids may stand anywhere
                up[:], to = True, n
            fresh = np.zeros(n, bool)
            fresh[self.order[n - to : n - at][:, up].ravel()] = True
            fresh[self.order[at:to][:, down].ravel()] = True
            fresh &= ~seen
            new = np.flatnonzero(fresh)
            seen |= fresh
            if len(new):
                scored += len(new)
                with np.errstate(over="ignore", invalid="ignore"):
                    s = rounded(q[live] @ self.x[new].T)
                same = self.ids[new][None, :] == q_ids[live][:, None]
                s[same] = -np.inf
                own = np.where(same, NONE, self.ids[new][None, :])
                top[live], who[live] = best(np.hstack([top[live], s]), np.hstack([who[live], own]), k)
            if seen.all():
                break
            with np.errstate(over="ignore", invalid="ignore"):
                bound = np.where(q[live] > 0, q[live] * self.value[n - to], q[live] * self.value[to - 1]).sum(axis=1)
            live = live[~(slack(bound) < top[live].min(axis=1))]
            at, step = to, step * 2
        return top, who, scored


def slack(bound: np.ndarray) -> np.ndarray:
    """A bound with room for the rounding of sums; not a number stays so and bounds nothing."""
    with np.errstate(over="ignore", invalid="ignore"):
        return bound + 1e-9 + 1e-12 * np.abs(bound)


def box_bounds(q: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """queries x blocks: no row whose values lie between a block's ``low`` and ``high`` has a higher inner product."""
    with np.errstate(over="ignore", invalid="ignore"):
        return slack(np.maximum(q, 0) @ high.T + np.minimum(q, 0) @ low.T)


def top_k(vectors: DataFrame, k: int = 10, block_rows: int = 4096, group: int = 128, asked: Column | None = None, ask_rows: int = 1024) -> DataFrame:
    """(vec_id, rank, neighbour_id, score) for every row of ``vectors`` (vec_id, embedding), or those where ``asked``, among all rows.

    ask_rows: where few rows are asked, so many of them go through the blocks together, or their tasks would read far more than they score.
    """
    good = "vec_id is not null and embedding is not null and size(embedding) > 0 and forall(embedding, e -> e is not null and not isnan(e) and abs(e) < double('Infinity'))"
    rows = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).where(good)
    rows = rows.groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    shape = rows.groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if shape is None:
        return rows.select("vec_id", F.lit(0).alias("rank"), F.col("vec_id").alias("neighbour_id"), F.lit(0.0).alias("score")).where("false")
    dim, n = shape["d"], shape["count"]
    # rows of one direction lie together: the dimension with the largest value by magnitude, its sign, its value
    size = F.transform("embedding", lambda e: F.abs(e))
    lead = F.array_position(size, F.array_max(size)).cast("int")
    rows = rows.where(F.size("embedding") == dim).withColumn("lead", lead).withColumn("value", F.element_at("embedding", F.col("lead")))
    rows = staged(rows.repartitionByRange(max(1, -(-n // block_rows)), "lead", "value", "vec_id").sortWithinPartitions("lead", "value", "vec_id"), "topk-rows")

    def matrix(t):
        x = t.column("embedding")
        x = x.combine_chunks() if isinstance(x, pa.ChunkedArray) else x
        return t.column("vec_id").to_numpy(), x.flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)

    def block(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, block_rows):
                ids, x = matrix(batch.slice(i, block_rows))
                order = np.argsort(ids, kind="stable")
                lists = Lists(ids[order], np.ascontiguousarray(x[order]))
                yield pa.RecordBatch.from_pydict({
                    "ids": [lists.ids.astype("<i8").tobytes()], "x": [lists.x.astype("<f8").tobytes()], "places": [lists.order.astype("<i4").tobytes()],
                    "low": [lists.x.min(axis=0).tolist()], "high": [lists.x.max(axis=0).tolist()],
                }, schema=pa.schema([("ids", pa.binary()), ("x", pa.binary()), ("places", pa.binary()), ("low", pa.list_(pa.float64())), ("high", pa.list_(pa.float64()))]))

    spark = vectors.sparkSession
    path = fresh_path(spark, "topk-blocks")
    (
        rows.select("vec_id", "embedding").mapInArrow(block, "ids binary, x binary, places binary, low array<double>, high array<double>")
        .write.option("maxRecordsPerFile", 1).parquet(path)
    )

    def search(batches):
        from pyarrow import dataset, fs

        system, root = fs.FileSystem.from_uri(path)
        files = sorted(dataset.dataset(root, filesystem=system, format="parquet", exclude_invalid_files=True).files)
        edges = [pq.read_table(f, filesystem=system, columns=["low", "high"]) for f in files]
        files = [f for f, e in zip(files, edges) if e.num_rows]
        low, high = (np.array([e.column(c)[0].as_py() for e in edges if e.num_rows]).reshape(-1, dim) for c in ("low", "high"))
        held: dict[int, Lists] = {}

        def lists(b: int) -> Lists:
            if b not in held:
                if len(held) >= 8:
                    held.pop(next(iter(held)))
                t = pq.read_table(files[b], filesystem=system, columns=["ids", "x", "places"])
                ids, x, places = (np.frombuffer(t.column(c)[0].as_py(), kind) for c, kind in (("ids", "<i8"), ("x", "<f8"), ("places", "<i4")))
                held[b] = Lists(ids, x.reshape(-1, dim), places.reshape(-1, dim))
            return held[b]

        for batch in batches:
            for i in range(0, batch.num_rows, block_rows):
                qi, q = matrix(batch.slice(i, block_rows))
                top, who = np.full((len(q), k), -np.inf), np.full((len(q), k), NONE, np.int64)
                bound = box_bounds(q, low, high)
                # blocks in order of their best bound for these queries; each is opened once and passed to the groups that need it
                for b in np.argsort(-np.nan_to_num(bound, nan=np.inf).max(axis=0), kind="stable"):
                    need = np.flatnonzero(~(bound[:, b] < top.min(axis=1)))
                    for j in range(0, len(need), group):
                        some = need[j : j + group]
                        top[some], who[some], _ = lists(b).search(qi[some], q[some], k, top=top[some], who=who[some])
                order = np.lexsort((who, -top), axis=1)
                top, who = np.take_along_axis(top, order, axis=1), np.take_along_axis(who, order, axis=1)
                ok = who != NONE
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.repeat(qi, ok.sum(axis=1)), pa.int64()), pa.array(np.cumsum(ok, axis=1)[ok], pa.int32()), pa.array(who[ok], pa.int64()), pa.array(top[ok], pa.float64())],
                    ["vec_id", "rank", "neighbour_id", "score"],
                )

    asks = rows
    if asked is not None:
        asks = rows.where(asked)
        asks = asks.repartitionByRange(max(1, -(-asks.count() // ask_rows)), "lead", "value", "vec_id").sortWithinPartitions("lead", "value", "vec_id")
    return asks.select("vec_id", "embedding").mapInArrow(search, "vec_id bigint, rank int, neighbour_id bigint, score double")
