"""Operator 9: pack documents into windows of ``window`` tokens, online and in bounded space.

Documents are spread over partitions by a hash of their id, so that placement doesn't depend on how the table is
stored. In each partition ``open_windows`` windows are open; a document goes to the one that it fits best (least room
left), and where none fits the fullest is emitted and a new one opened. Longer documents give full windows and a rest,
which is placed like a document. At the end the windows left open, at most ``open_windows`` per partition, are merged in
the same way (fullest first, best fit, nothing is cut).

Defined cases: null or empty text has 0 tokens and is listed with window_id null; rows with null ``doc_id`` are spread by a hash of their text;
repeated rows are placed each on their own; ties in room go to the window opened first, ties in order to the smaller id.
Empty table: empty result. Extra columns aren't read.
"""

from __future__ import annotations

import bisect

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from catalogflow.llm.mixing import word_count
from catalogflow.session import staged

#: Rows without id are spread by their text.
HASH = "cast(conv(substring(md5(coalesce(cast(doc_id as string), concat('null/', text), 'null')), 1, 15), 16, 10) as bigint)"
SCHEMA = "doc_id bigint, piece int, part bigint, w bigint, start int, tokens int, used int, is_open boolean"


class BestFit:
    """Open windows, sorted by room left; ``add`` says in which window an item begins where, and which windows closed."""

    def __init__(self, window: int, keep: int | None):
        self.window, self.keep, self.room, self.next = window, keep, [], 0
        self.used: dict[int, int] = {}

    def add(self, n: int) -> tuple[int, int]:
        at = bisect.bisect_left(self.room, (n, -1))
        if at < len(self.room):
            left, w = self.room.pop(at)
        else:
            if self.keep is not None and len(self.room) >= self.keep:
                self.room.pop(0)
            left, w = self.window, self.next
            self.next += 1
        start = self.window - left
        self.used[w] = start + n
        if left > n:
            bisect.insort(self.room, (left - n, w))
        return w, start

    def open(self) -> set[int]:
        return {w for _, w in self.room}


def pack_partition(ids, sizes, window: int, keep: int) -> dict[str, list]:
    """Pieces of the documents in the order given."""
    bins, out = BestFit(window, keep), {k: [] for k in ("row", "piece", "w", "start", "tokens")}
    for row, n in enumerate(sizes):
        piece = 0
        while n > 0:
            take = min(window, n)
            if take == window:  # a full window never stays open
                w, start = bins.next, 0
                bins.next += 1
                bins.used[w] = window
            else:
                w, start = bins.add(take)
            for k, v in zip(out, (row, piece, w, start, take)):
                out[k].append(v)
            n, piece = n - take, piece + 1
    out["used"] = [bins.used[w] for w in out["w"]]
    live = bins.open()
    out["is_open"] = [w in live for w in out["w"]]
    return out


def pack(docs: DataFrame, window: int = 2048, open_windows: int = 32, tokens_per_partition: int = 8_000_000, leftovers_per_merge: int = 100_000, tokens: Column | None = None) -> DataFrame:
    """(doc_id, piece, window_id, start, tokens, used): where each piece of each document lies; used: tokens in its window."""
    t = word_count() if tokens is None else tokens
    light = staged(docs.select("doc_id", t.cast("bigint").alias("n"), F.expr(HASH).alias("h")), "pack-light")
    total = light.agg(F.sum("n")).first()[0] or 0
    parts = max(1, -(-int(total) // tokens_per_partition))

    def run(key, rows):
        rows = rows.sort_by([("h", "ascending"), ("doc_id", "ascending"), ("n", "ascending")])
        got = pack_partition(None, rows.column("n").to_numpy(), window, open_windows)
        at = pa.array(got["row"], pa.int64())
        one = len(at)
        return pa.table({
            "doc_id": rows.column("doc_id").take(at), "piece": pa.array(got["piece"], pa.int32()), "part": pa.array([key[0].as_py()] * one, pa.int64()),
            "w": pa.array(got["w"], pa.int64()), "start": pa.array(got["start"], pa.int32()), "tokens": pa.array(got["tokens"], pa.int32()),
            "used": pa.array(got["used"], pa.int32()), "is_open": pa.array(got["is_open"], pa.bool_()),
        })

    placed = staged(light.where("n > 0").groupBy((F.col("h") % parts).alias("part")).applyInArrow(run, SCHEMA), "pack-placed")
    left = placed.where("is_open").groupBy("part", "w").agg(F.max("used").alias("used"))
    merges = max(1, -(-parts * open_windows // leftovers_per_merge))

    def merge(key, rows):
        rows = rows.sort_by([("used", "descending"), ("part", "ascending"), ("w", "ascending")])
        bins = BestFit(window, None)
        where = [bins.add(n) for n in rows.column("used").to_pylist()]
        return pa.table({
            "part": rows.column("part"), "w": rows.column("w"), "m": pa.array([w for w, _ in where], pa.int64()), "shift": pa.array([s for _, s in where], pa.int32()),
            "m_used": pa.array([bins.used[w] for w, _ in where], pa.int32()), "g": pa.array([key[0].as_py()] * len(where), pa.int64()),
        })

    merged = left.groupBy((F.col("part") % merges).alias("g")).applyInArrow(merge, "part bigint, w bigint, m bigint, shift int, m_used int, g bigint")
    closed = placed.where("not is_open").select("doc_id", "piece", F.concat_ws("-", F.lit("p"), "part", "w").alias("window_id"), "start", "tokens", "used")
    joined = placed.where("is_open").join(merged, ["part", "w"]).select("doc_id", "piece", F.concat_ws("-", F.lit("m"), "g", "m").alias("window_id"), (F.col("start") + F.col("shift")).alias("start"), "tokens", F.col("m_used").alias("used"))
    none = light.where("n <= 0").select("doc_id", F.lit(0).alias("piece"), F.lit(None).cast("string").alias("window_id"), F.lit(0).alias("start"), F.lit(0).alias("tokens"), F.lit(0).alias("used"))
    return closed.union(joined).union(none)
