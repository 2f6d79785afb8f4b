"""Connected groups of an edge list."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.session import staged


def connected_groups(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 50) -> DataFrame:
    """(id, group_id) for every id on an edge; group_id is the smallest id that it is linked to.

    Alternates hooking all larger neighbours to the smallest neighbour with hooking the smaller ones
    (O(log^2 n) rounds); every round is written to the shared folder and one row (count, sum of hashes)
    comes to the driver to see whether anything changed. Loops, repeated and reversed edges, nulls are ignored.
    Raises if ``max_rounds`` don't suffice: unfinished groups are never returned.
    """
    e = (
        edges.select(F.col(a).alias("u"), F.col(b).alias("v"))
        .where("u is not null and v is not null and u <> v")
        .select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        .distinct()
    )
    e, before = staged(e, "edges"), None
    near = Window.partitionBy("u")
    for _ in range(max_rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = (
            both.withColumn("m", F.least(F.col("u"), F.min("v").over(near)))
            .where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        )
        small = (
            large.withColumn("m", F.min("v").over(near))
            .select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("x"))
            .select("x.*").where("u <> v").distinct()
        )
        e = staged(small, "edges")
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"groups still change after {max_rounds} rounds")
    members = e.select(F.col("u").alias("id"), F.col("v").alias("group_id"))
    return members.union(e.select(F.col("v").alias("id"), F.col("v").alias("group_id")).distinct())
