"""Order without a global sort in one task, and names that don't clash."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.session import broadcast_small, staged


def free_name(df: DataFrame, name: str) -> str:
    """``name``, with as many underscores as it takes to be no column of ``df`` (in any case of letters)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def running_total(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """``df`` with ``before``: the sum of ``value`` over the rows that come before in order of ``keys``.

    Rows are spread by ranges of the keys and summed range by range; only the ranges' sums, one row for each partition, are
    put in order in one task. Rows with equal keys lie in one range, and their order among each other is that of ``value``.
    ``df`` must not have columns range_, before or ahead_.
    """
    spread = staged(df.repartitionByRange(*keys).withColumn("range_", F.spark_partition_id()), "ordered")
    sums = spread.groupBy("range_").agg(F.sum(value).alias("all_"))
    ahead = Window.orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)
    sums = staged(sums.select("range_", F.coalesce(F.sum("all_").over(ahead), F.lit(0)).alias("ahead_")), "ordered-sums")
    own = Window.partitionBy("range_").orderBy(*keys, value).rowsBetween(Window.unboundedPreceding, -1)
    placed = spread.withColumn("before", F.coalesce(F.sum(value).over(own), F.lit(0)))
    return placed.join(broadcast_small(sums), "range_").withColumn("before", F.col("before") + F.col("ahead_")).drop("range_", "ahead_")
