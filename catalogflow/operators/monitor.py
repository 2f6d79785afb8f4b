"""Monitoring of visits and the survey's summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.session import shared_root  # noqa: F401


def at(ts: str = "ts") -> Column:
    """Event time as a timestamp, whatever the table stores."""
    return F.col(ts).cast("timestamp")


def traffic_by_period(events: DataFrame, period: str = "1 day") -> DataFrame:
    return events.groupBy(F.window(at(), period).alias("w"), "event_type").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"), F.round(F.sum("value"), 2).alias("value")).select(F.col("w.start").cast("date").alias("day"), "event_type", "n", "users", "value")


def rolling_users(events: DataFrame, days: int = 7) -> DataFrame:
    w = F.window(at(), f"{days} days", "1 day")
    return events.groupBy(w.alias("w")).agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n")).select(F.col("w.start").cast("date").alias("day"), "users", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(user_id, started, ended, n): visits that end after a pause of ``gap``."""
    s = events.groupBy("user_id", F.session_window(at(), gap).alias("s")).agg(F.count("*").alias("n"), F.max(at()).alias("ended"))
    return s.select("user_id", F.col("s.start").alias("started"), "ended", "n")


def traffic_alerts(daily: DataFrame, days: int = 7, width: float = 2.0) -> DataFrame:
    """Daily counts with the band of the days before: alert where a day leaves mean +/- width * deviation."""
    w = Window.partitionBy("event_type").orderBy("day").rowsBetween(-days, -1)
    out = daily.withColumn("mean", F.avg("n").over(w)).withColumn("sd", F.stddev_samp("n").over(w))
    return out.select("day", "event_type", "n", F.round("mean", 6).alias("mean"), F.coalesce(F.abs(F.col("n") - F.col("mean")) > width * F.col("sd"), F.lit(False)).alias("alert"))


def survey_rows(customer: DataFrame, orders: DataFrame, lineitem: DataFrame) -> DataFrame:
    """(profession, likelihood, artefact, grade): answers that stand in the order tables; some grades are missing."""
    j = lineitem.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return j.select(
        F.col("c_mktsegment").alias("profession"), F.expr("cast(substring(o_orderpriority, 1, 1) as int)").alias("likelihood"), F.col("l_returnflag").alias("artefact"),
        F.expr("case when l_linenumber % 6 = 0 then null else cast(ceil(l_quantity / 5) as int) end").alias("grade"),
    )
