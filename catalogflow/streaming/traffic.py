"""Structured Streaming twins of the monitoring methods."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from catalogflow.session import fresh_path


def event_stream(spark, sf_dir: str, name: str = "events", files: int = 1) -> DataFrame:
    """A stream over the stored events, its schema taken from the table."""
    import os

    path = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    if os.path.isdir(path):
        raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    else:
        raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def finish(stream: DataFrame, mode: str = "append", keys: list[str] = ()) -> DataFrame:
    """Run what is there to the end into a table in the shared folder and return it.

    Complete mode keeps the last batch's table. Update mode needs ``keys``: each batch is kept as it is, under its number, and the
    newest row of each key is returned.
    """
    if mode == "update" and not keys:
        raise ValueError("update mode needs the keys of a row")
    spark = stream.sparkSession
    out, check = fresh_path(spark, "stream-out"), fresh_path(spark, "stream-check")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", check).trigger(availableNow=True)
    if mode == "append":
        q = writer.format("parquet").option("path", out).start()
    elif mode == "complete":
        q = writer.foreachBatch(lambda b, n: b.write.mode("overwrite").parquet(out)).start()
    else:
        q = writer.foreachBatch(lambda b, n: b.write.mode("overwrite").parquet(f"{out}/batch_={n}")).start()
    q.awaitTermination()
    if mode != "update":
        return spark.read.schema(stream.schema).parquet(out)
    every = spark.read.parquet(out)
    return every.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "batch_").alias("x")).select("x.*")


def tumbling(events: DataFrame, period: str = "1 day", slide: str | None = None) -> DataFrame:
    w = F.window("ts", period, slide) if slide else F.window("ts", period)
    return events.withWatermark("ts", "10 minutes").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("value")).select(F.col("w.start").alias("started"), "event_type", "n", "value")


def session_counts(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.withWatermark("ts", "10 minutes").groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("started"), "n")


FUNNEL = {"view": 1, "click": 2, "purchase": 3}


def funnel(events: DataFrame) -> DataFrame:
    """(user_id, step): the furthest step of view -> click -> purchase that a user reached in order; state is one number per user.

    Events of a batch are taken in order of time and id; a batch's events come after all earlier batches'. Run it by
    ``finish(..., "update", ["user_id"])``. (The newer state API needs a state store that not every session is started with.)
    """
    def advance(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        step = state.get[0] if state.exists else 0
        for kind in pd.concat(list(batches)).sort_values(["ts", "event_id"])["event_type"]:
            if FUNNEL.get(kind) == step + 1:
                step += 1
        state.update((step,))
        yield pd.DataFrame({"user_id": [key[0]], "step": [step]})

    return events.groupBy("user_id").applyInPandasWithState(advance, "user_id bigint, step int", "step int", "update", "NoTimeout")
