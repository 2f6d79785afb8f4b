"""Load: payloads, change plan, state, membership, search, streaming updates, enrichment."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def payloads(items: DataFrame, columns: list[str], key: str = "item_id") -> DataFrame:
    """(item_id, body, digest): the JSON that the portal gets."""
    return items.select(key, F.to_json(F.struct(*columns)).alias("body")).withColumn("digest", F.sha2("body", 256))


def item_payloads(items: DataFrame, triples: DataFrame, html: DataFrame, members: DataFrame) -> DataFrame:
    """(item_id, body, digest): metadata (each property with its values in order), layout and collection of an item as one JSON object.

    items: (item_id); triples: (item_id, property, ordinal, value); html: (item_id, html); members: (item_id, collection), one at most.
    """
    values = triples.groupBy("item_id", "property").agg(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", "value"))), lambda x: x["value"]).alias("values"))
    meta = values.groupBy("item_id").agg(F.array_sort(F.collect_list(F.struct("property", "values"))).alias("metadata"))
    j = items.select("item_id").join(meta, "item_id", "left").join(html, "item_id", "left").join(members, "item_id", "left")
    return payloads(j, ["metadata", "html", "collection"])


def search_items(items: DataFrame, labels: DataFrame | None = None, wanted: list[str] = (), region: str | None = None, catalog: int | None = None, text: str | None = None, top: int = 20) -> DataFrame:
    """(doc_id, score) of the first ``top`` items that meet every facet given; without labels in order of id, score 0.

    items: (doc_id, region, catalog_id, name, description); ``text`` must stand in the name or description, in any case of letters.
    """
    hit = items
    for column, value in (("region", region), ("catalog_id", catalog)):
        hit = hit if value is None else hit.where(F.col(column) == value)
    if text is not None:
        hit = hit.where(F.contains(F.lower(F.concat_ws(" ", "name", "description")), F.lit(text.lower())))
    if wanted:
        own = labels.where(F.col("label").isin(*wanted)).groupBy("doc_id").agg(F.countDistinct("label").alias("n"), F.sum("score").alias("score"))
        hit = hit.join(own.where(F.col("n") == len(set(wanted))), "doc_id")
    else:
        hit = hit.withColumn("score", F.lit(0).cast("bigint"))
    return hit.orderBy(F.desc("score"), "doc_id").limit(top).select("doc_id", "score")


def plan_sync(desired: DataFrame, current: DataFrame, key: str = "item_id") -> DataFrame:
    """(item_id, op): insert, update, delete or same, by digest. One full outer join."""
    a, b = desired.select(key, F.col("digest").alias("new_")), current.select(key, F.col("digest").alias("old_"))
    return a.join(b, key, "full").select(key, F.expr("case when old_ is null then 'insert' when new_ is null then 'delete' when new_ = old_ then 'same' else 'update' end").alias("op"))


def apply_sync(current: DataFrame, desired: DataFrame, plan: DataFrame, key: str = "item_id") -> DataFrame:
    """The new state; applying the plan of the result changes nothing."""
    kept = current.join(plan.where("op in ('update', 'delete')"), key, "left_anti")
    return kept.unionByName(desired.join(plan.where("op in ('insert', 'update')"), key, "left_semi"))


def check_membership(collections: DataFrame, exhibits: DataFrame, items: DataFrame) -> DataFrame:
    """(item_id, problem): items in more than one collection, and references to items that don't exist."""
    many = collections.groupBy("item_id").agg(F.countDistinct("collection").alias("n")).where("n > 1").select("item_id", F.lit("several collections").alias("problem"))
    lost = exhibits.select("item_id").distinct().join(items.select("item_id"), "item_id", "left_anti").select("item_id", F.lit("no such item").alias("problem"))
    return many.union(lost)


def search(labels: DataFrame, wanted: list[str], top: int = 20) -> DataFrame:
    """The first ``top`` items that carry all wanted labels, by the sum of their scores."""
    hit = labels.where(F.col("label").isin(*wanted)).groupBy("doc_id").agg(F.countDistinct("label").alias("n"), F.sum("score").alias("score"))
    return hit.where(F.col("n") == len(set(wanted))).orderBy(F.desc("score"), "doc_id").limit(top).select("doc_id", "score")


def owner_filter(updates: DataFrame, owners: DataFrame) -> DataFrame:
    """Updates by the producer that owns the item."""
    return updates.join(owners, ["item_id", "producer"], "left_semi")


def stream_load(updates: DataFrame, state_path: str, checkpoint: str, key: str = "item_id", buckets: int = 64):
    """Run the stream of (item_id, body, digest, ts) that is there into a state table: per item the row with the largest (ts, digest) wins.

    The state is ``buckets`` folders by a hash of the key. A batch reads and writes those only that it has items of, each as a new
    version (v = batch), so that late rows never replace newer ones and repeating a batch gives the same version; ``read_state`` takes the
    newest version of each bucket.
    """
    def one(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        new = batch.withColumn("bucket", F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int"))
        touched = [r["bucket"] for r in new.select("bucket").distinct().collect()]  # at most ``buckets``
        old = read_state(spark, state_path, batch.schema, before=number)
        both = new if old is None else new.unionByName(old.where(F.col("bucket").isin(touched)))
        best = both.groupBy(key).agg(F.max_by(F.struct(*both.columns), F.struct("ts", "digest")).alias("x")).select("x.*")
        best.write.mode("overwrite").partitionBy("bucket").parquet(f"{state_path}/v={number}")

    return updates.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_state(spark, state_path: str, schema, before: int | None = None) -> DataFrame | None:
    """The state's rows with their bucket: of each bucket the newest version (below ``before``); None where there is no version yet."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(state_path)
    system = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    names = [f.getPath().getName() for f in system.listStatus(path)] if system.exists(path) else []
    versions = sorted(int(n[2:]) for n in names if n.startswith("v=") and (before is None or int(n[2:]) < before))
    newest: dict[str, int] = {}
    for v in versions:
        for f in system.listStatus(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{state_path}/v={v}")):
            if f.getPath().getName().startswith("bucket="):
                newest[f.getPath().getName()] = v
    if not newest:
        return None
    full = schema.fromDDL(", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema.fields) + ", bucket int")
    return spark.read.schema(full).option("basePath", state_path).parquet(*[f"{state_path}/v={v}/{b}" for b, v in newest.items()]).select(*full.names)


def enrich(items: DataFrame, related: DataFrame, on: str) -> DataFrame:
    """Items with the sorted list of what relates to them."""
    per = related.groupBy(on).agg(F.array_sort(F.collect_set("related")).alias("related"))
    return items.join(per, on, "left")
