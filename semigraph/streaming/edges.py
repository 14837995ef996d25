"""Edges of user and key from the events as a stream: windows with a watermark, degrees, components."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..algorithms.components import label_propagation
from ..plans.loop import ensure_folder


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def _folder(spark: SparkSession, name: str) -> str:
    ensure_folder(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/stream-{name}-{uuid.uuid4().hex}"


def _to_table(stream: DataFrame, spark: SparkSession, name: str) -> DataFrame:
    """Runs the stream over what is there and gives its appended rows, written to the shared folder."""
    out = _folder(spark, name)
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", _folder(spark, "state")).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def window_degrees(spark: SparkSession, sf_dir: str, width: str = "1 day", late: str = "2 days") -> DataFrame:
    """(day, user_id, n): events per user and day. Windows are final once the watermark has passed them; those it has
    not passed when the stream ends come with their counts so far, so no event that is in time is missing."""
    e = events_stream(spark, sf_dir).withWatermark("ts", late)
    counts = e.groupBy(F.window("ts", width).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    out = _folder(spark, "degrees")

    def keep(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={k}")

    rows = counts.select(F.col("w.start").alias("day"), "user_id", "n")
    rows.writeStream.foreachBatch(keep).option("checkpointLocation", _folder(spark, "state")).outputMode("update").trigger(availableNow=True).start().awaitTermination()
    changes = spark.read.schema(rows.schema.add("batch", "long")).parquet(out)
    return changes.groupBy("day", "user_id").agg(F.max_by("n", "batch").alias("n"))


def distinct_edges(spark: SparkSession, sf_dir: str, late: str = "60 days") -> DataFrame:
    """(user_id, k) pairs, repeats dropped within the watermark."""
    e = events_stream(spark, sf_dir).withWatermark("ts", late).select("ts", "user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return _to_table(e.dropDuplicatesWithinWatermark(["user_id", "k"]).select("user_id", "k"), spark, "edges")


def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, c_name): events joined with the static customer table."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_name")
    e = events_stream(spark, sf_dir).select("event_id", "user_id")
    return _to_table(e.join(c, e.user_id == c.c_custkey).select("event_id", "c_name"), spark, "joined")


def incremental_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, v): labels of users and keys, refreshed by each micro-batch from the labels before it."""
    store = {"labels": None, "edges": None}

    def refresh(batch: DataFrame, _: int) -> None:
        e = batch.select(F.col("user_id").alias("i"), (F.get_json_object("props", "$.k").cast("long") + 1_000_000).alias("j")).filter("j is not null").distinct()
        e = e.unionByName(e.select(F.col("j").alias("i"), F.col("i").alias("j")))
        known = store["edges"]
        edges = e if known is None else known.unionByName(e).distinct()
        fresh = edges.select("i").distinct()
        label = fresh.select("i", F.col("i").alias("v")) if store["labels"] is None else fresh.join(store["labels"], "i", "left").select("i", F.coalesce("v", "i").alias("v"))
        at = _folder(spark, "cc")
        edges.write.parquet(at + "/edges")
        store["edges"] = spark.read.parquet(at + "/edges")
        label_propagation(store["edges"], label).write.parquet(at + "/labels")
        store["labels"] = spark.read.parquet(at + "/labels")

    events_stream(spark, sf_dir).writeStream.foreachBatch(refresh).option("checkpointLocation", _folder(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return store["labels"]
